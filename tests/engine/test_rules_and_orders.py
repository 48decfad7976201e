"""The rule catalogue, dependency graphs and order selection."""

import pytest

from ruleclosure.plans import depgraph, orders
from ruleclosure.plans.rules import RULES, as_printed, classify_rules


def test_catalogue_has_27_rules_in_four_classes():
    assert {k: len(v) for k, v in classify_rules().items()} == {"fact": 5, "type": 7, "identity": 7, "schema": 8}
    assert classify_rules()["type"] == ["R4", "R5", "R6", "O13", "O14", "O15", "O16"]


@pytest.mark.parametrize(("source", "counts"), [("printed", (42, 79, 29, 46)), ("repaired", (42, 274, 73, 46))])
def test_chain_counts(source, counts):
    assert tuple(len(list(depgraph.enumerate_chains(depgraph.dependency_graph(c, source)))) for c in depgraph.CLASSES) == counts


def test_repairs_only_add():
    for c in depgraph.CLASSES:
        printed, repaired = depgraph.dependency_graph(c, "printed"), depgraph.dependency_graph(c, "repaired")
        assert all(printed[a] <= repaired[a] for a in printed)


@pytest.mark.parametrize(("cls", "n", "length"), [("fact", 12, 4), ("type", 48, 6), ("identity", 12, 5)])
def test_longest_chains(cls, n, length):
    found = depgraph.longest_chains(depgraph.dependency_graph(cls))
    assert (len(found), len(found[0])) == (n, length)


@pytest.mark.parametrize("cls", depgraph.CLASSES)
def test_selection_gives_the_chosen_orders(cls):
    assert orders.select_orders(cls) == sorted(orders.ORDERS[cls])


def test_counting_stops_at_its_budget_and_says_so():
    n, most, whole = depgraph.count_chains(depgraph.dependency_graph(source="derived"), 1000)
    assert n == 1000 and not whole and most > 1


def test_contraction_joins_groups():
    g = depgraph.contract(depgraph.dependency_graph("type", "printed"))
    assert set(g) == {"R4 R5 O13", "R6", "O14", "O15 O16"} and g["R6"] == {"O14", "O15 O16"}


def test_plans():
    plan = orders.compose_plan()
    assert plan.loop[0].rules == ("O3", "R3", "O7a", "O7b", "O4")
    assert plan.loop[1].rules == ("R4", "R5", "R6", "O14", "O13", "O15", "O16")
    assert plan.identity.rules == ("O1", "O10", "O2", "O6", "O5")
    assert orders.compose_plan((1, 2, 1)).loop[0].rules[0] == "O7a"
    fixed = orders.fixed_plan(tuple(RULES))
    assert fixed.loop[0].rules == ("R3", "O3", "O4", "O7a", "O7b")


def test_search_prefers_producers_first():
    g = depgraph.dependency_graph("schema", "printed")
    cost, order = orders.search_order(g, orders.CostModel(), 30)
    assert order.index("O11a") < order.index("R1") < order.index("O11c") and cost >= 0


def test_printed_wording_differs_in_the_value_rules():
    printed = as_printed()
    assert printed["O13"].body[2].o == "?c" and printed["O14"].head.o == "?c" and printed["O16"] == RULES["O16"]
