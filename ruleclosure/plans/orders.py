"""Choosing rule orders from chains, and composing them into a plan."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from .depgraph import CLASSES, Graph, contract, dependency_graph, enumerate_chains, longest_chains
from .rules import RULES

#: The orders that the selection must arrive at.  Fixed values.
ORDERS: dict[str, list[tuple[str, ...]]] = {
    "fact": [("O3", "R3", "O7", "O4"), ("O7", "R3", "O3", "O4")],
    "type": [
        ("R4", "R6", "O14", "O13", "O15", "O16"),
        ("R4", "R6", "O14", "O13", "O16", "O15"),
        ("R5", "R6", "O14", "O13", "O15", "O16"),
        ("R5", "R6", "O14", "O13", "O16", "O15"),
    ],
    "schema": [("O11a", "O11b", "R1", "O11c"), ("O12a", "O12b", "R2", "O12c")],
    "identity": [("O1", "O10", "O2", "O6", "O5"), ("O2", "O10", "O1", "O6", "O5")],
}
#: Rules that run where one of them stands in a chain.
TOGETHER = {"R4": ("R4", "R5"), "R5": ("R4", "R5"), "O7": ("O7a", "O7b")}


def _readers(rule: str) -> int:
    return RULES[rule].instance_premises() if rule in RULES else 1


def select_orders(cls: str, graph: Graph | None = None) -> list[tuple[str, ...]]:
    """The longest chains of a class, thinned by its tie-breaks.

    fact: the closure of transitive properties, which makes most, comes last.  type: rules that read two instance
    triples come last, and superclasses follow the domain and range group at once.  identity: symmetry comes last, as it
    adds nothing others need, and producers come before transitivity.  schema: each part starts at the asserted
    equivalences; both equivalence directions are one step.
    """
    graph = graph or dependency_graph(cls)
    if cls == "schema":
        # Each part is a ring of equivalences, closure and mutual pairs, entered where the equivalences are asserted.
        return sorted(tuple(" ".join(c).split()) for c in longest_chains(contract(graph)) if c[0] in ("O11a O11b", "O12a O12b"))
    chains = longest_chains(graph)
    if cls == "fact":
        chains = [c for c in chains if c[-1] == "O4"]
    if cls == "type":
        heavy = [c for c in chains if all(_readers(a) <= _readers(b) for a, b in zip(c, c[1:], strict=False))]
        chains = [c for c in heavy if c[1] == "R6" and c[0] in ("R4", "R5")]
    if cls == "identity":
        chains = [c for c in chains if c[-1] == "O5" and max(c.index("O1"), c.index("O2")) < c.index("O6")]
    return sorted(chains)


@dataclass(frozen=True)
class Stage:
    cls: str
    rules: tuple[str, ...]


@dataclass(frozen=True)
class Plan:
    """Schema once; fact and type in turn until neither finds anything; identity."""

    schema: Stage
    loop: tuple[Stage, ...]
    identity: Stage


def expand(order: tuple[str, ...]) -> tuple[str, ...]:
    """Rules in the order's sequence, groups written out, each once."""
    return tuple(dict.fromkeys(r for x in order for r in TOGETHER.get(x, (x,))))


def compose_plan(choice: tuple[int, int, int] = (0, 0, 0), orders: dict[str, list[tuple[str, ...]]] = ORDERS) -> Plan:
    """A plan from one fact, one type and one identity order; the two schema orders concern different triples and both run."""
    fact, kind, same = choice
    schema = tuple(r for order in orders["schema"] for r in order)
    return Plan(
        Stage("schema", schema),
        (Stage("fact", expand(orders["fact"][fact])), Stage("type", expand(orders["type"][kind]))),
        Stage("identity", expand(orders["identity"][same])),
    )


def fixed_plan(order: tuple[str, ...], loop: tuple[str, ...] = ("fact", "type")) -> Plan:
    """A plan that runs each class's rules in the sequence in which ``order`` names them."""
    by = {c: Stage(c, tuple(r for r in order if RULES[r].cls() == c)) for c in CLASSES}
    return Plan(by["schema"], tuple(by[c] for c in loop), by["identity"])


@dataclass
class CostModel:
    """Estimated cost of a chain from the number of triples each rule was seen to derive: a rule that runs before one it
    feeds saves that rule's rows another round."""

    yields: dict[str, float] = field(default_factory=dict)
    default: float = 1.0

    def cost(self, order: tuple[str, ...], graph: Graph) -> float:
        late = 0.0
        for k, a in enumerate(order):
            late += sum(self.yields.get(a, self.default) for b in order[:k] if b in graph.get(a, ()))
        return late + sum(self.yields.get(a, self.default) for a in graph if a not in order)


def search_order(graph: Graph, model: CostModel, beam: int = 50, score: Callable[[tuple[str, ...]], float] | None = None) -> tuple[float, tuple[str, ...]]:
    """The cheapest order over all rules of a graph that a beam search finds, by recorded yields."""
    score = score or (lambda order: model.cost(order, graph))
    paths: list[tuple[str, ...]] = [()]
    for _ in graph:
        longer = {(*p, r) for p in paths for r in graph if r not in p}
        paths = sorted(longer, key=lambda p: (score(p), p))[:beam]
    return score(paths[0]), paths[0]


def chain_rows(cls: str, source: str = "repaired") -> list[tuple[str, list[str], int]]:
    """(class, path, length) of each chain."""
    return [(cls, list(c), len(c)) for c in enumerate_chains(dependency_graph(cls, source))]
