"""Rules one by one, closures by all methods, and the whole loop, against the in-memory fixpoint."""

import random

import pytest

from ruleclosure import baselines, match, measures
from ruleclosure.functions import terms
from ruleclosure.operators import identity
from ruleclosure.operators.closure import Limit, close_relation, closed_pairs, extend_relation
from ruleclosure.operators.firing import Schema, fire, property_rewrites
from ruleclosure.plans.orders import compose_plan
from ruleclosure.plans.rules import RULES, as_printed
from ruleclosure import reasoner
from ruleclosure.reasoner import Config, Run, reason, reason_incremental
from ruleclosure.triples import TRIPLE, class_shares, classify, collisions, decode, dictionary, encode, narrowed
from ruleclosure.vocab import VOCAB as V

OFF = Config(identity_mode="off")
LOOP = tuple(r for r in RULES if RULES[r].cls() in ("fact", "type", "schema"))


def frame(spark, rows):
    return spark.createDataFrame(list(rows), TRIPLE)


def triples(df):
    return {tuple(r) for r in df.select("s", "p", "o").collect()}


def line(text):
    return [tuple(x.split()) for x in text.split(";") if x.strip()]


#: rule, premises, consequences.
UNITS = [
    ("R3", f"x p y; x p y; a r b; p {V.sub_property} q; p {V.sub_property} q2", "x q y; x q2 y"),
    ("R4", f"x p y; z p y; p {V.domain} C", f"x {V.type} C; z {V.type} C"),
    ("R5", f"x p y; p {V.range} C; p {V.range} D", f"y {V.type} C; y {V.type} D"),
    ("R6", f"x {V.type} C; C {V.sub_class} D; E {V.sub_class} F", f"x {V.type} D"),
    ("O1", f"x p y; x p z; w p y; p {V.type} {V.functional}; x q k", f"y {V.identity} z; z {V.identity} y"),
    ("O2", f"x p y; w p y; w p z; p {V.type} {V.inverse_functional}", f"x {V.identity} w; w {V.identity} x"),
    ("O3", f"x p y; x q y; p {V.type} {V.symmetric}", "y p x"),
    ("O4", f"x p y; y p z; z p x; a q b; b q c; p {V.type} {V.transitive}", "x p z; y p x; z p y"),
    ("O5", f"x {V.identity} y", f"y {V.identity} x"),
    ("O6", f"x {V.identity} y; y {V.identity} z; y {V.identity} x", f"x {V.identity} z"),
    ("O7a", f"x p y; x q y; p {V.inverse} q", "y q x"),
    ("O7b", f"x p y; x q y; p {V.inverse} q", "y p x"),
    ("O8", f"A {V.type} {V.class_term}; A {V.identity} B; C {V.identity} D", f"A {V.sub_class} B"),
    ("O9", f"p {V.type} {V.property_term}; p {V.identity} q", f"p {V.sub_property} q"),
    ("O10", f"x p y; x {V.identity} u; y {V.identity} w", "u p y; x p w; u p w"),
    ("O10", f"x {V.type} C; x {V.identity} u; C {V.identity} D; p {V.type} {V.functional}; p {V.identity} q", f"u {V.type} C; x {V.type} D; u {V.type} D"),
    ("O11a", f"A {V.equivalent_class} B", f"A {V.sub_class} B"),
    ("O11b", f"A {V.equivalent_class} B", f"B {V.sub_class} A"),
    ("O11c", f"A {V.sub_class} B; B {V.sub_class} A; B {V.sub_class} C", f"A {V.equivalent_class} B; B {V.equivalent_class} A"),
    ("O12a", f"p {V.equivalent_property} q", f"p {V.sub_property} q"),
    ("O12b", f"p {V.equivalent_property} q", f"q {V.sub_property} p"),
    ("O12c", f"p {V.sub_property} q; q {V.sub_property} p", f"p {V.equivalent_property} q; q {V.equivalent_property} p"),
    ("R1", f"A {V.sub_class} B; B {V.sub_class} C; B {V.sub_class} A", f"A {V.sub_class} C"),
    ("R2", f"p {V.sub_property} q; q {V.sub_property} r", f"p {V.sub_property} r"),
    ("O13", f"C {V.has_value} v; C {V.on_property} p; x p v; z p w", f"x {V.type} C"),
    ("O14", f"C {V.has_value} v; C {V.on_property} p; C {V.on_property} p2; x {V.type} C", "x p v; x p2 v"),
    ("O15", f"C {V.some_values} D; C {V.on_property} p; x p y; y {V.type} D; z p k", f"x {V.type} C"),
    ("O16", f"C {V.all_values} D; C {V.all_values} E; C {V.on_property} p; x {V.type} C; x p y; z p k", f"y {V.type} D; y {V.type} E"),
]


@pytest.mark.parametrize(("rule", "given", "want"), UNITS, ids=[f"{u[0]}-{k}" for k, u in enumerate(UNITS)])
def test_each_rule(spark, rule, given, want):
    broadcast = len(rule) > 2
    split = classify(frame(spark, line(given)))
    parts = {k: split.where(f"kind = '{k}'").select("s", "p", "o") for k in ("type", "identity", "fact")}
    got = fire(rule, Schema(split.where("kind = 'schema'").select("s", "p", "o"), broadcast=broadcast), parts)
    assert triples(got) == set(line(want))
    assert baselines.local_fixpoint(set(line(given)), ids=(rule,)) >= set(line(want))


def test_printed_value_rules(spark):
    rules = as_printed()
    split = classify(frame(spark, line(f"C {V.has_value} v; C {V.on_property} p; x p C; y {V.type} C")))
    schema, parts = Schema(split.where("kind = 'schema'").select("s", "p", "o")), {k: split.where(f"kind = '{k}'").select("s", "p", "o") for k in ("type", "fact")}
    assert triples(fire(rules["O13"], schema, parts)) == {("x", V.type, "C")}
    assert triples(fire(rules["O14"], schema, parts)) == {("y", "p", "C")}


@pytest.mark.parametrize("method", ["doubling", "linear", "naive", "local", "grouped"])
def test_closure_methods_agree(spark, method):
    rng = random.Random(3)
    rows = {("p", f"n{rng.randrange(12)}", f"n{rng.randrange(12)}") for _ in range(18)}
    for n in (1, 2, 3, 4, 7, 8, 9, 16, 17):
        rows |= {(f"chain{n}", f"c{k}", f"c{k + 1}") for k in range(n)}
    got = close_relation(spark.createDataFrame(sorted(rows), "p string, src string, dst string"), method)
    assert {tuple(r) for r in got.collect()} == closed_pairs(rows)


def test_recursive_query_closes_acyclic_edges(spark):
    rows = [("p", f"c{k}", f"c{k + 1}") for k in range(12)]
    got = close_relation(spark.createDataFrame(rows, "p string, src string, dst string"), "sql")
    assert {tuple(r) for r in got.collect()} == closed_pairs(rows)


def test_recursive_query_loses_no_pair_of_a_deep_chain(spark):
    rows = [("deep", f"c{k}", f"c{k + 1}") for k in range(103)] + [("p", "a", "b")]
    got = close_relation(spark.createDataFrame(rows, "p string, src string, dst string"), "sql")
    assert {tuple(r) for r in got.collect()} == closed_pairs(rows)


@pytest.mark.parametrize("n", [98, 99, 100])
def test_recursive_query_at_the_last_level(spark, n):
    rows = [("p", f"c{k}", f"c{k + 1}") for k in range(n)]
    got = close_relation(spark.createDataFrame(rows, "p string, src string, dst string"), "sql")
    assert got.count() == n * (n + 1) // 2


def test_a_closed_relation_is_extended_from_new_edges(spark):
    rng = random.Random(8)
    for seed in range(3):
        rows = sorted({("p", f"n{rng.randrange(14)}", f"n{rng.randrange(14)}") for _ in range(16)} | {("c", f"c{k}", f"c{k + 1}") for k in range(9)})
        old = [x for x in rows if rng.random() < 0.6]
        df = lambda x: spark.createDataFrame(sorted(x), "p string, src string, dst string")
        known, gained, n = extend_relation(df(closed_pairs(old)), df(rows[:seed] + [x for x in rows if x not in old]))
        assert {tuple(r) for r in known.collect()} == closed_pairs(rows)
        assert {tuple(r) for r in gained.collect()} == closed_pairs(rows) - closed_pairs(old)
        assert n == len(set(rows) - closed_pairs(old))


@pytest.mark.parametrize("method", ["doubling", "linear"])
def test_closure_over_a_kept_partitioning(spark, method):
    rows = [("p", f"c{k}", f"c{k + 1}") for k in range(12)] + [("q", "a", "b"), ("q", "b", "a")]
    got = close_relation(spark.createDataFrame(rows, "p string, src string, dst string"), method, partitions=4)
    assert {tuple(r) for r in got.collect()} == closed_pairs(rows)


def test_dealt_edges_do_not_move_again(spark):
    from ruleclosure.durable import cut
    from ruleclosure.operators.closure import _compose, _dealt

    rows = spark.createDataFrame([("p", f"c{k}", f"c{k + 1}") for k in range(50)], "p string, src string, dst string")
    kept = spark.conf.get("spark.sql.autoBroadcastJoinThreshold"), spark.conf.get("spark.sql.adaptive.enabled")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        edges = cut(_dealt(rows, 4, "src"))
        plan = _compose(_dealt(edges, 4, "dst"), edges)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", kept[0])
        spark.conf.set("spark.sql.adaptive.enabled", kept[1])
    assert plan.count("Exchange") == 1


@pytest.mark.parametrize("method", ["doubling", "linear", "naive"])
def test_files_of_closure_rounds_go(spark, method):
    from pathlib import Path

    from ruleclosure.durable import shared_folder

    place, kept = Path(shared_folder(spark).removeprefix("file:")), []
    before = set(place.glob("*/")) | set(place.glob("rows-*"))
    edges = spark.createDataFrame([("p", f"n{k}", f"n{k + 1}") for k in range(6)], "p string, src string, dst string")
    found = close_relation(edges, method, kept=kept)
    assert found.count() == 21 and {x.name for x in set(place.glob("*")) - before} == {kept[0].folder.rsplit("/", 1)[1]}


def test_closure_respects_its_limit(spark):
    rows = [("p", f"c{k}", f"c{k + 1}") for k in range(30)]
    with pytest.raises(Limit):
        close_relation(spark.createDataFrame(rows, "p string, src string, dst string"), max_rows=50)


def random_graph(seed):
    rng = random.Random(seed)
    inst, props, classes = [f"i{k}" for k in range(6)], [f"p{k}" for k in range(4)], [f"C{k}" for k in range(4)]
    rows = set()
    for _ in range(9):
        rows.add((rng.choice(inst), rng.choice(props), rng.choice(inst)))
    for _ in range(4):
        rows.add((rng.choice(inst), V.type, rng.choice(classes)))
    makers = [
        lambda: (rng.choice(classes), V.sub_class, rng.choice(classes)),
        lambda: (rng.choice(props), V.sub_property, rng.choice(props)),
        lambda: (rng.choice(props), V.domain, rng.choice(classes)),
        lambda: (rng.choice(props), V.range, rng.choice(classes)),
        lambda: (rng.choice(props), V.inverse, rng.choice(props)),
        lambda: (rng.choice(props), V.type, rng.choice([V.symmetric, V.transitive, V.functional, V.inverse_functional])),
        lambda: (rng.choice(classes), V.equivalent_class, rng.choice(classes)),
        lambda: (rng.choice(props), V.equivalent_property, rng.choice(props)),
    ]
    for _ in range(6):
        rows.add(rng.choice(makers)())
    c = rng.choice(classes)
    rows |= {(c, V.on_property, rng.choice(props)), (c, rng.choice([V.some_values, V.all_values]), rng.choice(classes)), (rng.choice(classes), V.has_value, rng.choice(inst))}
    rows.add((rng.choice([x for x in rows if x[1] == V.has_value])[0], V.on_property, rng.choice(props)))
    return rows


def no_loops(rows):
    """Schema without x ~ x, which the engine leaves out."""
    return {t for t in rows if not (t[0] == t[2] and t[1] in (V.sub_class, V.sub_property, V.equivalent_class, V.equivalent_property, V.identity))}


@pytest.mark.parametrize("seed", range(4))
def test_loop_equals_the_fixpoint_in_memory(spark, seed):
    rows = random_graph(seed)
    want = baselines.local_fixpoint(rows, ids=LOOP)
    config = [OFF, Config(identity_mode="off", delta=False), Config(identity_mode="off", fused=True), Config(identity_mode="off", plan=compose_plan((1, 2, 0)))][seed % 4]
    got = triples(reason(frame(spark, rows), config).closure)
    assert no_loops(got) == no_loops(want)


def test_closed_chains_are_not_closed_again(spark):
    """The second round gives no edge to the closure: all new facts of the transitive property came from it."""
    rows = [(f"n{c}/{k}", "step", f"n{c}/{k + 1}") for c in range(4) for k in range(20)] + line(f"step {V.sub_property} reach; reach {V.type} {V.transitive}; reach {V.domain} C")
    run = Run(frame(spark, rows), OFF)
    run.loop()
    assert run.closings == [80] and run.known["fact"].where("p = 'reach'").count() == 4 * 210


def test_new_edges_of_later_rounds_are_closed(spark):
    """A value restriction gives an edge only after types are known."""
    rows = set(line(f"a p b; b p c; p {V.type} {V.transitive}; R {V.has_value} a; R {V.on_property} p; z {V.type} R; y p z"))
    run = Run(frame(spark, rows), OFF)
    run.loop()
    assert run.closings[1:] and triples(reason(frame(spark, rows), OFF).closure) == baselines.local_fixpoint(rows, ids=LOOP)


@pytest.mark.parametrize("seed", [20])
def test_results_meet_what_is_known_by_broadcast_and_by_aggregation(spark, seed, monkeypatch):
    rows = random_graph(seed)
    want = no_loops(baselines.local_fixpoint(rows, ids=LOOP))
    monkeypatch.setattr(reasoner, "FEW_RESULTS", 0)
    assert no_loops(triples(reason(frame(spark, rows), OFF).closure)) == want
    monkeypatch.setattr(reasoner, "MAX_NAMES", 0)
    assert no_loops(triples(reason(frame(spark, rows), OFF).closure)) == want


@pytest.mark.parametrize("seed", [21, 22, 23])
def test_results_of_one_rename_are_not_compared(spark, seed, monkeypatch):
    """Only where they neither repeat nor are known: the closure stays a set, and the same."""
    monkeypatch.setattr(reasoner, "FEW_RESULTS", 0)
    rows = random_graph(seed) | set(line(f"i1 own1 i2; i3 own1 i2; own1 {V.sub_property} own2; own2 {V.inverse} own3; own3 {V.sub_property} own4; own1 {V.sub_property} own4"))
    found = reason(frame(spark, rows), OFF).closure
    assert no_loops(triples(found)) == no_loops(baselines.local_fixpoint(rows, ids=LOOP)) and found.count() == found.distinct().count()
    run = Run(frame(spark, line(f"a p b; a k b; p {V.sub_property} q; q {V.sub_property} r; k {V.sub_property} r; q {V.inverse} t; p {V.sub_property} k")), OFF)
    # r has two sources, k is known, t comes from q alone.
    assert run.sole(["R3", "O7a"]) == {"q", "t"}


def test_rules_do_not_read_again_what_they_read_in_the_pass_before(spark):
    """The inverse rule, last of its stage, gave and read all of its own direction in the first pass; what types add it reads."""
    rows = line(f"a p b; p {V.inverse} q; R {V.has_value} v; R {V.on_property} p; x {V.type} R")
    run = Run(frame(spark, rows), OFF)
    run.loop()
    fired = [(n, rule) for n, stage, rule, *_ in run.stats if stage == "fact"]
    assert (2, "O7a") in fired and triples(run.known["fact"]) == set(line("a p b; b q a; x p v; v q x"))
    assert not run._touched("O7b", {"fact": {("q", "O7a")}}, frozenset({"O7a"})) and run._touched("O7b", {"fact": {("q", "O14")}}, frozenset({"O7a"}))


def test_files_of_a_stage_go_and_those_of_a_result_can(spark):
    from pathlib import Path

    from ruleclosure.durable import shared_folder

    place = Path(shared_folder(spark).removeprefix("file:"))
    before = set(place.glob("rows-*"))
    result = reason(frame(spark, random_graph(7)), OFF)
    assert len(set(place.glob("rows-*")) - before) == len(result.stored) and result.closure.count() > 0
    result.forget()
    assert set(place.glob("rows-*")) == before


@pytest.mark.parametrize("seed", [30])
def test_identity_fixpoint_equals_memory_on_random_graphs(spark, seed):
    rng = random.Random(seed)
    rows = {t for t in random_graph(seed) if t[2] not in (V.transitive,)} | {(f"i{rng.randrange(6)}", V.identity, f"i{rng.randrange(6)}")}
    assert no_loops(triples(reason(frame(spark, rows), Config(identity_mode="fixpoint")).closure)) == no_loops(baselines.local_fixpoint(rows))


def test_identity_fixpoint_and_final(spark):
    rows = set(line(f"a p b; a p c; c q d; e r c; p {V.type} {V.functional}; r {V.type} {V.symmetric}"))
    rows |= {("b", V.type, "K")}
    want = baselines.local_fixpoint(rows)
    assert ("c", V.type, "K") in want
    whole = triples(reason(frame(spark, rows), Config(identity_mode="fixpoint")).closure)
    final = triples(reason(frame(spark, rows), Config(identity_mode="final")).closure)
    off = triples(reason(frame(spark, rows), OFF).closure)
    assert whole == want and off <= final <= whole and ("b", V.identity, "c") in final
    again = triples(reason(frame(spark, whole), Config(identity_mode="fixpoint")).closure)
    assert again == whole


def test_canonical_mode_expands_to_the_pairs(spark):
    rows = set(line(f"a p b; a p c; a p d; c q x; p {V.type} {V.functional}"))
    r = reason(frame(spark, rows), Config(identity_mode="canonical"))
    pairs = triples(identity.expand_pairs(r.reps))
    assert pairs == {(x, V.identity, y) for x in "bcd" for y in "bcd" if x != y}
    assert ("b", "q", "x") in triples(r.closure)
    assert {("c", "q", "x"), ("d", "q", "x"), ("a", "p", "d")} <= triples(identity.expand_terms(r.closure, r.reps))


def test_canonical_links_are_linear(spark):
    rows = [("a", "p", f"o{k:03}") for k in range(300)] + line(f"p {V.type} {V.functional}")
    run = Run(frame(spark, rows), OFF)
    assert run.links().count() == 299
    r = reason(frame(spark, rows), Config(identity_mode="canonical"))
    assert r.reps.count() == 300 and triples(r.closure.where("p = 'p'")) == {("a", "p", "o000")}


@pytest.mark.parametrize("seed", [41])
def test_canonical_equals_the_fixpoint_over_representatives(spark, seed):
    """Rules run again over representatives: chains join, and cliques found later merge with earlier ones."""
    rng = random.Random(seed)
    rows = {t for t in random_graph(seed) if t[2] != V.transitive} | {(f"i{rng.randrange(6)}", V.identity, f"i{rng.randrange(6)}")}
    rows |= set(line(f"f {V.type} {V.functional}; g {V.type} {V.functional}; u f i0; u f i1; i0 g v; i1 g w; v p0 i2"))
    r = reason(frame(spark, rows), Config(identity_mode="canonical"))
    rep = {t.term: t.rep for t in r.reps.collect()}
    whole = baselines.local_fixpoint(rows)
    clique = {}
    for a, p, b in whole:
        if p == V.identity:
            clique.setdefault(a, {a}).add(b)
    assert {t: min(c) for t, c in clique.items() if len(c) > 1} == rep and rep["w"] == "v"
    schema = {*V.schema_predicates()}
    over = {(rep.get(s, s), p, rep.get(o, o)) for s, p, o in whole if p != V.identity and p not in schema and o not in V.schema_classes()}
    got = {t for t in triples(r.closure) if t[1] not in schema and t[2] not in V.schema_classes()}
    assert got == over


def test_rule_order_saves_rounds_in_the_worked_example(spark):
    rows = line(f"A {V.sub_class} B; B {V.equivalent_class} C; C {V.sub_class} D; x {V.type} A")
    r = reason(frame(spark, rows), OFF)
    want = {("x", V.type, c) for c in "BCD"}
    assert want <= triples(r.closure) and r.rounds <= 2


def test_feedback_from_types_to_facts_takes_another_round(spark):
    rows = line(f"x {V.type} C; C {V.has_value} v; C {V.on_property} p; p {V.sub_property} q")
    r = reason(frame(spark, rows), Config(identity_mode="off", provenance=True, count_raw=True))
    assert ("x", "q", "v") in triples(r.closure) and r.rounds >= 2
    assert [tuple(x) for x in match.why(r.derived, "x", "q", "v").collect()] == [("R3", 2)]
    assert sum(x[4] for x in r.stats) == 2 and all(x[3] >= x[4] for x in r.stats)


def test_a_fact_rule_that_reaches_schema_vocabulary(spark):
    rows = line(f"below {V.sub_property} {V.sub_class}; A below B; x {V.type} A")
    assert ("x", V.type, "B") in triples(reason(frame(spark, rows), OFF).closure)


def test_property_both_symmetric_and_inverse_ends(spark):
    rows = set(line(f"a p b; p {V.type} {V.symmetric}; p {V.inverse} q; q {V.inverse} q; p {V.type} {V.transitive}"))
    assert triples(reason(frame(spark, rows), OFF).closure) == baselines.local_fixpoint(rows, ids=LOOP)


def test_empty_inputs(spark):
    assert reason(frame(spark, []), Config()).closure.count() == 0
    assert triples(reason(frame(spark, [("a", "p", "b")]), Config()).closure) == {("a", "p", "b")}


def test_rewrites_equal_the_rules():
    for seed in range(200):
        rows = {t for t in random_graph(seed) if t[1] in (V.sub_property, V.inverse) or t[2] == V.symmetric} | {("a", f"p{k}", "b") for k in range(4)}
        want = {t for t in baselines.local_fixpoint(rows, ids=("R3", "O3", "O7a", "O7b")) if t[1].startswith("p") and t[1][1:].isdigit()}
        got = {("a", f"p{k}", "b") for k in range(4)}
        got |= {("b", q, "a") if swap else ("a", q, "b") for p, q, swap in property_rewrites(sorted(rows))}
        assert {t for t in got if t[1] in {f"p{k}" for k in range(4)}} == {t for t in want if {t[0], t[2]} == {"a", "b"}}


def test_schema_premises_join_alike_in_memory(spark):
    from ruleclosure.operators.firing import joined_locally, matched

    rows = sorted(random_graph(5))
    for r in RULES.values():
        atoms = [a for a in r.body if a.kind() == "schema"]
        if atoms:
            names, found = joined_locally(atoms, rows)
            if len(atoms) == 1:
                assert found == {tuple(x) for x in matched(atoms[0], frame(spark, rows)).select(*names).collect()}


def test_incremental_equals_from_scratch(spark):
    rows = sorted(random_graph(11))
    inst = [t for t in rows if t[1].startswith("p") and t[1][1:].isdigit()]
    late = set(inst[::2])
    first = reason(frame(spark, set(rows) - late), OFF)
    got = triples(reason_incremental(frame(spark, late), first).closure)
    assert no_loops(got) == no_loops(triples(reason(frame(spark, rows), OFF).closure))


def test_incremental_meets_derived_schema(spark):
    """What arrives may say, through a rule, that a class lies below another: old members follow."""
    rows = set(line(f"link {V.sub_property} {V.sub_class}; x {V.type} A; y {V.type} B; B p z"))
    late = {("A", "link", "B")}
    got = triples(reason_incremental(frame(spark, late), reason(frame(spark, rows), OFF)).closure)
    assert ("x", V.type, "B") in got and got == triples(reason(frame(spark, rows | late), OFF).closure)


def test_incremental_extends_the_closed_relation_and_identity(spark):
    chain = line(f"a p b; b p c; c p d; x p y; p {V.type} {V.transitive}; q {V.type} {V.functional}; k q l; l p m")
    late = {("d", "p", "x"), ("k", "q", "n")}
    got = triples(reason_incremental(frame(spark, late), reason(frame(spark, chain), OFF)).closure)
    assert got == triples(reason(frame(spark, set(chain) | late), OFF).closure)
    whole = Config(identity_mode="fixpoint")
    got = triples(reason_incremental(frame(spark, late), reason(frame(spark, chain), whole), whole).closure)
    assert got == baselines.local_fixpoint(set(chain) | late) and ("n", "p", "m") in got


def test_incremental_goes_on_from_the_files_of_the_closure(spark):
    """Three arrivals, edges that are already implied and a cycle among them: what is known is not stored again, and nothing comes twice."""
    rows = line(f"e {V.sub_property} p; p {V.type} {V.transitive}; p {V.domain} C; a e b; b e c; c e d")
    found = reason(frame(spark, rows), OFF)
    for late in ("d e f; f e g; a p d; a p g", "z e a; g p h", "h e f; b e c"):
        before, rows = found, rows + line(late)
        found = reason_incremental(frame(spark, line(late)), before, OFF)
        assert {x.folder for x in before.stored} <= {x.folder for x in found.stored}
        assert triples(found.closure) == baselines.local_fixpoint(set(rows), ids=LOOP) and found.closure.count() == len(triples(found.closure))


def test_representatives_close_only_what_moved(spark, monkeypatch):
    """Copies bring two chains together: the closure over representatives is the one from scratch, and all triples are read as new once."""
    rows = line(f"p {V.type} {V.transitive}; k {V.type} {V.inverse_functional}; p {V.domain} C; a p b; b p c1; c2 p d; d p e; c1 k x; c2 k x; c2 p b; c2 {V.type} K; u {V.type} K")
    whole, everything = [], Run.everything
    monkeypatch.setattr(Run, "everything", lambda self: whole.append(1) or everything(self))
    found = reason(frame(spark, rows), Config(identity_mode="canonical"))
    want = baselines.local_fixpoint({tuple("c1" if x == "c2" else x for x in t) for t in rows}, ids=LOOP)
    assert triples(found.closure) == want and found.closure.count() == len(want) and len(whole) == 1


def test_incremental_says_when_it_does_not_end(spark):
    rows = line(f"x {V.type} C; C {V.has_value} v; C {V.on_property} p; p {V.sub_property} q; q {V.domain} D; D {V.sub_class} E")
    first = reason(frame(spark, rows[1:]), OFF)
    with pytest.raises(RuntimeError):
        reason_incremental(frame(spark, rows[:1]), first, Config(identity_mode="off", max_rounds=1))


def test_answers_without_a_closure(spark):
    rows = line(
        f"p {V.sub_property} q; q {V.domain} C; r {V.inverse} q; r {V.range} D; S {V.has_value} w; S {V.on_property} q; S {V.sub_class} C; e {V.type} {V.symmetric};"
        f" a p b; c r d; f p w; g {V.type} S; m e n"
    )
    closed = reason(frame(spark, rows), OFF)
    schema = {tuple(r) for r in closed.schema.collect()}
    for text in (f"?x {V.type} C", f"?x {V.type} D", f"?x {V.type} S", "?x q ?y", "?x r ?y", "?x e ?y", "a q ?y"):
        want = match.bgp(closed.closure, [text])
        got = match.answer(frame(spark, rows), schema, text)
        if text in ("?x q ?y", f"?x {V.type} D"):  # what a type implies as a fact needs the closure
            want = want.where("x != 'g'")
        if text == "?x r ?y":
            want = want.where("y != 'g'")
        assert {tuple(x) for x in got.collect()} == {tuple(x) for x in want.collect()}, text


def test_copies_of_a_graph_close_apart(spark):
    from ruleclosure.triples import multiplied

    rows = set(line(f"a p b; b p c; x {V.type} K; p {V.type} {V.transitive}; K {V.sub_class} L; R {V.has_value} c; R {V.on_property} p"))
    df = multiplied(frame(spark, rows), 3, ["c", "R"])
    got = triples(df)
    assert ("a~2", "p", "b~2") in got and ("b~1", "p", "c") in got and ("x~1", V.type, "K") in got and len(got) == 4 + 3 * 3
    closure = triples(reason(df, OFF).closure)
    assert ("a~1", "p", "c") in closure and ("a~2", V.type, "R") in closure and ("x~2", V.type, "L") in closure and ("a~1", "p", "b~2") not in closure


def test_shuffled_bytes_and_mean_times(spark):
    rows = spark.range(20_000).selectExpr("id % 1000 k", "id")
    _, many = measures.shuffled(spark, lambda: rows.repartition(4, "id").write.format("noop").mode("overwrite").save())
    _, none = measures.shuffled(spark, lambda: rows.write.format("noop").mode("overwrite").save())
    assert many > 20_000 and none == 0
    assert measures.measure(lambda: rows, 2) > 0


def test_formats(spark, tmp_path):
    from ruleclosure.sources import formats

    rows = frame(spark, line("a p b; c q d"))
    name = "bucketed_triples_test"
    formats.write_bucketed(frame(spark, [(f"s{k % 50}", "p", f"o{k}") for k in range(500)]), name, 4)
    t = spark.table(name)
    kept = spark.conf.get("spark.sql.autoBroadcastJoinThreshold"), spark.conf.get("spark.sql.adaptive.enabled")
    try:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
        spark.conf.set("spark.sql.adaptive.enabled", "false")
        joined = t.join(t.groupBy("s").count(), "s")
        assert joined.count() == 500 and "Exchange" not in joined._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", kept[0])
        spark.conf.set("spark.sql.adaptive.enabled", kept[1])
        spark.sql(f"DROP TABLE {name}")
    path = tmp_path / "x.nt"
    path.write_text('<a> <p> <b> .\n<c> <q> "d" .\njunk\n')
    spark.dataSource.register(formats.NTriplesSource)
    assert triples(spark.read.format("ntriples").option("paths", str(path)).load()) == triples(rows)


def test_sql_functions(spark):
    from ruleclosure.sqlapi import register_functions

    register_functions(spark)
    assert spark.sql("SELECT parse_ntriple('<a> <b> <c> .').o AS o").first().o == "c"
    assert spark.sql("SELECT count(*) AS n FROM LATERAL expand_clique(array('a', 'b', 'c'))").first().n == 6


def test_a_cluster_needs_a_shared_folder():
    from types import SimpleNamespace

    from ruleclosure.durable import shared_folder

    empty = SimpleNamespace(getCheckpointDir=lambda: SimpleNamespace(isEmpty=lambda: True))
    context = SimpleNamespace(getConf=lambda: {}, master="spark://host:7077", _jsc=SimpleNamespace(sc=lambda: empty))
    with pytest.raises(RuntimeError):
        shared_folder(SimpleNamespace(sparkContext=context))


@pytest.mark.parametrize("f", ["fixed", "naive", "late", "staged", "subset"])
def test_baselines(spark, f):
    rows = random_graph(2) if f != "late" else set(line(f"a p b; b r c; p {V.sub_property} q; q {V.domain} C; C {V.sub_class} D"))
    want = no_loops(baselines.local_fixpoint(rows, ids=LOOP))
    g = frame(spark, rows)
    if f == "subset":
        got = triples(baselines.rule_subset(g, config=OFF).closure)
        assert no_loops(got) <= want
        return
    runs = {"fixed": lambda: baselines.fixed_order(g, baselines.shuffled(1), OFF).closure, "naive": lambda: baselines.naive(g), "late": lambda: baselines.late_dedup(g, 4), "staged": lambda: baselines.disk_staged(g)}
    assert no_loops(triples(runs[f]())) == want


def test_late_dedup_ends_at_the_fixpoint_or_says_so(spark):
    rows = {(f"n{k}", "p", f"n{k + 1}") for k in range(5)} | {("p", V.type, V.transitive)}
    g = frame(spark, rows)
    assert triples(baselines.late_dedup(g)) == baselines.local_fixpoint(rows, ids=LOOP)
    with pytest.raises(RuntimeError):
        baselines.late_dedup(g, 2)


def test_encoding_round_trip(spark):
    df = frame(spark, random_graph(1))
    d = dictionary(df)
    assert collisions(d).isEmpty() and triples(decode(encode(df), d)) == triples(df)


def test_shares_choose_the_effort(spark):
    shares = {r.kind: r.share for r in class_shares(frame(spark, line("a p b; a p c; x rdf:type C; a p d"))).collect()}
    assert shares == {"fact": 75.0, "type": 25.0}
    assert Config.from_shares(shares).identity_mode == "off" and Config.from_shares({"identity": 5.0}).identity_mode == "canonical"


def test_compare_and_fit(spark):
    a, b = frame(spark, line("a p b; c p d")), frame(spark, line("a p b; e p f"))
    missing, extra = measures.compare(a, b)
    assert triples(missing) == {("e", "p", "f")} and triples(extra) == {("c", "p", "d")}
    assert measures.improvement(8850, 7080) == (pytest.approx(20.0), pytest.approx(1.25))
    assert measures.scaling_fit(measures.published(spark)).first().r2 > 0.9


def test_plans_broadcast_the_schema_and_never_cross(spark):
    split = classify(frame(spark, line(UNITS[-1][1])))
    parts = {k: split.where(f"kind = '{k}'").select("s", "p", "o") for k in ("type", "fact")}
    out = fire("O16", Schema(split.where("kind = 'schema'").select("s", "p", "o")), parts)
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert plan.count("BroadcastHashJoin") >= 2 and "CartesianProduct" not in plan and "NestedLoop" not in plan


def test_ntriples_lines():
    assert terms.parse_line('<a> <b> "x\\n\\"y\\u00e9\\""@en .') == ("a", "b", 'x\n"yé"')
    assert terms.parse_line("<a> <b> <c> .") == ("a", "b", "c") and terms.parse_line("junk") == (None, None, None)


def test_large_results_lie_in_files_by_name(spark, monkeypatch):
    """A rule opens the files of the names that it can match; results stay the same."""
    monkeypatch.setattr(reasoner, "FEW_RESULTS", 0)
    rows = random_graph(31) | set(line(f"i1 own1 i2; own1 {V.sub_property} own2; own2 {V.domain} C; C {V.sub_class} D"))
    run = Run(frame(spark, rows), OFF)
    run.loop()
    for kind, name, column in (("fact", "own2", "p"), ("type", "D", "o")):
        some = narrowed(run.known[kind], {name}, column)
        scans = [x for x in some._jdf.queryExecution().executedPlan().toString().splitlines() if "FileScan" in x]
        assert scans and all("PartitionFilters: [isnotnull(b" in x or "PartitionFilters: [b" in x for x in scans)
        assert triples(some) == {t for t in triples(run.known[kind]) if t["spo".index(column)] == name} != set()
    assert no_loops(triples(reason(frame(spark, rows), OFF).closure)) == no_loops(baselines.local_fixpoint(rows, ids=LOOP))


def test_many_matches_of_one_triple_are_not_handed_on(spark, monkeypatch):
    """Twenty facts of a subject give its type once to the rules behind; with ``count_raw`` all derivations count."""
    rows = [("s", "p", f"o{k}") for k in range(20)] + line(f"p {V.domain} C; C {V.sub_class} D")
    kept = []
    monkeypatch.setattr(reasoner, "store", lambda *a, keep=reasoner.store: kept.append(keep(*a)) or kept[-1])
    found = triples(reason(frame(spark, rows), OFF).closure)
    assert ("s", V.type, "D") in found and max(x.rows for x in kept[1:]) <= 2
    stats = {r[2]: r[3] for r in reason(frame(spark, rows), Config(identity_mode="off", count_raw=True)).stats}
    assert stats["R4"] == 20


def test_a_rule_without_broadcast_moves_only_what_it_can_match(spark, tmp_path):
    rows = line(f"a p b; c q d; p {V.domain} C")
    frame(spark, rows).write.parquet(f"{tmp_path}/t")
    facts = spark.read.parquet(f"{tmp_path}/t")
    found = fire("R4", Schema(frame(spark, rows), broadcast=False, rows=frozenset(rows)), {"fact": facts})
    plan = found._jdf.queryExecution().executedPlan().toString()
    assert triples(found) == {("a", V.type, "C")} and "EqualTo(p,p)" in plan


def test_few_results_meet_only_known_triples_of_their_names(spark):
    """Without delta every round derives again what is known; what it compares does not grow with predicates that it did not derive."""
    run = Run(frame(spark, line(f"a p b; a q b; x {V.type} C; x {V.type} D; p {V.sub_property} q")), Config(identity_mode="off", delta=False))
    names = run._names_like(frame(spark, line(f"x q y; x new y; y {V.type} D; y {V.type} E")))
    assert names == ({"q"}, {"D"}) and triples(run._known(names)) == set(line(f"a q b; x {V.type} D"))


@pytest.mark.parametrize("method", ["doubling", "linear"])
def test_many_edges_close_over_numbers(spark, method, monkeypatch):
    """The same pairs, those with nulls included; rounds hold no terms, and all files that the result reads are handed over."""
    from ruleclosure.operators import closure

    rows = [("p", f"n{k}", f"n{k + 1}") for k in range(9)] + [("p", "n9", "n7"), ("q", "n1", "n0"), ("q", "n0", "a"), ("q", "a", None)]
    edges = spark.createDataFrame(rows, "p string, src string, dst string")
    want = {tuple(r) for r in close_relation(edges, method).collect()}
    monkeypatch.setattr(closure, "MANY_EDGES", 0)
    kept, stored = [], []
    monkeypatch.setattr(closure, "store", lambda *a, keep=closure.store: stored.append(keep(*a)) or stored[-1])
    found = close_relation(edges, method, kept=kept).collect()
    assert {tuple(r) for r in found} == want and len(found) == len(want) and ("q", "n1", "a") in want
    assert dict(stored[-1].frame.dtypes)["src"] == "bigint" and len(kept) == 2
    assert {tuple(r) for r in close_relation(edges, method, beyond=True).where("dst IS NOT NULL").collect()} == {r for r in want if r[2]} - set(rows)
