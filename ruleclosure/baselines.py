"""What the ordered closure is compared with.

The published comparisons name a reasoner with one fixed rule order and one with part of the rules, but print neither; both are
parameters here, and the defaults are stand-ins.
"""

from __future__ import annotations

import random
import uuid
from dataclasses import replace
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .durable import cut, forget, shared_folder
from .operators.firing import Schema, fire
from .plans.orders import fixed_plan
from .plans.rules import MERGING, RULES, Rule
from .reasoner import Config, ReasonResult, close_schema, reason, schema_rows
from .triples import TRIPLE, classify
from .vocab import VOCAB, Vocabulary

NUMERIC = tuple(RULES)
REVERSED = tuple(reversed(NUMERIC))
#: Stand-in for a reasoner with part of the rules.
SUBSET = ("R1", "R2", "R3", "R4", "R5", "R6", "O3", "O4", "O7a", "O7b", "O11a", "O11b", "O11c", "O12a", "O12b", "O12c")
RDFS = ("R1", "R2", "R3", "R4", "R5", "R6")


def shuffled(seed: int) -> tuple[str, ...]:
    order = list(NUMERIC)
    random.Random(seed).shuffle(order)
    return tuple(order)


def fixed_order(triples: DataFrame, order: tuple[str, ...] = NUMERIC, config: Config | None = None) -> ReasonResult:
    """The same loop with another order of rules in each stage.  The schema part keeps the order that completes it in one pass."""
    config = config or Config()
    plan = replace(fixed_plan(order), schema=config.plan.schema)
    return reason(triples, replace(config, plan=plan))


def type_before_fact(triples: DataFrame, config: Config | None = None) -> ReasonResult:
    config = config or Config()
    return reason(triples, replace(config, plan=replace(config.plan, loop=tuple(reversed(config.plan.loop)))))


def closure_first(triples: DataFrame, config: Config | None = None) -> ReasonResult:
    """The transitive rule first instead of last among the fact rules."""
    config = config or Config()
    fact, kind = config.plan.loop
    rules = ("O4", *[r for r in fact.rules if r != "O4"])
    return reason(triples, replace(config, plan=replace(config.plan, loop=(replace(fact, rules=rules), kind))))


def rule_subset(triples: DataFrame, ids: tuple[str, ...] = SUBSET, config: Config | None = None) -> ReasonResult:
    return reason(triples, replace(config or Config(), rules=ids))


def _all_rules(triples: DataFrame, rules: tuple[str, ...], config: Config):
    schema = Schema(triples.sparkSession.createDataFrame(sorted(close_schema(schema_rows(classify(triples).where("kind = 'schema'").select("s", "p", "o")), config)), TRIPLE))
    chosen = [r for r in rules if RULES[r].cls() in ("fact", "type")]
    return schema, chosen


def naive(triples: DataFrame, rules: tuple[str, ...] = NUMERIC, max_rounds: int = 100) -> DataFrame:
    """All fact and type rules each round on everything known, unordered, until nothing is new."""
    config = Config()
    known = cut(triples.distinct())
    schema, chosen = _all_rules(known, rules, config)
    known = cut(known.union(schema.triples).distinct())
    for _ in range(max_rounds):
        outs = _fire_all(known, schema, chosen)
        new = cut(outs.distinct().join(known, ["s", "p", "o"], "left_anti"))
        if new.isEmpty():
            return known
        known = cut(known.union(new))
    raise RuntimeError(f"no fixpoint in {max_rounds} rounds")


def _fire_all(known: DataFrame, schema: Schema, rules: list[str]) -> DataFrame:
    split = classify(known)
    parts = {k: split.where(F.col("kind") == k).select("s", "p", "o") for k in ("type", "fact")}
    outs = [x for r in rules if (x := fire(r, schema, parts)) is not None]
    return reduce(DataFrame.union, outs) if outs else known.limit(0)


def late_dedup(triples: DataFrame, max_rounds: int = 100, rules: tuple[str, ...] = NUMERIC) -> DataFrame:
    """All rules each round without removing repeats in between, until the distinct triples stop growing; repeats go at the end."""
    known = cut(triples.distinct())
    schema, chosen = _all_rules(known, rules, Config())
    known = known.union(schema.triples)
    before, parts = known.distinct().count(), int(triples.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    for _ in range(max_rounds):
        # Each union adds the partitions of all rules, which would multiply in every round.
        known = cut(known.union(_fire_all(known, schema, chosen)).repartition(parts))
        now = known.distinct().count()
        if now == before:
            return known.distinct()
        before = now
    raise RuntimeError(f"no fixpoint in {max_rounds} rounds")


def disk_staged(triples: DataFrame, folder: str | None = None, rules: tuple[str, ...] | None = None, max_rounds: int = 100) -> DataFrame:
    """Each rule's output goes to files and is read again before the next rule runs; the files go at the end."""
    spark = triples.sparkSession
    folder = folder or f"{shared_folder(spark)}/staged-{uuid.uuid4().hex}"
    plan = Config().plan
    order = rules or (*plan.loop[0].rules, *plan.loop[1].rules)
    known = cut(triples.distinct())
    schema, chosen = _all_rules(known, order, Config())
    known = known.union(schema.triples).distinct()
    known.write.parquet(f"{folder}/0")
    paths = [f"{folder}/0"]
    for number in range(1, max_rounds + 1):
        grown = False
        for rule in chosen:
            known = spark.read.parquet(*paths)
            out = _fire_all(known, schema, [rule]).distinct().join(known, ["s", "p", "o"], "left_anti")
            path = f"{folder}/{number}-{rule}"
            out.write.parquet(path)
            if not spark.read.parquet(path).isEmpty():
                paths.append(path)
                grown = True
        if not grown:
            closure = cut(spark.read.parquet(*paths))
            forget(spark, folder)
            return closure
    raise RuntimeError(f"no fixpoint in {max_rounds} rounds")


def local_fixpoint(rows: set[tuple[str, str, str]], rules: dict[str, Rule] = RULES, ids: tuple[str, ...] | None = None, vocab: Vocabulary = VOCAB, keep_reflexive: bool = False) -> set[tuple[str, str, str]]:
    """In memory on one machine, all rules until nothing is new: the oracle of the tests."""
    known = set(rows)
    chosen = [r for k, r in rules.items() if (ids is None or k in ids) and k not in (() if ids else MERGING)]
    words = {*vocab.schema_predicates(), vocab.type, vocab.identity}
    while True:
        new = set()
        by: dict[str, list] = {}
        for t in known:
            by.setdefault(t[1], []).append(t)
        for rule in chosen:
            found = [{}]
            if rule.id == "O10":
                same = [(s, o) for s, _, o in by.get(vocab.identity, ())]
                ids_of: dict[str, set[str]] = {}
                for a, b in same:
                    ids_of.setdefault(a, set()).add(b)
                for s, p, o in known:
                    if p not in words or p == vocab.type and o not in vocab.schema_classes():
                        new |= {(x, p, y) for x in (s, *ids_of.get(s, ())) for y in (o, *ids_of.get(o, ()))}
                continue
            for a in rule.body:
                longer = []
                for b in found:
                    p = b.get(a.p, a.p)
                    for t in known if p.startswith("?") else by.get(p, ()):
                        if a.p.startswith("?") and t[1] in words:
                            continue
                        c = dict(b)
                        if all(c.setdefault(x, y) == y if x.startswith("?") else x == y for x, y in zip(a.terms(), t, strict=True)):
                            longer.append(c)
                found = longer
            for b in found:
                if rule.differ and not keep_reflexive and b[rule.differ[0]] == b[rule.differ[1]]:
                    continue
                new.add(tuple(b.get(x, x) for x in rule.head.terms()))
        if new <= known:
            return known
        known |= new
