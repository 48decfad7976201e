"""Graph patterns over a closure, and answering them from the schema alone."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .operators.firing import BROADCAST_ROWS, matched, property_rewrites, variable
from .plans.rules import Atom
from .vocab import VOCAB, Vocabulary


def pattern(text: str) -> Atom:
    """``"?x p ?y"`` as an atom."""
    s, p, o = text.split(" ", 2)
    return Atom(s, p, o)


def _joined(left: DataFrame, right: DataFrame, how: str = "inner") -> DataFrame:
    shared = [c for c in left.columns if c in right.columns]
    if not shared:
        raise ValueError("a pattern must share a variable with those before it")
    return left.join(right, shared, how)


def bgp(triples: DataFrame, patterns: list[str], optional: list[str] = (), distinct: bool = True) -> DataFrame:
    """Bindings (columns named like variables) of a conjunction of patterns, left-joined with optional ones."""
    rows = reduce(_joined, [matched(pattern(p), triples) for p in patterns])
    for p in optional:
        rows = _joined(rows, matched(pattern(p), triples), "left")
    rows = rows.toDF(*[c.removeprefix("v_") for c in rows.columns])
    return rows.distinct() if distinct else rows


def ask(triples: DataFrame, patterns: list[str]) -> bool:
    return not bgp(triples, patterns, distinct=False).isEmpty()


def construct(rows: DataFrame, template: list[str]) -> DataFrame:
    """Triples from bindings."""
    out = []
    for t in template:
        a = pattern(t)
        out.append(rows.select(*[F.col(x[1:]).alias(c) if x.startswith("?") else F.lit(x).alias(c) for c, x in zip("spo", a.terms(), strict=True)]))
    return reduce(DataFrame.union, out).distinct()


def rewrite(triples: DataFrame, schema: DataFrame, text: str, vocab: Vocabulary = VOCAB) -> DataFrame:
    """Bindings of one pattern over triples that were not closed: the closed schema says which classes or properties
    imply the one asked for (instances of subclasses, facts of subproperties)."""
    a = pattern(text)
    edge, column = (vocab.sub_class, "o") if a.p == vocab.type else (vocab.sub_property, "p")
    wanted = a.o if column == "o" else a.p
    below = schema.where((F.col("p") == edge) & (F.col("o") == wanted)).select(F.col("s").alias("name"))
    names = _small(below.union(below.sparkSession.createDataFrame([(wanted,)], "name string")).distinct())
    source = triples.where(F.col("p") == vocab.type) if column == "o" else triples
    met = source.join(names, F.col(column) == F.col("name"), "left_semi")
    places = [(c, t) for c, t in zip("spo", a.terms(), strict=True) if t.startswith("?")]
    return met.select(*[F.col(c).alias(variable(t).removeprefix("v_")) for c, t in places]).distinct()


def _small(rows: DataFrame) -> DataFrame:
    """``rows`` with a broadcast hint if there are few enough."""
    return F.broadcast(rows) if rows.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else rows


def answer(triples: DataFrame, schema: set[tuple[str, str, str]], text: str, vocab: Vocabulary = VOCAB) -> DataFrame:
    """Bindings of one pattern over triples that were not closed, the rest done at query time from the closed schema (held by the
    driver, as in reasoning).

    ``?x p ?y``: facts of all properties that super-properties, inverses and symmetry turn into p.  ``?x rdf:type C``: members of C's
    subclasses, ends of facts whose property has one of them as domain or range, and subjects that hold the required value of one of
    them.  Transitive properties, identity, facts that follow from a type, and rules of two instance premises need the closure.
    """
    a, spark, v = pattern(text), triples.sparkSession, vocab
    pairs = lambda p: {(s, o) for s, q, o in schema if q == p}
    rewrites = property_rewrites(sorted(schema), v)

    def facts(wanted: set[str]) -> DataFrame:
        """s, q, o: facts of the wanted properties."""
        rows = {(q, q, False) for q in wanted} | {(p, q, swap) for p, q, swap in rewrites if q in wanted}
        side = _small(spark.createDataFrame(sorted(rows), "p string, q string, swap boolean"))
        met = triples.join(side, "p")
        return met.select(F.when(F.col("swap"), F.col("o")).otherwise(F.col("s")).alias("s"), "q", F.when(F.col("swap"), F.col("s")).otherwise(F.col("o")).alias("o"))

    if a.p != v.type:
        found = facts({a.p}).select("s", F.lit(a.p).alias("p"), "o")
    else:
        classes = {a.o} | {s for s, o in pairs(v.sub_class) if o == a.o}
        names = _small(spark.createDataFrame([(c,) for c in sorted(classes)], "o string"))
        parts = [triples.where(F.col("p") == v.type).join(names, "o", "left_semi").select("s")]
        for edge, end in ((v.domain, "s"), (v.range, "o")):
            if wanted := {p for p, c in pairs(edge) if c in classes}:
                parts.append(facts(wanted).select(F.col(end).alias("s")))
        values = {(p, w) for c, w in pairs(v.has_value) if c in classes for d, p in pairs(v.on_property) if d == c}
        if values:
            held = _small(spark.createDataFrame(sorted(values), "q string, o string"))
            parts.append(facts({p for p, _ in values}).join(held, ["q", "o"], "left_semi").select("s"))
        found = reduce(DataFrame.union, parts).select("s", F.lit(v.type).alias("p"), F.lit(a.o).alias("o"))
    rows = matched(a, found)
    return rows.toDF(*[c.removeprefix("v_") for c in rows.columns]).distinct()


def why(derived: DataFrame, s: str, p: str, o: str) -> DataFrame:
    """rule and round that first gave a triple, from a result with provenance."""
    return derived.where((F.col("s") == s) & (F.col("p") == p) & (F.col("o") == o)).select("rule", "round")
