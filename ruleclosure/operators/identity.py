"""Identity: pair closure, canonical representatives, rewriting and expansion."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..durable import cut
from ..vocab import VOCAB, Vocabulary
from .closure import close_relation


def pair_closure(identity: DataFrame, vocab: Vocabulary = VOCAB) -> DataFrame:
    """All identity triples that transitivity adds, without x = x; quadratic in a clique's size."""
    edges = identity.select(F.lit(vocab.identity).alias("p"), F.col("s").alias("src"), F.col("o").alias("dst"))
    return close_relation(edges).where("src <> dst").select(F.col("src").alias("s"), "p", F.col("dst").alias("o"))


def canonicalize(pairs: DataFrame, max_rounds: int = 100) -> DataFrame:
    """term, rep: the smallest term of each clique, for pairs (s, o) read in both directions.

    Labels move to the smallest neighbour and jump to their label's label; rows stay linear in the number of terms.
    """
    both = pairs.select(F.col("s").alias("a"), F.col("o").alias("b")).union(pairs.select("o", "s")).where("a <> b").distinct()
    both = cut(both)
    label = cut(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("rep")).select(F.col("a").alias("term"), "rep"))
    for _ in range(max_rounds):
        near = both.join(label, F.col("b") == F.col("term")).groupBy("a").agg(F.min("rep").alias("low"))
        jump = label.select(F.col("term").alias("t2"), F.col("rep").alias("rep2"))
        step = label.join(near, F.col("term") == F.col("a"), "left").join(jump, F.col("rep") == F.col("t2"), "left")
        step = step.select("term", F.least("rep", F.coalesce("low", "rep"), F.coalesce("rep2", "rep")).alias("next"), "rep")
        step = cut(step)
        if step.where("next <> rep").isEmpty():
            return label
        label = step.select("term", F.col("next").alias("rep"))
    raise RuntimeError(f"labels did not settle in {max_rounds} rounds")


def rewrite(triples: DataFrame, reps: DataFrame) -> DataFrame:
    """Triples over representatives."""
    s, o = reps.select(F.col("term").alias("ts"), F.col("rep").alias("rs")), reps.select(F.col("term").alias("to_"), F.col("rep").alias("ro"))
    out = triples.join(s, F.col("s") == F.col("ts"), "left").join(o, F.col("o") == F.col("to_"), "left")
    return out.select(F.coalesce("rs", "s").alias("s"), "p", F.coalesce("ro", "o").alias("o")).distinct()


def expand_terms(triples: DataFrame, reps: DataFrame) -> DataFrame:
    """The triples that all members of the cliques have, from those over representatives."""
    s, o = reps.select(F.col("term").alias("ts"), F.col("rep").alias("rs")), reps.select(F.col("term").alias("to_"), F.col("rep").alias("ro"))
    out = triples.join(s, F.col("s") == F.col("rs"), "left").join(o, F.col("o") == F.col("ro"), "left")
    return out.select(F.coalesce("ts", "s").alias("s"), "p", F.coalesce("to_", "o").alias("o")).distinct()


def expand_pairs(reps: DataFrame, vocab: Vocabulary = VOCAB) -> DataFrame:
    """All identity triples from representatives, without x = x."""
    a, b = reps.select(F.col("term").alias("s"), "rep"), reps.select(F.col("term").alias("o"), "rep")
    return a.join(b, "rep").where("s <> o").select("s", F.lit(vocab.identity).alias("p"), "o")


def star_pairs(facts: DataFrame, key: str, term: str, vocab: Vocabulary = VOCAB) -> DataFrame:
    """Identity by linking each term of a (p, ``key``) group to the smallest: linear where all pairs are quadratic, with the
    same closure.  The smallest is found by a two-step aggregate, so a large group stays spread."""
    low = facts.groupBy("p", key).agg(F.min(term).alias("low"))
    met = facts.join(low, ["p", key]).where(F.col(term) != F.col("low"))
    return met.select(F.col("low").alias("s"), F.lit(vocab.identity).alias("p"), F.col(term).alias("o")).distinct()
