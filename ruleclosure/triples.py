"""Triples as DataFrames: kinds, shares, profiles and dictionary ids."""

from __future__ import annotations

import zlib

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .vocab import VOCAB, Vocabulary

TRIPLE = "s string, p string, o string"
KINDS = ("schema", "type", "identity", "fact")
#: Folders into which large intermediate files are dealt by name.
BUCKETS = 64
#: Names by which triples are narrowed; more are left to the joins.
MAX_NAMES = 2_000


def kind_of(vocab: Vocabulary = VOCAB, p: str = "p", o: str = "o") -> Column:
    """schema, type, identity or fact."""
    is_type = F.col(p) == vocab.type
    return (
        F.when(F.col(p).isin(vocab.schema_predicates()) | (is_type & F.col(o).isin(vocab.schema_classes())), "schema")
        .when(is_type, "type")
        .when(F.col(p) == vocab.identity, "identity")
        .otherwise("fact")
    )


def classify(triples: DataFrame, vocab: Vocabulary = VOCAB) -> DataFrame:
    """Triples with their ``kind``.  One scan; written with ``partitionBy("kind")`` it prunes later scans."""
    return triples.withColumn("kind", kind_of(vocab))


def placed(triples: DataFrame, vocab: Vocabulary = VOCAB) -> DataFrame:
    """Triples with ``b``, the bucket of their name: the class of types, the predicate of others."""
    name = F.when(F.col("p") == vocab.type, F.col("o")).otherwise(F.col("p"))
    return triples.withColumn("b", (F.crc32(name) % BUCKETS).cast("int"))


def narrowed(triples: DataFrame, names: set[str] | None, column: str = "p") -> DataFrame:
    """Triples whose ``column`` (``o``: of types alone) is one of ``names``; where they have ``b``, files of other buckets are not read.
    All, where there are too many names or None."""
    if names is None or len(names) > MAX_NAMES:
        return triples
    if "b" in triples.columns:
        triples = triples.where(F.col("b").isin(*sorted({zlib.crc32(x.encode()) % BUCKETS for x in names})))
    return triples.where(F.col(column).isin(*sorted(names)))


def class_shares(triples: DataFrame, vocab: Vocabulary = VOCAB, fraction: float | None = None, seed: int = 7) -> DataFrame:
    """kind, n and share (percent) of distinct triples; ``fraction`` looks at a sample, as suffices where data of all
    sizes have one character."""
    rows = triples.sample(fraction, seed) if fraction else triples
    counts = classify(rows.distinct(), vocab).groupBy("kind").agg(F.count("*").alias("n"))
    # Four rows at most stand in the window.
    return counts.select("kind", "n", F.round(100 * F.col("n") / F.sum("n").over(_all()), 3).alias("share"))


def _all():
    from pyspark.sql import Window

    return Window.partitionBy(F.lit(0))


def predicate_profile(triples: DataFrame) -> DataFrame:
    """p, n, subjects, objects: what skew to expect of each predicate."""
    return triples.groupBy("p").agg(F.count("*").alias("n"), F.approx_count_distinct("s").alias("subjects"), F.approx_count_distinct("o").alias("objects"))


def multiplied(triples: DataFrame, times: int, fixed: list[str], vocab: Vocabulary = VOCAB) -> DataFrame:
    """A graph ``times`` as large: copies of all instance triples over terms of their own.  Schema triples, classes and the terms in
    ``fixed`` (those the schema names) stay as they are."""
    copies = classify(triples, vocab).withColumn("k", F.explode(F.when(F.col("kind") == "schema", F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.lit(times - 1)))))
    own = lambda c: F.when((F.col("k") == 0) | F.col(c).isin(*fixed), F.col(c)).otherwise(F.concat(c, F.lit("~"), F.col("k").cast("string")))
    return copies.select(own("s").alias("s"), "p", F.when(F.col("kind") == "type", F.col("o")).otherwise(own("o")).alias("o"))


def dictionary(triples: DataFrame) -> DataFrame:
    """id, lex: 64-bit ids of all terms."""
    terms = triples.select(F.explode(F.array("s", "p", "o")).alias("lex")).distinct()
    return terms.select(F.xxhash64("lex").alias("id"), "lex")


def collisions(terms: DataFrame) -> DataFrame:
    """Ids that stand for more than one term.  An encoding is sound where this is empty."""
    return terms.groupBy("id").agg(F.count("*").alias("n")).where("n > 1")


def encode(triples: DataFrame) -> DataFrame:
    """Ids in place of terms: 24 bytes a triple, without a join."""
    return triples.select(*[F.xxhash64(c).alias(c) for c in ("s", "p", "o")])


def decode(encoded: DataFrame, terms: DataFrame) -> DataFrame:
    for c in ("s", "p", "o"):
        named = terms.select(F.col("id").alias(f"{c}_id"), F.col("lex").alias(f"{c}_lex"))
        encoded = encoded.join(named, F.col(c) == F.col(f"{c}_id"))
    return encoded.select(*[F.col(f"{c}_lex").alias(c) for c in ("s", "p", "o")])
