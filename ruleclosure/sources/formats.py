"""Triples in files: N-Triples text, CSV, JSON lines, Parquet by kind, bucketed tables, and a Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.terms import escape, parse_line, parse_ntriple
from ..triples import TRIPLE, classify
from ..vocab import VOCAB, Vocabulary
from ..shipping import by_value

by_value(__name__)

#: Lines whose terms are all IRIs need no Python.
_IRIS = r"^\s*<([^>]*)>\s*<([^>]*)>\s*<([^>]*)>\s*\.\s*$"


def write_ntriples(triples: DataFrame, path: str, literals: bool = False) -> None:
    """One line a triple; ``literals``: objects are written as literals."""
    o = F.concat(F.lit('"'), escape(F.col("o")), F.lit('"')) if literals else F.concat(F.lit("<"), "o", F.lit(">"))
    triples.select(F.concat(F.lit("<"), "s", F.lit("> <"), "p", F.lit("> "), o, F.lit(" ."))).write.mode("overwrite").text(path)


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """Lines of IRIs by pattern in generated code, others by the vectorised parser; lines that are neither are left out."""
    lines = spark.read.text(path)
    plain = lines.where(F.col("value").rlike(_IRIS)).select(*[F.regexp_extract("value", _IRIS, k).alias(c) for k, c in ((1, "s"), (2, "p"), (3, "o"))])
    other = lines.where(~F.col("value").rlike(_IRIS)).select(parse_ntriple("value").alias("t")).where("t.s is not null").select("t.s", "t.p", "t.o")
    return plain.union(other)


def write_by_kind(triples: DataFrame, path: str, vocab: Vocabulary = VOCAB) -> None:
    """Parquet partitioned by kind, sorted by predicate and subject within files, so scans prune by both."""
    classify(triples, vocab).repartition("kind", F.pmod(F.xxhash64("s"), F.lit(16))).sortWithinPartitions("kind", "p", "s").write.mode("overwrite").partitionBy("kind").parquet(path)


def read_by_kind(spark: SparkSession, path: str, kind: str | None = None) -> DataFrame:
    rows = spark.read.parquet(path)
    return (rows.where(F.col("kind") == kind) if kind else rows).select("s", "p", "o")


def write_bucketed(triples: DataFrame, table: str, buckets: int = 64, key: str = "s") -> None:
    """A table whose joins and duplicate removal on ``key`` need no exchange."""
    triples.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


class _Part(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.options = options

    def partitions(self):
        return [_Part(x) for x in self.options["paths"].split(",")]

    def read(self, partition):
        with open(partition.path, encoding="utf-8") as lines:
            for line in lines:
                t = parse_line(line)
                if t[0] is not None:
                    yield t


class NTriplesSource(DataSource):
    """``spark.read.format("ntriples").option("paths", "a.nt,b.nt")`` for files that workers can open; files in a store that
    only Spark reads go through :func:`read_ntriples`."""

    @classmethod
    def name(cls) -> str:
        return "ntriples"

    def schema(self) -> str:
        return TRIPLE

    def reader(self, schema):
        return _Reader(self.options)
