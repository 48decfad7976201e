"""Cutting lineage so that lost executors cost a re-read, not a re-run.

Everything iterative in this library ends a round with :func:`cut`.  It uses Spark's reliable
checkpoint, which writes to the folder all executors share; a local checkpoint would lose data with
its executor.
"""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager, suppress
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

#: Shuffle files of a statement go when it ends, not when the driver happens to collect its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
#: Files that a task may have open; beyond it, the task's rows are sorted.
WRITERS = "spark.sql.maxConcurrentOutputFileWriters"


def shared_folder(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; a temporary one only where the session names none and all runs on one machine."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir")
    current = sc._jsc.sc().getCheckpointDir()
    if current.isEmpty():
        if not named and not sc.master.startswith("local[") and sc.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="ruleclosure-checkpoint-"))
        current = sc._jsc.sc().getCheckpointDir()
    return current.get()


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared folder and continue from there.  Spark removes the files with the DataFrame where
    spark.cleaner.referenceTracking.cleanCheckpoints is set."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def forget(spark: SparkSession, folder: str) -> None:
    """Remove a folder of intermediate files."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


@contextmanager
def setting(spark: SparkSession, name: str, value: str):
    """A setting for the statements in this block."""
    before = spark.conf.get(name, None)
    with suppress(Exception):  # a Spark without this setting
        spark.conf.set(name, value)
    try:
        yield
    finally:
        with suppress(Exception):
            spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def tidy(spark: SparkSession):
    """Statements in this block leave no shuffle files."""
    return setting(spark, CLEANUP, "true")


@dataclass(frozen=True)
class Stored:
    """Rows in a folder of their own, as compressed columns."""

    frame: DataFrame
    folder: str
    rows: int

    def forget(self) -> None:
        forget(self.frame.sparkSession, self.folder)


def store(df: DataFrame, by: str | None = None) -> Stored:
    """As :func:`cut`, in columns: a triple takes a tenth of a checkpoint's bytes and scans skip what they don't read.  No garbage
    collection removes the files; who stored them forgets them.  by: a column of few values, each of which gets files of its own."""
    spark = df.sparkSession
    folder = f"{shared_folder(spark)}/rows-{uuid.uuid4().hex}"
    writer = df.write.option("compression", "zstd")
    with tidy(spark), setting(spark, WRITERS, "100"):
        # All of a task's files are open at once, which spares sorting it; small row groups bound what they hold.
        (writer if by is None else writer.partitionBy(by).option("parquet.block.size", str(4 << 20))).parquet(folder)
    frame = spark.read.schema(df.schema).parquet(folder)
    return Stored(frame, folder, frame.count())
