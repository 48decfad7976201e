"""Rules on streams.

Rules with one instance premise are joins of the stream with the static schema.  Two instance premises meet in a
stream-stream join within a time bound.  Closures, which need everything known, merge each micro-batch into what is stored.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..durable import cut, forget, shared_folder
from ..operators.firing import BROADCAST_ROWS, Schema, fire
from ..plans.rules import RULES
from ..reasoner import Config, ReasonResult, reason_incremental
from ..shipping import by_value

by_value(__name__)

#: Rules that read one instance triple.
STATELESS = ("R3", "R4", "R5", "R6", "O3", "O7a", "O7b", "O13", "O14")


def table_stream(spark: SparkSession, sf_dir: str, table: str, files_per_batch: int | None = None) -> DataFrame:
    """The table's files as a stream; time stamps become instants, as watermarks need."""
    return file_stream(spark, f"{sf_dir}/{table}.parquet", files_per_batch)


def file_stream(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    schema = spark.read.parquet(path).schema
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    rows = reader.parquet(f"{path}*")
    return rows.withColumns({f.name: F.col(f.name).cast("timestamp") for f in schema.fields if f.dataType.typeName() == "timestamp_ntz"})


def drain(stream: DataFrame, mode: str = "append", progress: list | None = None) -> DataFrame:
    """Run a stream over what is there and return the result, cut into the shared folder; the stream's own files go.

    append goes to a file sink, exactly once; complete keeps the last batch's table.  progress: takes what the query reports of each
    batch.
    """
    spark = stream.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True)
    last = {}

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out-{number}")
        last["n"] = number

    if mode == "append":
        query = writer.format("parquet").outputMode("append").start(f"{folder}/out")
    else:
        query = writer.outputMode(mode).foreachBatch(keep).start()
    query.awaitTermination()
    if progress is not None:
        progress += query.recentProgress
    place = f"{folder}/out" if mode == "append" else f"{folder}/out-{last['n']}"
    result = cut(spark.read.schema(stream.schema).parquet(place))
    forget(spark, folder)
    return result


def dropped_late(progress: list) -> int:
    """Rows that came behind the watermark, by what a query reported of its batches."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in progress for op in p["stateOperators"])


def stateless(stream: DataFrame, schema: Schema, rules: tuple[str, ...] = STATELESS) -> DataFrame:
    """What each rule derives from a stream of triples (append; repeats included)."""
    vocab = schema.vocab
    parts = {"type": stream.where(F.col("p") == vocab.type), "fact": stream.where(~F.col("p").isin(vocab.type, vocab.identity, *vocab.schema_predicates()))}
    outs = [x for r in rules if (x := fire(RULES[r], schema, parts)) is not None]
    return reduce(DataFrame.union, outs)


def joined_within(facts: DataFrame, types: DataFrame, schema: Schema, rule: str, bound: str = "1 hour") -> DataFrame:
    """O15 or O16 on two streams of triples with a column ``ts``, within ``bound`` of each other."""
    vocab, r = schema.vocab, RULES[rule]
    rows, n = schema.bindings(r)
    names = rows.toDF(*[c.removeprefix("v_") for c in rows.columns])
    names = F.broadcast(names) if n <= BROADCAST_ROWS else names
    filler, link = ("f", "o") if rule == "O15" else ("c", "s")
    f = facts.withWatermark("ts", bound).join(names.withColumnRenamed("p", "q"), F.col("p") == F.col("q"))
    f = f.select(F.col("s").alias("fs"), F.col("o").alias("fo"), "c", "f", F.col("ts").alias("ft"))
    t = types.withWatermark("ts", bound).where(F.col("p") == vocab.type).select(F.col("s").alias("member"), F.col("o").alias("cls"), F.col("ts").alias("tt"))
    met = f.join(t, (F.col(f"f{link}") == F.col("member")) & (F.col(filler) == F.col("cls")) & F.expr(f"tt BETWEEN ft - INTERVAL {bound} AND ft + INTERVAL {bound}"))
    subject, klass = ("fs", "c") if rule == "O15" else ("fo", "f")
    return met.select(F.col(subject).alias("s"), F.lit(vocab.type).alias("p"), F.col(klass).alias("o"))


def first_sightings(stream: DataFrame, delay: str = "10 minutes") -> DataFrame:
    """Triples (with ``ts``) seen for the first time within the watermark."""
    return stream.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["s", "p", "o"])


def next_events(events: DataFrame) -> DataFrame:
    """nextEvent edges per user; the state is the user's last event."""

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState):
        last = state.get[0] if state.exists else None
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        out = []
        for e in rows["event_id"].tolist():
            if last is not None:
                out.append((f"event/{last}", "nextEvent", f"event/{e}"))
            last = e
        if last is not None:
            state.update((int(last),))
        yield pd.DataFrame(out, columns=["s", "p", "o"])

    return (
        events.select("user_id", "ts", "event_id")
        .groupBy("user_id")
        .applyInPandasWithState(step, "s string, p string, o string", "last long", "append", GroupStateTimeout.NoTimeout)
    )


def windowed(stream: DataFrame, window: F.Column, delay: str = "1 hour", *keys: str) -> DataFrame:
    """Rows per window."""
    return stream.withWatermark("ts", delay).groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n"))


def incremental_sink(store: dict[str, ReasonResult], config: Config | None = None) -> Callable[[DataFrame, int], None]:
    """A ``foreachBatch`` function that merges each batch of triples into ``store["closed"]``."""

    def merge(batch: DataFrame, number: int) -> None:
        if not batch.isEmpty():
            store["closed"] = reason_incremental(batch.select("s", "p", "o"), store["closed"], config)

    return merge
