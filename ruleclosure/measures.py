"""Cost and accuracy measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .durable import cut
from .reasoner import ReasonResult
from .triples import classify

#: Published reasoning times in seconds and inferred triples a second, by size of the input.  Fixed values.
SIZES = (10, 50, 100, 150, 200)
INPUTS = (1449832, 6822632, 12297500, 20652819, 27643644)
OURS_S = (460, 1413, 2460, 4224, 7080)
BASELINE_A_S = (480, 1910, 3250, 5460, 8850)
OURS_RATE = (38425.335, 67471.298, 83201.436, 86510.952, 72749.017)
BASELINE_B_RATE = (41840.289, 60950.250, 69645.680, 75657.241, 59880.319)


def measure(work: Callable[[], DataFrame], runs: int = 3) -> float:
    """Mean seconds of ``runs`` runs, results written to the no-op sink."""
    times = []
    for _ in range(runs):
        began = time.time()
        work().write.format("noop").mode("overwrite").save()
        times.append(time.time() - began)
    return sum(times) / runs


def shuffled(spark: SparkSession, work: Callable[[], object]) -> tuple[object, int]:
    """(what ``work`` returns, bytes its stages wrote to shuffles), from the status store."""
    before = _shuffle_bytes(spark)
    out = work()
    return out, sum(n for k, n in _shuffle_bytes(spark).items() if k not in before)


def _shuffle_bytes(spark: SparkSession) -> dict[tuple[int, int], int]:
    """Bytes by stage and attempt.  The store keeps the last stages only (spark.ui.retainedStages)."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty(60_000)
    none = sc._jvm.java.util.ArrayList()
    empty = sc._gateway.new_array(sc._jvm.double, 0)
    found = sc._jsc.sc().statusStore().stageList(none, False, False, empty, none)
    return {(x.stageId(), x.attemptId()): x.shuffleWriteBytes() for x in (found.apply(k) for k in range(found.size()))}


def inferred_count(result: ReasonResult) -> int:
    return result.derived.count()


def throughput(result: ReasonResult, secs: float) -> dict[str, float]:
    """Inferred triples a second, distinct and (where counted) raw: published rates may count either."""
    raw = sum(x[3] or 0 for x in result.stats)
    return {"distinct": inferred_count(result) / secs, "raw": raw / secs}


def improvement(base: float, ours: float) -> tuple[float, float]:
    """(percent less time, speed-up)."""
    return 100 * (base - ours) / base, base / ours


def published(spark: SparkSession) -> DataFrame:
    rows = list(zip(SIZES, INPUTS, OURS_S, BASELINE_A_S, OURS_RATE, BASELINE_B_RATE, strict=True))
    return spark.createDataFrame(rows, "size int, triples long, ours_s int, base_s int, ours_rate double, base_rate double")


def improvements(points: DataFrame) -> DataFrame:
    """size, less_time (percent), speed_up, rate_ratio."""
    return points.select(
        "size",
        F.round(100.0 * (F.col("base_s") - F.col("ours_s")) / F.col("base_s"), 3).alias("less_time"),
        F.round(F.col("base_s") / F.col("ours_s"), 4).alias("speed_up"),
        F.round(F.col("ours_rate") / F.col("base_rate"), 4).alias("rate_ratio"),
    )


def scaling_fit(points: DataFrame, x: str = "triples", y: str = "ours_s") -> DataFrame:
    """slope (per million) and r2 of time against input size."""
    return points.agg(F.round(F.regr_slope(F.col(y), F.col(x) / 1e6), 3).alias("slope"), F.round(F.regr_r2(F.col(y), F.col(x) / 1e6), 4).alias("r2"))


def compare(a: DataFrame, b: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(missing from a, extra in a), against b."""
    a, b = a.select("s", "p", "o").distinct(), b.select("s", "p", "o").distinct()
    return b.exceptAll(a), a.exceptAll(b)


def closure_counts(closure: DataFrame, repeats: bool = True) -> DataFrame:
    """kind, p, n.  repeats: whether triples may come more than once; the closure of a result has each once."""
    return classify(closure.distinct() if repeats else closure).groupBy("kind", "p").agg(F.count("*").alias("n"))


def result_counts(result: ReasonResult) -> DataFrame:
    """``closure_counts`` of a result, whose files go."""
    counts = cut(closure_counts(result.closure, repeats=False))
    result.forget()
    return counts


def yields(result: ReasonResult, spark: SparkSession) -> DataFrame:
    """rule, raw, fresh over all rounds."""
    return result.stats_df(spark).groupBy("rule").agg(F.sum("raw").alias("raw"), F.sum("fresh").alias("fresh"))
