"""Timing, cost and correctness measures."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def force(df: DataFrame) -> None:
    """Run a plan and throw its rows away."""
    df.write.format("noop").mode("overwrite").save()


def timed(run: Callable[[], object]) -> float:
    began = time.perf_counter()
    run()
    return time.perf_counter() - began


def phases(df: DataFrame, key: str, ptr: list[str], mode: str, path: str, **options) -> dict[str, float]:
    """Seconds of a whole sort by phase: reading keys and payload, sorting (or making runs), merging, and writing; each ends before the next.

    ``write_s`` is what writing the result takes beyond producing it.
    """
    from .operators import external
    from .operators.engine import sort

    out = {"read_s": timed(lambda: force(df)), "merge_s": 0.0}
    if mode == "external":
        made: list = []
        out["sort_s"] = timed(lambda: made.append(external.make_runs(df, key, ptr, **options)))
        ordered = external.merge_runs(made[0])
        out["merge_s"] = timed(lambda: force(ordered))
        out["write_s"] = max(0.0, timed(lambda: ordered.write.mode("overwrite").parquet(path)) - out["merge_s"])
        made[0].drop()
    else:
        ordered = sort(df, key, ptr, mode=mode, **options)
        out["sort_s"] = max(0.0, timed(lambda: force(ordered)) - out["read_s"])
        out["write_s"] = max(0.0, timed(lambda: ordered.write.mode("overwrite").parquet(path)) - out["sort_s"] - out["read_s"])
    out["total_s"] = sum(out.values())
    return out


def shuffle_bytes(spark) -> int:
    """Bytes that the application has written to shuffles so far, over all stages that the status store still knows."""
    stages = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), None)
    return sum(int(stages.apply(i).shuffleWriteBytes()) for i in range(stages.size()))


def peak_memory(spark) -> dict[str, int]:
    """The largest heap that each executor was seen to use, in bytes, and what it may use."""
    executors = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    out = {}
    for i in range(executors.size()):
        e = executors.apply(i)
        peak = e.peakMemoryMetrics()
        used = int(peak.get().getMetricValue("JVMHeapMemory")) if peak.isDefined() else int(e.memoryUsed())
        out[e.id()] = {"peak": used, "most": int(e.maxMemory())}
    return out


def pairs_per_second(rows: int, seconds: float) -> float:
    return rows / seconds


def bandwidth(bytes_read: int, seconds: float) -> float:
    return bytes_read / seconds


def is_sorted(ordered: DataFrame, key: str) -> DataFrame:
    """One row: whether keys ascend with position, and how many rows there are."""
    return validate(ordered, key).select(F.col("ordered").alias("is_sorted"), "n")


def borders(ordered: DataFrame, key: str, rows: int) -> DataFrame:
    """Parts of ``rows`` positions each, with their least and greatest key, and whether no part begins below where the one before it ends."""
    parts = ordered.withColumn("part", F.floor((F.col("position") - 1) / rows).cast("int")).groupBy("part").agg(F.min(key).alias("low"), F.max(key).alias("high"))
    before = parts.select((F.col("part") + 1).alias("part"), F.col("high").alias("before"))
    return parts.join(before, "part", "left").select("part", "low", "high", F.coalesce(F.col("before") <= F.col("low"), F.lit(True)).alias("apart"))


def speedup(baseline_s: float, own_s: float) -> float:
    return baseline_s / own_s


def io_share(read_s: float, write_s: float, total_s: float) -> float:
    return (read_s + write_s) / total_s


def checksum(c: Column) -> Column:
    """Order-free: the sum of the first seven md5 digits."""
    return F.sum(F.conv(F.substring(F.md5(c), 1, 7), 16, 10).cast("long"))


def validate(ordered: DataFrame, key: str) -> DataFrame:
    """One row: rows, whether keys ascend with position, whether positions are 1 to n, checksum, duplicate keys.

    Neighbours are compared by joining position and position + 1, so no task holds all rows.
    """
    following = ordered.select((F.col("position") - 1).alias("position"), F.col(key).alias("next"))
    pairs = ordered.select("position", key).join(following, "position", "left")
    return pairs.agg(
        F.count("*").alias("n"),
        F.bool_and(F.coalesce(F.col(key) <= F.col("next"), F.lit(True))).alias("ordered"),
        ((F.min("position") == 1) & (F.max("position") == F.count("*")) & (F.countDistinct("position") == F.count("*"))).alias("gapless"),
        checksum(F.col(key)).alias("checksum"),
        (F.count("*") - F.countDistinct(key)).alias("duplicates"),
    )


def imbalance(sizes: DataFrame, n: str = "n") -> DataFrame:
    """Largest range over the mean."""
    return sizes.agg((F.max(n) / F.avg(n)).alias("imbalance"))


def rank_error(df: DataFrame, key: str, cuts: list[str]) -> DataFrame:
    """Rows in each interval of approximate cut points."""
    expr = sum((F.when(F.col(key) >= c, 1).otherwise(0) for c in cuts), F.lit(0))
    return df.groupBy(expr.alias("cell")).agg(F.count("*").alias("n")).withColumn("start", F.sum("n").over(Window.orderBy("cell")))
