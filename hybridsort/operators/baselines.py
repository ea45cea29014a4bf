"""What the adaptive sort is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import fresh, kept
from .msd import adaptive_sort, named


def spark_sort(df: DataFrame, *order) -> DataFrame:
    """Spark's own sort: sampled range exchange and local prefix sort; positions from range counts.

    The order is written out as it stands; the rank is a prefix sum over partition counts.
    """
    df = df.select(*named([c for c in df.columns if c.lower() != "position"]))
    part, rank, start = fresh(df, "part"), fresh(df, "rank"), fresh(df, "start")
    spread = df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn(part, F.spark_partition_id())
    ranked = kept(spread.withColumn(rank, F.row_number().over(Window.partitionBy(part).orderBy(*order))), "ordered")
    counts = ranked.groupBy(part).count()
    before = F.coalesce(F.sum("count").over(Window.orderBy(part).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = counts.select(part, before.alias(start))
    out = ranked.join(F.broadcast(starts), part)  # a row a partition
    return out.select((F.col(start) + F.col(rank)).cast("long").alias("position"), *named(df.columns))


def comparison_sort(df: DataFrame, key: str, ptr: list[str], stable: bool = True, **options) -> DataFrame:
    """The library's merge or quick sort in each range, in place of radix."""
    return adaptive_sort(df, key, ptr, kernel="stable" if stable else "quick", **options)


def single_task_sort(df: DataFrame, key: str, ptr: list[str]) -> DataFrame:
    """All rows in one task; only for comparison on small data."""
    rank = F.row_number().over(Window.orderBy(key, *ptr))
    return df.coalesce(1).select(rank.cast("long").alias("position"), *[f"`{c}`" for c in df.columns])


def staged_sort(df: DataFrame, key: str, ptr: list[str], path: str, **options) -> dict[str, float]:
    """Read, sort and write without overlap, each materialised before the next; seconds of each."""
    import time

    from pyspark import StorageLevel

    marks = [time.perf_counter()]
    read = df.persist(StorageLevel.MEMORY_AND_DISK)
    read.count()
    marks.append(time.perf_counter())
    ordered = comparison_sort(read, key, ptr, **options).persist(StorageLevel.MEMORY_AND_DISK)
    ordered.count()
    marks.append(time.perf_counter())
    ordered.write.mode("overwrite").parquet(path)
    marks.append(time.perf_counter())
    ordered.unpersist()
    read.unpersist()
    return {"read_s": marks[1] - marks[0], "sort_s": marks[2] - marks[1], "write_s": marks[3] - marks[2], "total_s": marks[3] - marks[0]}
