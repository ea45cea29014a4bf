"""External sort: sorted runs on shared storage, then one merge for each key range.

The runs are one bucketed table with a bucket for each range: a task writes its rows as sorted runs of
at most ``run_rows`` rows, cut by range into the range's bucket. A merge task reads the pieces of all
runs of its range, and no row crosses the network between. A range is read by no one else, so ranges
can also be merged and written as independent jobs, restarted where they ended (``run_pipeline``).
"""

from __future__ import annotations

import functools
import math
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.tables import delete, exists, fresh, scratch
from .kernels import kway_merge
from .msd import Ranges, key_bytes, named, prepared, with_digits


@dataclass
class Runs:
    """A table of runs: ``bucket`` of a row is the range's number in the table's layout, ``run`` its run."""

    spark: SparkSession
    name: str
    bucket: str
    run: str
    width: int
    columns: list[str]
    order: list[str]
    buckets: list[int]  # of each range
    starts: list[int]

    def read(self) -> DataFrame:
        return self.spark.table(self.name)

    def with_digits(self) -> tuple[DataFrame, str, int, list[str]]:
        """The rows with the digits of their order, which are made again rather than stored."""
        return with_digits(self.read(), self.order[0], self.width, self.order[1:])

    def drop(self) -> None:
        self.spark.sql(f"drop table if exists {self.name}")


def bucket_numbers(spark: SparkSession, n: int) -> list[int]:
    """For each of n buckets, the least number that Spark's hash puts there, so that every range gets a bucket of its own."""
    found: list[int | None] = [None] * n
    step = max(64, int(2 * n * (math.log(n) + 2)))
    low = 0
    while None in found:
        hashed = spark.range(low, low + step, 1, 1).select(F.col("id").cast("int").alias("id"), F.pmod(F.hash(F.col("id").cast("int")), F.lit(n)).alias("at"))
        for r in hashed.groupBy("at").agg(F.min("id").alias("id")).collect():  # a row a range
            if found[r["at"]] is None:
                found[r["at"]] = r["id"]
        low += step
    return found


def _write(rows: DataFrame, runs: Runs, n: int, order: list[str]) -> None:
    """The writer sorts each task's rows by bucket, run and order, and opens one file for each bucket."""
    rows.write.bucketBy(n, runs.bucket).sortBy(runs.run, *order).option("path", scratch(runs.spark, "runs")).saveAsTable(runs.name)


def make_runs(df: DataFrame, key: str, ptr: list[str], width: int = 10, split_limit: int = 2_000_000, target_rows: int = 2_000_000, run_rows: int = 8_000_000, run_of: str | None = None) -> Runs:
    """Write df as sorted runs, cut by range. No shuffle: a run holds rows of one input split, ``run_rows`` at most.

    With the column ``run_of`` its values are the runs, as far as a task has them; it is no part of the output.
    """
    df = prepared(df, key, ptr)
    spark = df.sparkSession
    ranges = Ranges(df, key, width, ptr, split_limit, target_rows)
    numbers = bucket_numbers(spark, ranges.n)
    bucket, run = fresh(ranges.rows, "bucket"), fresh(ranges.rows, "run")
    place = F.monotonically_increasing_id()
    in_split = F.floor(place.bitwiseAND(F.lit((1 << 33) - 1)) / run_rows)
    number = F.spark_partition_id().cast("long") * (1 << 20) + in_split if run_of is None else F.col(f"`{run_of}`").cast("long") * (1 << 32) + F.spark_partition_id()
    rows = ranges.rows.withColumn(run, number.cast("long"))
    rows = rows.withColumn(bucket, F.element_at(F.array(*[F.lit(b) for b in numbers]), F.col(ranges.range_id) + 1)).drop(ranges.range_id, ranges.start, ranges.digits)
    starts = [s for _, s, _ in ranges.cuts.ranges] or [0]
    out = Runs(spark, f"runs_{uuid.uuid4().hex}", bucket, run, width, [c for c in df.columns if c != run_of], [key, *ptr], numbers, starts)
    _write(rows, out, len(numbers), out.order)
    return out


def fan_in(runs: Runs) -> int:
    """How many runs meet in one range at most."""
    return runs.read().groupBy(runs.bucket).agg(F.countDistinct(runs.run).alias("n")).agg(F.max("n")).first()[0] or 0


def compact(runs: Runs, limit: int) -> Runs:
    """One merge round, bucket by bucket and without a shuffle: neighbours of ``limit`` runs become one run; the old table goes."""
    rank = F.dense_rank().over(Window.partitionBy(runs.bucket).orderBy(runs.run))
    rows = runs.read().withColumn(runs.run, F.floor((rank - 1) / limit).cast("long"))
    out = Runs(**{**vars(runs), "name": f"runs_{uuid.uuid4().hex}"})
    _write(rows, out, len(runs.buckets), runs.order)
    runs.drop()
    return out


def merge_runs(runs: Runs, kernel: str = "jvm", most: int = 500) -> DataFrame:
    """One task a range brings its pieces of all runs into one order; position is the range's start and the rank.

    Above ``most`` runs in a range they are merged in rounds first. ``jvm`` merges by Spark's sorter;
    ``kway`` merges the sorted pieces of a range by their key bytes, a column batch each.
    """
    while fan_in(runs) > most:
        runs = compact(runs, most)
    start = F.element_at(F.map_from_arrays(F.array(*[F.lit(b) for b in runs.buckets]), F.array(*[F.lit(int(s)) for s in runs.starts])), F.col(runs.bucket))
    if kernel == "jvm":
        rows = runs.read()
        rank = F.row_number().over(Window.partitionBy(runs.bucket).orderBy(*[F.col(f"`{c}`").asc_nulls_first() for c in runs.order]))
        return rows.withColumn(runs.run, rank).select((start + F.col(runs.run)).cast("long").alias("position"), *named(runs.columns))
    rows, digits, width, rest = runs.with_digits()
    first = fresh(rows, "first")
    schema = T.StructType([T.StructField("position", T.LongType()), *[rows.schema[c] for c in runs.columns]])
    rows = rows.withColumns({first: start.cast("long"), digits: F.unhex(digits)})
    return rows.groupBy(runs.bucket).applyInArrow(_merging(digits, width, runs.run, first, runs.columns, rest), schema)


def _merging(digits: str, width: int, run: str, first: str, columns: list[str], rest: list[str]):
    def merge(table: pa.Table) -> pa.Table:
        own = table.column(run).to_numpy()
        keys = key_bytes(table.column(digits), width)
        lead = np.argsort(own, kind="stable")  # files come in any order, each run's rows in theirs
        parts = np.split(lead, np.flatnonzero(np.diff(own[lead])) + 1)
        order = lead[kway_merge([keys[p] for p in parts])]
        if rest and len(order) > 1:
            ranked = keys[order]
            same = np.cumsum(np.concatenate([[0], (ranked[1:] != ranked[:-1]).any(1)]))
            ties = pa.table([pa.array(same), *[table.column(c).take(pa.array(order)) for c in rest]], names=[str(i) for i in range(len(rest) + 1)])
            order = order[pc.sort_indices(ties, [(str(i), "ascending") for i in range(len(rest) + 1)], null_placement="at_start").to_numpy()]
        start = table.column(first)[0].as_py()
        out = table.select(columns).take(pa.array(order))
        return out.add_column(0, pa.field("position", pa.int64()), pa.array(start + 1 + np.arange(len(order))))

    return merge


def external_sort(df: DataFrame, key: str, ptr: list[str], width: int = 10, split_limit: int = 2_000_000, target_rows: int = 2_000_000, kernel: str = "jvm", run_rows: int = 8_000_000, most: int = 500) -> DataFrame:
    """Runs, then merges."""
    return merge_runs(make_runs(df, key, ptr, width, split_limit, target_rows, run_rows), kernel, most)


def merge_sorted(inputs: list[DataFrame], key: str, ptr: list[str], width: int = 10, split_limit: int = 2_000_000, target_rows: int = 2_000_000) -> DataFrame:
    """One order from several sorted inputs with the same columns: each is a run, and the runs are merged by key."""
    run = fresh(inputs[0], "input")
    every = functools.reduce(DataFrame.unionByName, [df.withColumn(run, F.lit(i).cast("long")) for i, df in enumerate(inputs)])
    return merge_runs(make_runs(every, key, ptr, width, split_limit, target_rows, run_of=run), "kway")


def run_pipeline(runs: Runs, path: str, overlap: bool = True, order: str = "key", workers: int = 4) -> DataFrame:
    """Merge and write every range as a job of its own, and return the whole output.

    Jobs run together from a pool, so that one range is read while another is merged or written, or one
    after the other. They are submitted by ``key``, largest first (``size_desc``), or as they come
    (``arrival``). A range whose directory is complete is not done again.
    """
    spark = runs.spark
    ids = range(len(runs.buckets))
    if order == "size_desc":
        rows = {r[0]: r[1] for r in runs.read().groupBy(runs.bucket).count().collect()}  # a row a range
        ids = sorted(ids, key=lambda i: -rows.get(runs.buckets[i], 0))
    elif order == "arrival":
        ids = sorted(ids, key=lambda i: runs.buckets[i])

    def write(i: int) -> int:
        to = f"{path}/range_id={i}"
        if exists(spark, f"{to}/_SUCCESS"):
            return i
        if exists(spark, to):
            delete(spark, to)
        rows = runs.read().where(F.col(runs.bucket) == runs.buckets[i])  # one bucket is read
        rank = F.row_number().over(Window.partitionBy(runs.bucket).orderBy(*[F.col(f"`{c}`").asc_nulls_first() for c in runs.order]))
        rows.select((F.lit(int(runs.starts[i])) + rank).cast("long").alias("position"), *named(runs.columns)).write.parquet(to)
        return i

    if overlap:
        with ThreadPoolExecutor(workers) as pool:
            list(pool.map(write, ids))
    else:
        for i in ids:
            write(i)
    schema = T.StructType([T.StructField("position", T.LongType()), *[runs.read().schema[c] for c in runs.columns]])
    return spark.read.schema(schema).option("recursiveFileLookup", "true").parquet(path)


def count_runs(runs: Runs) -> DataFrame:
    """Rows of all runs, ranges, and whether every run is sorted within its range; the number of runs and the fan-in depend on the splits."""
    by = Window.partitionBy(runs.bucket, runs.run).orderBy(*[F.col(f"`{c}`").asc_nulls_first() for c in runs.order])
    rows, digits, _, _ = runs.with_digits()
    rows = rows.withColumn("before", F.lag(digits).over(by))
    return rows.agg(F.count("*").alias("rows"), F.countDistinct(runs.bucket).alias("ranges"), F.bool_and(F.coalesce(F.col("before") <= F.col(digits), F.lit(True))).alias("ordered"), F.max(runs.run).alias("last_run"))


