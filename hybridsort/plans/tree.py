"""The adaptive bucket tree: histograms of digits, refinement of heavy buckets, routes and balanced ranges."""

from __future__ import annotations

import functools
import os

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keys import prefix
from ..sources.tables import kept

#: Leaves up to which the tree is broadcast; beyond, rows are joined to it by a shuffle.
BROADCAST_LEAVES = 1_000_000


def digit_histogram(df: DataFrame, key: Column, depth: int, within: DataFrame | None = None) -> DataFrame:
    """prefix, n of all prefixes of ``depth`` digits, or of those below the prefixes of ``within``."""
    rows = df.select(key.alias("k"))
    if within is not None:
        sizes = [r[0] for r in within.select(F.length("prefix")).distinct().collect()]  # at most the key width
        parts = [rows.withColumn("prefix", F.substring("k", 1, n)).join(within.select("prefix"), "prefix", "left_semi") for n in sizes]
        rows = functools.reduce(DataFrame.unionByName, parts) if parts else rows.limit(0)
    return rows.groupBy(prefix(F.col("k"), depth).alias("prefix")).agg(F.count("*").alias("n"))


def offsets(histogram: DataFrame) -> DataFrame:
    """The first position of each bucket: an exclusive prefix sum over a histogram."""
    return histogram.withColumn("start", F.coalesce(F.sum("n").over(Window.orderBy("prefix").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))


def common_prefix(df: DataFrame, key: Column) -> int:
    """Digits that all keys share, from the smallest and largest key."""
    r = df.agg(F.min(key).alias("low"), F.max(key).alias("high")).first()
    return len(os.path.commonprefix([r["low"], r["high"]])) // 2 if r["low"] is not None else 0


def leaves(df: DataFrame, key: Column, width: int, split_limit: int, step: int = 2, skip_common: bool = True) -> DataFrame:
    """prefix, depth, n of the leaves: the shortest prefixes of at most ``split_limit`` keys, or of ``width`` digits.

    Each round scans only keys below heavy prefixes, counts ``step`` digits at once and sums the
    counts back to each digit, so that a bucket already small is not cut further.
    """
    depth = min(common_prefix(df, key), width - 1) if skip_common else 0
    rows = df.select(key.alias("k"))
    found: list[DataFrame] = []
    heavy: DataFrame | None = None
    while True:
        to = min(width, depth + step)
        part = rows
        if heavy is not None:
            part = rows.withColumn("above", prefix(F.col("k"), depth)).join(heavy.select(F.col("prefix").alias("above")), "above", "left_semi")  # Spark broadcasts it where its size allows
        counted = kept(part.groupBy(prefix(F.col("k"), to).alias("prefix")).agg(F.count("*").alias("n")), "histogram")
        open_ = counted
        for d in range(depth + 1, to + 1):
            level = open_.groupBy(prefix(F.col("prefix"), d).alias("above")).agg(F.sum("n").alias("total"))
            done = level.where((F.col("total") <= split_limit) | F.lit(d == width))
            found.append(done.select(F.col("above").alias("prefix"), F.lit(d).alias("depth"), F.col("total").alias("n")))
            more = level.where(F.col("total") > split_limit) if d < width else level.limit(0)
            open_ = open_.withColumn("above", prefix(F.col("prefix"), d)).join(more.select("above"), "above", "left_semi").select("prefix", "n")
        heavy = kept(open_, "heavy")
        depth = to
        if depth == width or not heavy.limit(1).count():
            break
    out = found[0]
    for part in found[1:]:
        out = out.unionByName(part)
    return kept(out, "leaves")


def route(n: Column, depth: Column, split_limit: int, compare_limit: int, width: int, eager_tiny: bool = False, from_task: Column | None = None, single_finished: bool = True) -> Column:
    """What happens to a bucket: all workers on it, one task, a comparison sort, or nothing more.

    Above split_limit it is shared, below compare_limit it is compared; the second test is only made
    for buckets that come out of a task, unless ``eager_tiny``. A single key is finished at once, unless
    ``single_finished`` is off.
    """
    tiny = n < compare_limit
    if not eager_tiny and from_task is not None:
        tiny = tiny & from_task
    done = depth >= width
    return F.when((n <= 1) | done if single_finished else done, "finished").when(n > split_limit, "cooperative").when(tiny, "comparison").otherwise("sequential")


def leaf_depths(df: DataFrame, key: str, width: int, split_limit: int) -> DataFrame:
    """df with ``depth``: the least number of digits that at most ``split_limit`` rows share with the row, or all of them.

    The definition of the leaves, a window for each digit; ``leaves`` finds the same from histograms.
    """
    out = df
    depth = F.lit(width)
    for d in range(width - 1, 0, -1):
        name = f"__n{d}"
        out = out.withColumn(name, F.count("*").over(Window.partitionBy(F.substring(key, 1, 2 * d))))
        depth = F.when(F.col(name) <= split_limit, d).otherwise(depth)
    return out.select(*[f"`{c}`" for c in df.columns], depth.alias("depth"))


def tree_nodes(df: DataFrame, key: Column, width: int, split_limit: int, compare_limit: int, eager_tiny: bool = False, single_finished: bool = True) -> DataFrame:
    """Every node that the adaptive sort meets: prefix, depth, n, route, from_task; for cost counting on small widths."""
    rows = kept(df.select(key.alias("k")), "keys")
    level = rows.agg(F.count("*").alias("n")).select(F.lit("").alias("prefix"), F.lit(0).alias("depth"), "n", F.lit("cooperative").alias("route"), F.lit(False).alias("from_task"))
    out = level
    for d in range(1, width + 1):
        active = level.where(F.col("route").isin("cooperative", "sequential")).select(F.col("prefix").alias("above"), (F.col("route") == "sequential").alias("from_task"))
        cut = rows.groupBy(prefix(F.col("k"), d).alias("prefix")).agg(F.count("*").alias("n")).withColumn("above", prefix(F.col("prefix"), d - 1))
        level = cut.join(F.broadcast(active), "above").select("prefix", F.lit(d).alias("depth"), "n", "from_task")
        level = level.withColumn("route", route(F.col("n"), F.col("depth"), split_limit, compare_limit, width, eager_tiny, F.col("from_task"), single_finished))
        level = kept(level.select("prefix", "depth", "n", "route", "from_task"), "level")
        out = out.unionByName(level)
    return out


def pack_ranges(tree: DataFrame, target_rows: int) -> DataFrame:
    """Leaves with start and the contiguous range that they fall in; a range holds about target_rows rows."""
    placed = offsets(tree).withColumn("cell", F.floor(F.col("start") / target_rows))
    return placed.withColumn("range_id", (F.dense_rank().over(Window.orderBy("cell")) - 1).cast("int")).drop("cell")


def pack_lpt(tree: DataFrame, workers: int) -> DataFrame:
    """Leaves dealt to workers, largest first, each to the least loaded; for comparison with contiguous packing.

    The leaves are a bounded table, so this is done on the driver.
    """
    import heapq

    loads = [(0, w) for w in range(workers)]
    out = []
    for r in sorted(tree.select("prefix", "n").collect(), key=lambda r: (-r["n"], r["prefix"])):
        load, w = heapq.heappop(loads)
        out.append((r["prefix"], r["n"], w))
        heapq.heappush(loads, (load + r["n"], w))
    return tree.sparkSession.createDataFrame(out, "prefix string, n long, worker int")


def assign(df: DataFrame, key: str, tree: DataFrame, columns: list[str]) -> DataFrame:
    """df with ``columns`` of the leaf of each row: one hash join for each depth that occurs, no range join."""
    depths = [r["depth"] for r in tree.select("depth").distinct().orderBy("depth").collect()]  # at most the key width
    small = tree.count() <= BROADCAST_LEAVES
    names = {c: [] for c in columns}
    out = df
    for d in depths:
        at = tree.where(F.col("depth") == d).select(F.col("prefix").alias(f"__p{d}"), *[F.col(c).alias(f"__{c}{d}") for c in columns])
        out = out.withColumn(f"__q{d}", prefix(F.col(key), d)).join(F.broadcast(at) if small else at, F.col(f"__q{d}") == F.col(f"__p{d}"), "left")
        for c in columns:
            names[c].append(f"__{c}{d}")
    found = {c: F.coalesce(*names[c]) if names[c] else F.lit(None).cast(tree.schema[c].dataType) for c in columns}
    return out.select(*[f"`{c}`" for c in df.columns], *[found[c].alias(c) for c in columns])
