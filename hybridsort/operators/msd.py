"""Distributed sorts. Each adds ``position`` (long, from 1) and puts every row on the network once.

Rows are dealt to contiguous key ranges of about equal size, cut from exact histograms, and each range
is sorted by one task; no global window or sort is used.

Defined results: null keys and null pointers come first; rows equal in key and pointer are all kept, in
any order among themselves; an empty table gives no rows; a column ``position`` of the input is
replaced; other columns may have any names.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.keys import tie_digits
from ..plans.cuts import Cuts, cut, deal
from ..plans.tree import assign, pack_ranges
from ..sources.tables import fresh, kept
from .kernels import KERNELS


def named(columns: list[str]) -> list[str]:
    return [f"`{c}`" for c in columns]


def prepared(df: DataFrame, key: str, ptr: list[str]) -> DataFrame:
    """df without a column ``position``, which the sorts add."""
    if "position" in {c.lower() for c in (key, *ptr)}:
        raise ValueError("`position` is what a sort adds; rename the key or pointer column")
    return df.select(*named([c for c in df.columns if c.lower() != "position"]))


def key_digits(key: str, width: int) -> Column:
    """A byte that puts nulls first, and the key."""
    k = F.col(f"`{key}`")
    long = F.raise_error(F.lit(f"a key is longer than {width} bytes")).cast("string")
    own = F.when(F.length(k) > 2 * width, long).otherwise(F.rpad(k, 2 * width, "0"))
    return F.when(k.isNull(), F.lit("00" * (width + 1))).otherwise(F.concat(F.lit("01"), own))


def with_digits(df: DataFrame, key: str, width: int, ptr: list[str], full_key: str | None = None) -> tuple[DataFrame, str, int, list[str]]:
    """df with the digits of its whole order, their column and number, and the columns that they leave unsettled.

    Shorter keys are filled up with zeros, longer ones are an error. After the key come digits of the full key or of the pointers, up to the first whose digits don't tell
    all its values apart.
    """
    name = fresh(df, "digits")
    parts, size = [key_digits(key, width)], width + 1
    rest = [*([full_key] if full_key else []), *ptr]
    while rest:
        digits, more, whole = tie_digits(F.col(f"`{rest[0]}`"), df.schema[rest[0]].dataType)
        parts.append(digits)
        size += more
        if not whole:
            break
        rest.pop(0)
    return df.withColumn(name, F.concat(*parts)), name, size, rest


class Ranges:
    """Rows with their range: ``rows`` has the columns ``digits``, ``range_id`` and ``start`` under fresh names."""

    def __init__(self, df: DataFrame, key: str, width: int, ptr: list[str], split_limit: int, target_rows: int, full_key: str | None = None, counted: DataFrame | None = None):
        self.columns = df.columns
        source, digits, self.width, self.rest = with_digits(df if counted is None else counted, key, width, ptr, full_key)
        head = key_digits(key, width)
        self.cuts: Cuts = cut(source, F.col(f"`{digits}`"), self.width, split_limit, target_rows, head, width + 1)
        full, self.digits, _, _ = with_digits(df, key, width, ptr, full_key)
        self.range_id, self.start, short = fresh(full, "range"), fresh(full, "start"), fresh(full, "head")
        by = short if self.cuts.reach() <= width + 1 else self.digits
        self.rows = deal(full.withColumn(short, head), by, self.cuts, range_id=self.range_id, start=self.start).drop(short)

    @property
    def n(self) -> int:
        return max(1, len(self.cuts.ranges))

    def order(self, key: str, ptr: list[str], full_key: str | None = None) -> list:
        return [F.col(f"`{c}`").asc_nulls_first() for c in [key, *([full_key] if full_key else []), *ptr]]

    def spread(self) -> DataFrame:
        """The one exchange of the rows."""
        return self.rows.repartitionById(self.n, F.col(self.range_id))

    def placed(self, rows: DataFrame, order: list) -> DataFrame:
        rank = F.row_number().over(Window.partitionBy(self.range_id).orderBy(*order))
        return rows.select((F.col(self.start) + rank).cast("long").alias("position"), *named(self.columns))


def adaptive_sort(df: DataFrame, key: str, ptr: list[str], width: int = 10, split_limit: int = 2_000_000, target_rows: int = 2_000_000, kernel: str = "jvm", compare_limit: int | None = None, full_key: str | None = None, counted: DataFrame | None = None) -> DataFrame:
    """The adaptive most-significant-digit sort by hex key ``key`` of ``width`` bytes and pointer columns ``ptr``.

    With kernel ``jvm`` a range is sorted by Spark; any name of KERNELS sorts it as key bytes and row
    numbers in one Arrow task, and takes the payload in that order there. ``full_key`` orders rows
    whose fixed-width keys are equal; its first 64 bytes part ranges, and rows equal in all of these stay
    in one range. ``counted`` may hold the pairs of key and pointer, if they are cached somewhere.
    """
    df = prepared(df, key, ptr)
    ranges = Ranges(df, key, width, ptr, split_limit, target_rows, full_key, counted)
    spread = ranges.spread()
    if kernel == "jvm":
        return ranges.placed(spread, ranges.order(key, ptr, full_key))
    source = spread.withColumn(ranges.digits, F.unhex(ranges.digits)).drop(ranges.range_id)
    schema = T.StructType([T.StructField("position", T.LongType()), *df.schema.fields])
    return source.mapInArrow(_sorting(kernel, compare_limit, df.columns, ranges.rest, ranges.digits, ranges.width, ranges.start), schema)


def key_bytes(column: pa.ChunkedArray, width: int) -> np.ndarray:
    """Binary keys of equal width as rows of bytes, without copies where one chunk has them."""
    whole = column.combine_chunks()
    whole = whole.chunk(0) if isinstance(whole, pa.ChunkedArray) else whole
    _, offsets, data = whole.buffers()
    first = int(np.frombuffer(offsets, np.int32)[whole.offset])
    return np.frombuffer(data, np.uint8, len(whole) * width, first).reshape(-1, width)


def _sorting(kernel: str, compare_limit: int | None, columns: list[str], rest: list[str], digits: str, width: int, start: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = [b for b in batches if b.num_rows]
        if not own:
            return
        table = pa.Table.from_batches(own)  # one range: bounded by its size
        keys = key_bytes(table.column(digits), width)
        order = KERNELS[kernel](keys) if compare_limit is None else KERNELS[kernel](keys, compare_limit)
        if rest and len(order) > 1:  # columns without full digits settle what is left
            ranked = keys[order]
            same = np.cumsum(np.concatenate([[0], (ranked[1:] != ranked[:-1]).any(1)]))
            if same[-1] + 1 < len(same):
                ties = pa.table([pa.array(same), *[table.column(c).take(pa.array(order)) for c in rest]], names=[str(i) for i in range(len(rest) + 1)])
                order = order[pc.sort_indices(ties, [(str(i), "ascending") for i in range(len(rest) + 1)], null_placement="at_start").to_numpy()]
        first = table.column(start)[0].as_py()
        out = table.select(columns).take(pa.array(order))
        yield from out.add_column(0, pa.field("position", pa.int64()), pa.array(first + 1 + np.arange(len(order)))).to_batches(100_000)

    return run


def static_sort(df: DataFrame, key: str, ptr: list[str], depth: int = 1) -> DataFrame:
    """The plain form: one task for each value of the first digits, whatever its size."""
    df = prepared(df, key, ptr)
    name = fresh(df, "key")
    keyed = df.withColumn(name, F.coalesce(F.col(f"`{key}`"), F.lit("")))
    tree = keyed.groupBy(F.substring(name, 1, 2 * depth).alias("prefix")).agg(F.count("*").alias("n"))
    tree = kept(pack_ranges(tree.withColumn("depth", F.lit(depth)), 1), "static")
    at, start = fresh(keyed, "range"), fresh(keyed, "start")
    dealt = assign(keyed, name, tree.withColumnsRenamed({"range_id": at, "start": start}), [at, start]).repartitionById(max(1, tree.count()), F.col(at))
    rank = F.row_number().over(Window.partitionBy(at).orderBy(*[F.col(f"`{c}`").asc_nulls_first() for c in (key, *ptr)]))
    return dealt.select((F.col(start) + rank).cast("long").alias("position"), *named(df.columns))


def lsd_distributed(df: DataFrame, key: str, ptr: list[str], width: int) -> DataFrame:
    """Least significant digit first over the cluster: a pass, and a shuffle, for each digit; for small data only."""
    df = prepared(df, key, ptr)
    name = fresh(df, "at")
    at = df.withColumn(name, F.row_number().over(Window.orderBy(*named(ptr))))
    for d in range(width - 1, -1, -1):
        at = kept(at.withColumn(name, F.row_number().over(Window.orderBy(F.substring(f"`{key}`", 2 * d + 1, 2), name))), "pass")
    return at.select(F.col(name).cast("long").alias("position"), *named(df.columns))


def lpt_sort(df: DataFrame, key: str, ptr: list[str], workers: int = 8) -> DataFrame:
    """Buckets of two digits dealt to workers by size, whole; starts come from the histogram."""
    from ..plans.tree import offsets, pack_lpt

    df = prepared(df, key, ptr)
    name = fresh(df, "key")
    keyed = df.withColumn(name, F.coalesce(F.col(f"`{key}`"), F.lit("")))
    tree = kept(keyed.groupBy(F.substring(name, 1, 4).alias("prefix")).agg(F.count("*").alias("n")), "lpt")
    placed = offsets(tree).join(pack_lpt(tree, workers).select("prefix", "worker"), "prefix").withColumn("depth", F.lit(2))
    worker, start, bucket = fresh(keyed, "worker"), fresh(keyed, "start"), fresh(keyed, "bucket")
    placed = kept(placed.withColumn(bucket, F.col("prefix")).withColumnsRenamed({"worker": worker, "start": start}), "lpt")
    dealt = assign(keyed, name, placed, [worker, start, bucket]).repartitionById(workers, F.col(worker))
    rank = F.row_number().over(Window.partitionBy(worker, bucket).orderBy(*[F.col(f"`{c}`").asc_nulls_first() for c in (key, *ptr)]))
    return dealt.select((F.col(start) + rank).cast("long").alias("position"), *named(df.columns))


def gather(order: DataFrame, records: DataFrame, ptr: list[str]) -> DataFrame:
    """Records in the order of sorted pairs: the payload is fetched by pointer, a second exchange."""
    return order.join(records, ptr)


def select_rank(df: DataFrame, key: str, rank: int, width: int) -> str:
    """The key of a rank (from 1), by descending only the bucket that holds it; shared digits are skipped in one scan."""
    found, left = "", rank
    while len(found) < 2 * width:
        below = df.where(F.col(key).startswith(found)).groupBy(F.substring(key, len(found) + 1, 4).alias("digits"))
        for r in below.agg(F.count("*").alias("n"), F.min(key).alias("low"), F.max(key).alias("high")).orderBy("digits").collect():  # at most 65,536 rows
            if left <= r["n"]:
                if r["low"] == r["high"]:
                    return r["low"]
                found += r["digits"]
                break
            left -= r["n"]
        else:
            raise IndexError("rank beyond the rows")
    return found
