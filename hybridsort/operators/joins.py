"""Joins: one over the sort's ranges, the choice among Spark's, and forms that Spark has no operator for."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.cuts import cut, deal
from .kernels import _wide, msd_sort
from .msd import key_bytes


def choose_join(left_bytes: int, right_bytes: int, limit: int = 10 << 20, prefer_merge: bool = True, equi: bool = True) -> str:
    """broadcast under the limit, else merge where preferred, else shuffle_hash."""
    if min(left_bytes, right_bytes) <= limit:
        return "broadcast"
    if not equi:
        return "shuffle_replicate_nl"
    return "merge" if prefer_merge else "shuffle_hash"


def radix_merge_join(left: DataFrame, right: DataFrame, key: str, width: int, target_rows: int, how: str = "inner") -> DataFrame:
    """A merge join by the sort kernel inside common key ranges; how is inner, left, right or full.

    Both sides are cut by one histogram over their hex column ``key`` and grouped by range; a task
    sorts its two pieces by the radix kernel and merges them. A key with more rows than a range should
    hold is parted: the rows of one side are dealt to several tasks, those of the other are sent to all
    of these (not with a full join, which has to see both sides whole). Null keys match nothing.
    """
    if how == "right":
        out = radix_merge_join(right, left, key, width, target_rows, "left")
        return out.select(key, *[f"`{c}`" for c in left.columns if c != key], *[f"`{c}`" for c in right.columns if c != key])
    digits = lambda s: s.withColumn(name, F.when(F.col(key).isNull(), F.lit("00" * (width + 1))).otherwise(F.concat(F.lit("01"), F.col(key))))
    name, cell, pieces = "__digits", "__range", "__pieces"
    a, b = digits(left), digits(right)
    cuts = cut(a.select(name).unionByName(b.select(name)), F.col(name), width + 1, target_rows, target_rows)
    a, b = (deal(s, name, cuts, range_id=cell, pieces=pieces) for s in (a, b))
    own = F.lit(1) if how == "full" else F.col(pieces)
    a = a.withColumn(pieces, F.pmod(F.xxhash64(*[f"`{c}`" for c in left.columns]), own).cast("int"))
    b = b.withColumn(pieces, F.explode(F.sequence(F.lit(0), (own - 1).cast("int"))))
    rest = [left.schema[c] for c in left.columns if c != key], [right.schema[c] for c in right.columns if c != key]
    schema = T.StructType([left.schema[key], *[T.StructField(f.name, f.dataType) for part in rest for f in part]])
    sides = [s.withColumn(name, F.when(F.col(key).isNotNull(), F.unhex(name))) for s in (a, b)]
    sides[1] = sides[1].select(*[F.col(f"`{c}`").alias(c) for c in sides[1].columns])  # a table may be joined to itself
    merge = _merging(key, name, width + 1, [f.name for f in rest[0]], [f.name for f in rest[1]], how)
    return sides[0].groupBy(cell, pieces).cogroup(sides[1].groupBy(cell, pieces)).applyInArrow(merge, schema)


def _merging(key: str, digits: str, width: int, left: list[str], right: list[str], how: str):
    def ordered(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        known = table.column(digits).is_valid().to_numpy()
        at = np.flatnonzero(known)
        keys = key_bytes(table.column(digits).filter(pa.array(known)), width) if len(at) else np.zeros((0, width), np.uint8)
        order = msd_sort(keys)
        return _wide(keys[order]), at[order], np.flatnonzero(~known)

    def merge(a: pa.Table, b: pa.Table) -> pa.Table:
        x, row_a, null_a = ordered(a)
        y, row_b, null_b = ordered(b)
        low, high = np.searchsorted(y, x, side="left"), np.searchsorted(y, x, side="right")
        runs = high - low
        i = np.repeat(row_a, runs)
        j = row_b[np.repeat(low - (np.cumsum(runs) - runs), runs) + np.arange(int(runs.sum()))]
        none = np.zeros(0, np.int64)
        alone_a = np.concatenate([row_a[runs == 0], null_a]) if how in ("left", "full") else none
        met = np.searchsorted(x, y, side="right") > np.searchsorted(x, y, side="left") if len(y) else np.zeros(0, bool)
        alone_b = np.concatenate([row_b[~met], null_b]) if how == "full" else none
        i, j = np.concatenate([i, alone_a, np.full(len(alone_b), -1)]), np.concatenate([j, np.full(len(alone_a), -1), alone_b])
        take_a, take_b = pa.array(i, mask=i < 0), pa.array(j, mask=j < 0)
        own = a.column(key).take(take_a)
        if len(alone_b):
            own = pc.coalesce(own, b.column(key).take(take_b))
        return pa.table([own, *[a.column(c).take(take_a) for c in left], *[b.column(c).take(take_b) for c in right]], names=[key, *left, *right])

    return merge


def asof(left: DataFrame, right: DataFrame, by: str, at: str, values: list[str]) -> DataFrame:
    """Each row of left with the values of the last row of right at or before it: one sort of both, no range join."""
    tagged = left.select(by, at, F.lit(1).alias("__side"), *[c for c in left.columns if c not in (by, at)], *[F.lit(None).cast(right.schema[v].dataType).alias(v) for v in values])
    other = right.select(by, at, F.lit(0).alias("__side"), *[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (by, at)], *values)
    w = Window.partitionBy(by).orderBy(at, "__side").rowsBetween(Window.unboundedPreceding, 0)
    out = tagged.unionByName(other)
    for v in values:
        out = out.withColumn(v, F.last(F.when(F.col("__side") == 0, F.col(v)), ignorenulls=True).over(w))
    return out.where("__side = 1").drop("__side")


def within(left: DataFrame, right: DataFrame, by: str, left_at: str, right_at: str, span: int) -> DataFrame:
    """Pairs with equal ``by`` and right_at in [left_at, left_at + span]: an equi-join on time cells, then a filter."""
    cell = lambda c: F.floor(F.col(c) / span)
    a = left.withColumn("__cell", F.explode(F.array(cell(left_at), cell(left_at) + 1)))
    b = right.withColumn("__cell", cell(right_at))
    return a.join(b, [by, "__cell"]).where(F.col(right_at).between(F.col(left_at), F.col(left_at) + span)).drop("__cell")


def salted(left: DataFrame, right: DataFrame, key: str, salts: int = 8) -> DataFrame:
    """An inner join whose hot keys are spread: left rows get a salt, right rows all of them.

    Always a merge join: Spark sizes the right side without its copies, and would broadcast all of them.
    """
    a = left.withColumn("__salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    b = right.withColumn("__salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return a.join(b.hint("merge"), [key, "__salt"]).drop("__salt")
