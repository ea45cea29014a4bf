"""Cut points of a sort: contiguous key ranges of about equal size, from exact histograms.

The first scan counts two digits at once, and sums them to one digit where that bucket is small. Buckets
above the limit are refined one digit a scan, each at the digit where its own keys first differ, so that
long common prefixes cost nothing. Only counts reach the driver: 65,536 of the first scan at most, and
of each later one 256 for each heavy bucket, of which there are MAX_LEAVES at most. Rows find their
range by one broadcast hash join for each level of the tree.
"""

from __future__ import annotations

import os
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.tables import fresh

#: Leaves of a tree at most; beyond, leaves and ranges grow with the rows, and Spark's sorter spills inside them.
MAX_LEAVES = 50_000


@dataclass
class Node:
    """A bucket: its level and place there, the digits that lead to it, and what becomes of it."""

    level: int
    parent: int
    digits: str
    prefix: str
    n: int
    known: str  # the digits that all its keys share, as far as they were looked at
    depth: int
    node: int = -1
    equal: bool = False
    range_id: int = -1
    start: int = 0
    pieces: int = 1
    open: bool = True


@dataclass
class Cuts:
    rows: int = 0
    nodes: list[Node] = field(default_factory=list)
    ranges: list[tuple[int, int, int]] = field(default_factory=list)  # range, start, rows

    @property
    def leaves(self) -> list[Node]:
        return [x for x in self.nodes if x.node < 0]

    def routes(self, compare_limit: int) -> dict[str, tuple[int, int]]:
        """Buckets and rows by what happens to them: ``cooperative`` ones were refined by a scan of everybody, the others are one task's work."""
        out: dict[str, tuple[int, int]] = {}
        for x in self.nodes:
            name = "cooperative" if x.node >= 0 else "finished" if x.equal or x.n == 1 else "comparison" if x.n < compare_limit else "sequential"
            buckets, rows = out.get(name, (0, 0))
            out[name] = (buckets + 1, rows + x.n)
        return out

    def reach(self) -> int:
        """How many digits a row needs to find its leaf."""
        return 1 + max((x.depth for x in self.nodes if x.node >= 0), default=0)

    def levels(self) -> int:
        return max((x.level for x in self.nodes), default=-1) + 1

    def table(self, level: int) -> pa.Table:
        own = [x for x in self.nodes if x.level == level]
        kinds = (("parent", pa.int32()), ("digits", pa.string()), ("node", pa.int32()), ("depth", pa.int32()), ("range_id", pa.int32()), ("start", pa.int64()), ("pieces", pa.int32()))
        return pa.table({name: pa.array([getattr(x, name) for x in own], kind) for name, kind in kinds})


def _descend(df: DataFrame, key: Column, cuts: Cuts) -> tuple[DataFrame, list[dict[str, str]]]:
    """df joined to the levels known so far; the names of the columns that each has added."""
    out, names = df, []
    for level in range(cuts.levels()):
        own = {c: fresh(out, f"{c}{level}") for c in ("parent", "digits", "node", "depth", "range_id", "start", "pieces")}
        right = df.sparkSession.createDataFrame(cuts.table(level)).withColumnsRenamed(own)  # bounded by MAX_LEAVES
        if level:
            last = names[-1]
            digits = F.substring(key, 2 * F.col(last["depth"]) + 1, F.lit(2))
            on = (F.col(last["node"]) == F.col(own["parent"])) & (digits == F.col(own["digits"]))
        else:
            on = F.substring(key, 1, 2) == F.col(own["digits"])
        out = out.join(F.broadcast(right), on, "left")
        names.append(own)
    return out, names


#: Digits after a bucket's own that a scan compares: as many as a long can hold, so that the grouping stays in hash tables.
AHEAD = 7


def _counted(rows: DataFrame, key: Column, depth: Column, *group: Column) -> DataFrame:
    """Counts, and the least and greatest of the digits from ``depth`` on."""
    ahead = F.conv(F.rpad(F.substring(key, 2 * depth + 1, F.lit(2 * AHEAD)), 2 * AHEAD, "0"), 16, 10).cast("long")
    return rows.withColumn("ahead", ahead).groupBy(*group).agg(F.count("*").alias("n"), F.min("ahead").alias("low"), F.max("ahead").alias("high"))


def _shared(low: int, high: int) -> str:
    """The whole digits that the numbers from low to high begin with."""
    common = os.path.commonprefix([f"{low:0{2 * AHEAD}X}", f"{high:0{2 * AHEAD}X}"])
    return common[: len(common) // 2 * 2]


def cut(df: DataFrame, key: Column, width: int, split_limit: int, target_rows: int, head: Column | None = None, head_width: int = 0) -> Cuts:
    """The ranges of df by the hex key ``key`` of ``width`` bytes, which is never null.

    ``head`` may give the first ``head_width`` bytes of the key, where they are cheaper than all of it: scans that
    look no further compute only them.
    """
    k = F.col("k")

    def rows(reach: int) -> DataFrame:
        return df.select((head if head is not None and reach <= head_width else key).alias("k"))

    both = _counted(rows(2 + AHEAD), k, F.lit(2), F.substring(k, 1, 4).alias("digits"))
    lead = F.substring("digits", 1, 2)
    small = F.sum("n").over(Window.partitionBy(lead)) <= split_limit
    both = both.withColumn("digits", F.when(small, lead).otherwise(F.col("digits")))
    first = both.groupBy("digits").agg(F.sum("n").alias("n"), F.min("low").alias("low"), F.max("high").alias("high")).toArrow().to_pylist()
    out = Cuts(sum(r["n"] for r in first))
    split_limit, target_rows = max(split_limit, out.rows // MAX_LEAVES), max(target_rows, out.rows // MAX_LEAVES)
    heavy: dict[int, Node] = {}

    def add(parent: Node | None, digits: str, n: int, shared: str) -> Node:
        """A bucket, whose keys go on with the digits ``shared``; it is heavy if it is large and has digits left."""
        prefix = (parent.known if parent else "") + digits
        known = (prefix + shared)[: 2 * width]
        x = Node(parent.level + 1 if parent else 0, parent.node if parent else 0, digits, prefix, n, known, len(known) // 2)
        if n > split_limit:
            x.equal = x.depth == width
            if not x.equal:
                x.node = len(heavy)
                heavy[x.node] = x
        out.nodes.append(x)
        return x

    leads: dict[str, list[dict]] = {}
    for r in first:
        leads.setdefault(r["digits"][:2], []).append(r)
    for digits, parts in leads.items():
        alone = parts[0]["digits"][2:4] + _shared(parts[0]["low"], parts[0]["high"]) if len(parts) == 1 else ""
        x = add(None, digits, sum(r["n"] for r in parts), alone)
        if x.node >= 0 and len(parts) > 1:  # the second digit is counted already
            x.open = False
            for r in parts:
                add(x, r["digits"][2:4], r["n"], _shared(r["low"], r["high"]))
    while any(x.open for x in heavy.values()):
        found, names = _descend(rows(max(x.depth for x in heavy.values()) + 1 + AHEAD), k, out)
        node, depth = (F.coalesce(*[F.col(own[c]) for own in reversed(names)]) for c in ("node", "depth"))
        found = found.select("k", node.alias("parent"), depth.alias("depth")).where("parent >= 0")
        counted = _counted(found, k, F.col("depth") + 1, F.col("parent"), F.substring(k, 2 * F.col("depth") + 1, F.lit(2)).alias("digits"))
        children = counted.toArrow().to_pylist()
        for x in heavy.values():
            x.open = False
        for r in children:
            add(heavy[r["parent"]], r["digits"], r["n"], _shared(r["low"], r["high"]))
    _pack(out, target_rows)
    return out


def _pack(cuts: Cuts, target_rows: int) -> None:
    """Leaves into contiguous ranges of about target_rows rows, by prefix sums."""
    leaves = sorted(cuts.leaves, key=lambda x: x.prefix)
    start = np.cumsum([0] + [x.n for x in leaves])
    cell = -1
    for x, at in zip(leaves, start.tolist(), strict=False):
        if at // target_rows != cell:
            cell = at // target_rows
            cuts.ranges.append((len(cuts.ranges), at, 0))
        number, first, n = cuts.ranges[-1]
        x.range_id, x.start = number, first
        x.pieces = max(1, x.n // target_rows) if x.equal else 1
        cuts.ranges[-1] = (number, first, n + x.n)


def deal(df: DataFrame, key: str, cuts: Cuts, **names: str) -> DataFrame:
    """df with the leaf's values under the given names (range_id, start, pieces); a row that was not counted is an error."""
    out, levels = _descend(df, F.col(f"`{key}`"), cuts)
    found = {}
    for value, name in names.items():
        settled = [F.when(F.col(own["node"]) < 0, F.col(own[value])) for own in levels]
        found[name] = F.coalesce(*settled, F.raise_error(F.lit("a row was not counted: the input is not repeatable")).cast("long" if value == "start" else "int"))
    if not levels:  # an empty table
        found = {name: F.lit(0) for name in names.values()}
    return out.select(*[f"`{c}`" for c in df.columns], *[c.alias(name) for name, c in found.items()])
