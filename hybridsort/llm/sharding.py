"""Uniform shuffle into shards of exact size.

The numbers of rows that each input partition sends to each block of each shard form a matrix with
fixed row sums (partition sizes) and column sums (block sizes); under a uniform shuffle it is
multivariate hypergeometric. Each task draws its own row of that matrix by descending a seeded
binary tree over the partitions, so no full matrix exists anywhere. It deals the drawn block
labels to its rows in random order, the rows are exchanged, and each block is permuted again.

Shard sizes differ by one row at most, whatever the values: there is no key that could be hot. Draws are
exact at any size; those over 1e9 rows and more are made once, by the driver.

Defined results: null text or id is a row like any other; repeated rows keep a place each; an empty
table gives no rows; input columns named ``shard`` or ``slot`` are replaced, others may have any names;
a very long text is a row like any other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.tables import fresh
from .common import repeatable, staged, tidy, without

#: numpy's hypergeometric sampler takes populations below this.
SMALL = 1_000_000_000
#: Bytes of a block, by the optimiser's estimate of the input (texts take some four times as much), and blocks at most: beyond, blocks grow, and Spark's sorter spills inside them.
BLOCK_BYTES, MOST_BLOCKS = 4 << 20, 20_000


def shard_sizes(rows: int, shards: int) -> list[int]:
    return [rows // shards + (s < rows % shards) for s in range(shards)]


def block_sizes(rows: int, shards: int, block_rows: int) -> list[list[int]]:
    """The sizes of each shard's blocks, which are equal but for one row."""
    return [shard_sizes(n, max(1, -(-n // block_rows))) for n in shard_sizes(rows, shards)]


def hypergeometric(rng: np.random.Generator, good: int, bad: int, n: int) -> int:
    """How many of n items drawn without replacement are good, for populations of any size.

    Give every item a uniform number and draw the n smallest. The middle good item's number has a beta
    distribution, the bad ones below it a binomial one; what is drawn lies on one side of it or takes that
    side whole. So each step halves the good items, until numpy's sampler takes the rest.
    """
    got = 0
    while good and n and good + bad >= SMALL:
        middle = (good + 1) // 2
        below = int(rng.binomial(bad, rng.beta(middle, good - middle + 1)))
        if middle + below <= n:
            got, good, bad, n = got + middle, good - middle, bad - below, n - middle - below
        else:
            good, bad = middle - 1, below
    return got + (int(rng.hypergeometric(good, bad, n)) if good and n else 0)


def draw(rng: np.random.Generator, capacity: np.ndarray, rows: int) -> np.ndarray:
    """How many of ``rows`` drawn without replacement come from each class."""
    rest = int(capacity.sum())
    if rest < SMALL:
        return rng.multivariate_hypergeometric(capacity, rows, method="marginals")
    out = np.zeros_like(capacity)
    for k, size in enumerate(capacity.tolist()):
        rest -= size
        out[k] = hypergeometric(rng, size, rest, rows)
        rows -= int(out[k])
    return out


def split(before: np.ndarray, low: int, high: int, left: np.ndarray, seed: int) -> tuple[int, np.ndarray]:
    """The middle of the partitions low to high, and what those before it get of ``left``."""
    middle = (low + high) // 2
    return middle, draw(np.random.default_rng([seed, low, high]), left, int(before[middle] - before[low]))


def roots(counts: np.ndarray, capacity: np.ndarray, seed: int) -> list[tuple[int, int, np.ndarray]]:
    """The nodes of the tree over the partitions below which draws are cheap: first and past partition, and their share."""
    before = np.concatenate([[0], np.cumsum(counts)])
    open_, out = [(0, len(counts), capacity)], []
    while open_:
        low, high, left = open_.pop()
        if high - low < 2 or int(left.sum()) < SMALL:
            out.append((low, high, left))
            continue
        middle, taken = split(before, low, high, left, seed)
        open_ += [(low, middle, taken), (middle, high, left - taken)]
    return out


def matrix_row(counts: np.ndarray, nodes: list[tuple[int, int, np.ndarray]], partition: int, seed: int) -> np.ndarray:
    """The partition's row of the communication matrix; all rows together use each column's capacity exactly."""
    before = np.concatenate([[0], np.cumsum(counts)])
    low, high, left = next(x for x in nodes if x[0] <= partition < x[1])
    while high - low > 1:
        middle, taken = split(before, low, high, left, seed)
        if partition < middle:
            high, left = middle, taken
        else:
            low, left = middle, left - taken
    return left


def _dealing(shared, blocks: int, block: str, order: str, seed: int):
    @tidy
    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        partition = TaskContext.get().partitionId()
        rng = np.random.default_rng([seed, partition])
        counts, nodes = shared.value
        row = matrix_row(counts, nodes, partition, seed) if partition < len(counts) else np.zeros(blocks, np.int64)
        labels = rng.permutation(np.repeat(np.arange(blocks, dtype=np.int32), row))
        at = 0
        for batch in batches:
            n = batch.num_rows
            if at + n > len(labels):
                raise RuntimeError(f"partition {partition} has more rows than were counted: its input is not repeatable")
            yield pa.RecordBatch.from_arrays(
                [*batch.columns, pa.array(labels[at : at + n]), pa.array(rng.integers(0, 1 << 62, n))],
                names=[*batch.schema.names, block, order],
            )
            at += n
        if at != len(labels):
            raise RuntimeError(f"partition {partition} has fewer rows than were counted: its input is not repeatable")

    return deal


def shard(docs: DataFrame, shards: int = 24, block_rows: int | None = None, seed: int = 20) -> DataFrame:
    """docs with ``shard`` (int) and ``slot`` (long, gapless from 0 in each shard), in uniformly random order.

    A shard is cut into blocks of at most ``block_rows`` rows (by default as many as make BLOCK_BYTES),
    each permuted by one task; a slot is the fixed start of its block plus the rank there. The input
    is counted by partition first, so it has to be repeatable: anything but a scan of files is staged.
    """
    docs = without(docs, "shard", "slot")
    docs = docs if repeatable(docs) else staged(docs, "sharded")
    spark = docs.sparkSession
    found = docs.groupBy(F.spark_partition_id().alias("p")).count().collect()  # a row a partition
    counts = np.zeros(max((r["p"] for r in found), default=0) + 1, np.int64)
    for r in found:
        counts[r["p"]] = r["count"]
    rows = int(counts.sum())
    if block_rows is None:
        size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        block_rows = max(1, rows // MOST_BLOCKS, min(rows, rows * BLOCK_BYTES // max(1, size)))
    sizes = block_sizes(rows, shards, block_rows)
    capacity = np.array([n for own in sizes for n in own], np.int64)
    block, order, first = fresh(docs, "block"), fresh(docs, "order"), fresh(docs, "start")
    schema = T.StructType([*docs.schema, T.StructField(block, T.IntegerType()), T.StructField(order, T.LongType())])
    shared = spark.sparkContext.broadcast((counts, roots(counts, capacity, seed)))  # a number a partition, and MOST_BLOCKS of them for each 1e9 rows
    dealt = docs.mapInArrow(_dealing(shared, len(capacity), block, order, seed), schema)

    starts = [(s, sum(own[:b])) for s, own in enumerate(sizes) for b in range(len(own))]
    spread = dealt.repartitionById(len(capacity), F.col(block))
    ranked = spread.withColumn(order, F.row_number().over(Window.partitionBy(block).orderBy(order)) - 1)
    places = F.broadcast(spark.createDataFrame([(b, s, at) for b, (s, at) in enumerate(starts)], f"{block} int, shard int, {first} long"))  # a row a block
    return ranked.join(places, block).select(*[f"`{c}`" for c in docs.columns], "shard", (F.col(first) + F.col(order)).alias("slot"))
