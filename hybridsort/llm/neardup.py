"""MinHash near-duplicates by one-permutation hashing.

A document's set is its distinct word shingles, each hashed to 64 bits. One permutation is cut into
equal bins and each bin keeps its smallest hash; an empty bin borrows from the first non-empty one in
an order that depends only on the bin, which keeps the collision probability of a bin equal to the
similarity of the sets. Bins are grouped into bands, and a band's values name a bucket.

Documents with the same set form a class at once, and only one of each class goes on. Every member of
a bucket is compared with the bucket's smallest member, a star, so a bucket costs as many
comparisons as it has members. Where buckets still hold several components after that, members
whose sets hold so many shingles of their own that they can have no further link are left out, and
the rest of those outside the largest component are asked, in blocks, against all of them. So no link
between members of a bucket is lost, and no bucket is capped. Links are confirmed on the full sets.

Classes are told apart by 128-bit digests of their sets and linked under numbers of their own; ids come
in only once the components are known.

Defined results: null text, empty text and text without words have empty sets and no links; rows that
share an id are one node with the links of all their texts; rows without an id have no links and are
kept; with an empty table there are no rows; other columns are ignored; a very long text is one set.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, gram_hashes, light_batches, mix, split_words, staged, text_slices, tidy, word_hashes
from .components import components

#: Shingles of the sets that a task holds while others are streamed past.
BLOCK_SHINGLES = 128_000


def donors(bins: int) -> np.ndarray:
    """For each bin, all bins in the order in which it borrows, itself first."""
    out = np.empty((bins, bins), np.int64)
    for b in range(bins):
        order = np.random.default_rng([11, b]).permutation(bins)
        out[b] = np.concatenate([[b], order[order != b]])
    return out


def shingle_sets(buffer: bytes, starts: np.ndarray, width: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; a text of fewer words is one shingle."""
    words, _, first = split_words(buffer.lower(), starts)
    hashes = word_hashes(words)
    grams = gram_hashes(hashes, width)
    out = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= width:
            out.append(np.unique(grams[a : b - width + 1]))
        elif b > a:
            out.append(gram_hashes(hashes[a:b], b - a))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def band_keys(found: np.ndarray, bands: int, rows: int, order: np.ndarray) -> np.ndarray:
    """Bucket keys of a non-empty sorted set of hashes."""
    bins = bands * rows
    bounds = (np.arange(bins + 1, dtype=np.float64) * (2.0**64 / bins))[:-1].astype(np.uint64)
    at = np.searchsorted(found, bounds)
    after = np.append(at[1:], len(found))
    full = after > at
    values = found[np.minimum(at, len(found) - 1)]
    chosen = order[np.arange(bins), np.argmax(full[order], 1)]
    values = mix(values[chosen]).reshape(bands, rows)
    key = np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for r in range(rows):
        key = mix(key ^ values[:, r]) + np.uint64(r)
    return key.view(np.int64)


def _describing(width: int, bands: int, rows: int):
    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        order = donors(bands * rows)
        for batch in light_batches(batches):
            n, keys, buckets = [], [], []
            for _, _, buffer, starts in text_slices(column(batch, "text")):
                for found in shingle_sets(buffer, starts, width):
                    n.append(len(found))
                    keys.append(xxhash.xxh3_128_digest(found.tobytes()) if len(found) else None)
                    buckets.append(band_keys(found, bands, rows, order) if len(found) else None)
            keep = [c for c in batch.schema.names if c != "text"]
            yield pa.RecordBatch.from_arrays([*[column(batch, c) for c in keep], pa.array(n, pa.int64()), pa.array(keys, pa.binary()), pa.array(buckets, pa.list_(pa.int64()))], names=[*keep, "n_shingles", "set_key", "buckets"])

    return run


def _setting(width: int):
    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in light_batches(batches, limit=4 << 20):
            keys, sets = [], []
            for _, _, buffer, starts in text_slices(column(batch, "text")):
                for found in shingle_sets(buffer, starts, width):
                    keys.append(xxhash.xxh3_128_digest(found.tobytes()))
                    sets.append(found.view(np.int64))
            yield pa.RecordBatch.from_arrays([column(batch, "doc_id"), pa.array(keys, pa.binary()), pa.array(sets, pa.list_(pa.int64()))], names=["doc_id", "set_key", "shingles"])

    return run


def _full_sets(docs: DataFrame, nodes: DataFrame, width: int) -> DataFrame:
    """node and shingles for each of nodes(node, set_key, first_id)."""
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(nodes.select(F.col("first_id").alias("doc_id")).distinct(), "doc_id", "left_semi")
    sets = texts.mapInArrow(_setting(width), "doc_id long, set_key binary, shingles array<long>").drop("doc_id")
    return sets.join(nodes.select("node", "set_key"), "set_key").dropDuplicates(["node"]).select("node", "shingles")


def _confirmed(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Those of pairs(a, b, na, nb) whose full sets are similar enough."""
    joined = pairs.join(sets.withColumnsRenamed({"node": "a", "shingles": "sa"}), "a").join(sets.withColumnsRenamed({"node": "b", "shingles": "sb"}), "b")
    shared = F.size(F.array_intersect("sa", "sb"))
    return joined.where(100 * shared >= percent * (F.col("na") + F.col("nb") - shared)).select("a", "b")


def link(docs: DataFrame, width: int = 5, percent: int = 80, bands: int = 20, rows: int = 4) -> DataFrame:
    """doc_id, n_shingles, component_id and kept for every row of docs.

    Two documents are linked if 100 * intersection >= percent * union. At similarity s a pair shares a
    bucket with probability 1 - (1 - s**rows)**bands.
    """
    text = docs.select("doc_id", "text")
    kind = docs.schema["doc_id"].dataType.simpleString()
    described = staged(text.mapInArrow(_describing(width, bands, rows), f"doc_id {kind}, n_shingles long, set_key binary, buckets array<long>"), "described")
    linkable = described.where("set_key is not null and doc_id is not null")
    classes = staged(linkable.groupBy("set_key").agg(F.min("doc_id").cast("long").alias("first_id"), F.first("n_shingles").alias("n"), F.first("buckets").alias("buckets")).withColumn("node", F.monotonically_increasing_id()), "classes")
    members = classes.select("node", "n", F.explode("buckets").alias("bucket"))
    stars = members.groupBy("bucket").agg(F.min(F.struct("node", "n")).alias("centre"), F.count("*").alias("size")).where("size > 1")
    members = staged(members.join(stars, "bucket").select("bucket", "node", "n", "centre"), "members")
    pairs = members.where(F.col("node") != F.col("centre.node")).select(F.col("centre.node").alias("a"), F.col("node").alias("b"), F.col("centre.n").alias("na"), F.col("n").alias("nb"))
    similar = 100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")
    tried = staged(pairs.where(similar).distinct(), "pairs")
    met = members.select("node").distinct()
    sets = staged(_full_sets(docs, classes.join(met, "node", "left_semi").select("node", "set_key", "first_id"), width), "sets")
    links = staged(_confirmed(tried, sets, percent), "links")
    joined = staged(components(links), "components")
    open_ = _possible(members, joined, sets, percent)
    found = staged(_across(open_, joined, sets, percent), "links")
    joined = staged(components(links.union(found)), "components")
    own = classes.select("set_key", "node", "first_id").join(joined, "node", "left")
    least = own.where("component is not null").groupBy("component").agg(F.min("first_id").alias("least"))
    same = own.join(least, "component", "left").select("set_key", F.coalesce("least", "first_id").alias("class_component"))
    out = described.join(same, "set_key", "left")
    by_id = _by_shared_id(out)
    component = F.coalesce("class_component", F.col("doc_id").cast("long"))
    out = out.join(by_id, component == F.col("from_component"), "left") if by_id is not None else out.withColumn("to_component", F.lit(None).cast("long"))
    out = out.select("doc_id", "n_shingles", F.coalesce("to_component", component).alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def _by_shared_id(rows: DataFrame) -> DataFrame | None:
    """Components joined by rows that share an id: from_component, to_component; None if no id is shared by two."""
    own = F.coalesce("class_component", F.col("doc_id").cast("long"))
    shared = rows.where("doc_id is not null").groupBy("doc_id").agg(F.min(own).alias("a"), F.max(own).alias("b")).where("a < b")
    shared = staged(shared.select("a", "b"), "shared")
    if not shared.limit(1).count():
        return None
    return components(shared).select(F.col("node").alias("from_component"), F.col("component").alias("to_component"))


def _possible(members: DataFrame, joined: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The members of buckets of several components that can have a link left to find, with ``unique``.

    Of a node's shingles, ``unique`` are in no other node of these buckets, so in no intersection
    that is still to be tried; where too few remain, the node has no further link.
    """
    placed = members.join(joined, "node", "left").withColumn("component", F.coalesce("component", "node"))
    several = placed.groupBy("bucket").agg((F.min("component") < F.max("component")).alias("several")).where("several").select("bucket")
    open_ = staged(members.join(several, "bucket", "left_semi").select("bucket", "node", "n", (F.col("node") == F.col("centre.node")).alias("used")), "open")
    held = sets.join(open_.select("node").distinct(), "node", "left_semi").select("node", F.explode("shingles").alias("shingle"))
    alone = held.groupBy("shingle").agg(F.count("*").alias("docs"), F.min("node").alias("node")).where("docs = 1")
    unique = alone.groupBy("node").agg(F.count("*").alias("unique"))
    open_ = open_.join(unique, "node", "left").withColumn("unique", F.coalesce("unique", F.lit(0)))
    return staged(open_.where(100 * (F.col("n") - F.col("unique")) >= percent * F.col("n")), "open")


def _across(open_: DataFrame, joined: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The links a, b between components of buckets that share members.

    Buckets that share members form a group. The sets outside a group's largest component are taken
    in blocks of about BLOCK_SHINGLES, and all sets of the group are streamed past each block; only
    links leave a task. A task holds one block, however large the group is.
    """
    nodes = open_.select("node", "n").distinct()
    edges = open_.join(open_.groupBy("bucket").agg(F.min("node").alias("a")), "bucket").select("a", F.col("node").alias("b"))
    groups = staged(components(edges), "groups").withColumnRenamed("component", "grp")
    nodes = nodes.join(groups, "node").join(joined, "node", "left").withColumn("component", F.coalesce("component", "node"))
    nodes = staged(nodes, "nodes")
    sizes = nodes.groupBy("grp", "component").agg(F.count("*").alias("size"), F.sum("n").alias("n"))
    tops = sizes.groupBy("grp").agg(F.max(F.struct("size", "component")).alias("top"), F.sum("n").alias("all"), F.max_by("n", F.struct("size", "component")).alias("n_top"), F.count("*").alias("kinds"))
    tops = tops.where("kinds > 1").select("grp", F.col("top.component").alias("largest"), F.ceil((F.col("all") - F.col("n_top")) / BLOCK_SHINGLES).alias("blocks"))
    nodes = nodes.join(tops, "grp")
    asked = nodes.where("component != largest").select("grp", F.pmod(F.xxhash64("node"), "blocks").alias("block"), F.lit(0).alias("role"), "node", "component")
    every = nodes.select("grp", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"), F.lit(1).alias("role"), "node", "component")
    rows = asked.unionByName(every).join(sets, "node").select("grp", "block", "role", "node", "component", "shingles")
    rows = rows.repartition("grp", "block").sortWithinPartitions("grp", "block", "role")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _streamed(batches, percent)

    return rows.mapInArrow(run, "a long, b long")


class _Block:
    """The asked sets of one block, inverted."""

    def __init__(self):
        self.nodes, self.components, self.sets, self.keys = [], [], [], None

    def add(self, node: int, component: int, found: np.ndarray) -> None:
        self.nodes.append(node)
        self.components.append(component)
        self.sets.append(found)

    def links(self, node: int, component: int, found: np.ndarray, percent: int) -> list[tuple[int, int]]:
        if self.keys is None:
            self.size = np.array([len(s) for s in self.sets])
            keys = np.concatenate(self.sets)
            order = np.argsort(keys, kind="stable")
            self.keys, self.owner = keys[order], np.repeat(np.arange(len(self.sets)), self.size)[order]
            self.node, self.component = np.array(self.nodes), np.array(self.components)
        low, high = np.searchsorted(self.keys, found), np.searchsorted(self.keys, found, side="right")
        runs = high - low
        at = np.repeat(low - np.concatenate([[0], np.cumsum(runs)[:-1]]), runs) + np.arange(int(runs.sum()))
        shared = np.bincount(self.owner[at], minlength=len(self.node))
        good = (100 * shared >= percent * (self.size + len(found) - shared)) & (self.component != component)
        return [(int(x), node) for x in self.node[good]]


def _streamed(batches: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    block, key = _Block(), None
    for batch in batches:
        out: list[tuple[int, int]] = []
        shingles = column(batch, "shingles")
        bounds = shingles.offsets.to_numpy()
        values = shingles.values.to_numpy()
        names = [column(batch, c).to_pylist() for c in ("grp", "block", "role", "node", "component")]
        for k, (grp, number, role, node, component) in enumerate(zip(*names, strict=True)):
            if (grp, number) != key:
                block, key = _Block(), (grp, number)
            found = values[bounds[k] : bounds[k + 1]]
            if role == 0:
                block.add(node, component, found.copy())
            elif block.nodes:
                out += block.links(node, component, found, percent)
        yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in out], pa.int64()), pa.array([y for _, y in out], pa.int64())], names=["a", "b"])
