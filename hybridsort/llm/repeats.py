"""Repeated windows across a corpus: what the suffix-tree and the suffix-array operators share.

A window is a run of ``length`` units (words or bytes) of one text. All windows of a text are divided
into segments: consecutive windows whose smallest hashed gram is the same. Equal windows have equal
smallest grams, so that gram is a prefix key by which segments can be brought together, and a key
that occurs once in the corpus belongs to windows that occur once.

1. Equal texts become one: their first in order stands for all.
2. Each task sends the keys of its segments, and keys met often within a task only once; those
   that occur twice or more in all are kept. A key that is frequent is deepened: its segments are
   taken apart into single windows, each with its full content as key.
3. The segments of kept keys are cut from the texts and brought together by key, equal ones of a
   task as one; what a task already knows to go is sent as whole spans. Equal segments of a key become
   one string with all its places, and the strings are solved by the index structure of the operator,
   about INDEX_UNITS at once.
4. The spans found are applied to the texts.

The texts are exchanged once, by row, and read three times from that exchange. A row is known by its id
and 63 bits of its text's digest, a row without an id by 127 bits.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import column, light_batches, mix, staged, text_slices, tidy

#: Bits of a segment's key: two different grams of one key only cost a comparison.
KEY = np.uint64((1 << 48) - 1)
#: Occurrences in one batch from which a key is frequent, and in all.
OFTEN_HERE, OFTEN = 64, 50_000
#: Most windows of a segment.
LONGEST = 250
#: Units of unequal segments that are indexed at once.
INDEX_UNITS = 1 << 20


@dataclass
class Kind:
    """How texts become units and which windows go.

    ``units(buffer, starts)`` gives the hash of each unit and the first unit of each text.
    ``pieces(text)`` gives the units of one text as something to slice; ``pack(units)`` makes bytes.
    ``solve(payloads, windows, many, docs, starts)`` gives for the windows of all payloads whether they go;
    ``many`` of the payloads stand in several places, the first of which is given.
    """

    length: int
    gram: int
    units: Callable[[bytes, np.ndarray], tuple[np.ndarray, np.ndarray]]
    pieces: Callable[[bytes], object]
    pack: Callable[[object], bytes]
    join: Callable[[list], bytes]
    solve: Callable[[list[bytes], np.ndarray, np.ndarray, np.ndarray, np.ndarray], np.ndarray]
    keep_first: bool


def grams_of(x: np.ndarray, width: int) -> np.ndarray:
    """Hash of the ``width`` units from each position, by doubling; positions too near the end are left out."""
    out, have, power, size = None, 0, x, 1
    rest = width
    while rest:
        if rest & 1:
            if out is None:
                out = power
            else:
                n = len(power) - have
                out = out[:n] * np.uint64(0x9E3779B97F4A7C15) + (power[have:] ^ np.uint64(0x5851F42D4C957F2D))
            have += size
        rest >>= 1
        if rest:
            n = len(power) - size
            if n <= 0:
                return np.zeros(0, np.uint64)
            power = power[:n] * np.uint64(0xD6E8FEB86659FD93) + (power[size:] ^ (power[size:] >> np.uint64(29)))
            size *= 2
    return mix(out[: max(0, len(x) - width + 1)])


def sliding_minimum(x: np.ndarray, width: int) -> np.ndarray:
    size, out = 1, x
    while size * 2 <= width:
        out = np.minimum(out[:-size], out[size:])
        size *= 2
    return np.minimum(out[: len(x) - width + 1], out[width - size :][: len(x) - width + 1]) if size < width else out


def segments(hashes: np.ndarray, first: np.ndarray, kind: Kind) -> tuple[np.ndarray, ...]:
    """Text, first window (in the text), windows and key of every segment, and whether its key stands in it more than once."""
    n = len(hashes) - kind.length + 1
    if n <= 0:
        return (*(np.zeros(0, np.int64) for _ in range(3)), np.zeros(0, np.uint64), np.zeros(0, bool))
    grams, width = grams_of(hashes, kind.gram), kind.length - kind.gram + 1
    key = sliding_minimum(grams, width)[:n]
    row = np.repeat(np.arange(len(first) - 1), np.diff(first))
    valid = row[:n] == row[kind.length - 1 :]
    change = np.ones(n + 1, bool)
    change[1:n] = (key[1:] != key[:-1]) | (row[1:n] != row[: n - 1]) | (valid[1:] != valid[:-1])
    at = np.flatnonzero(change)
    begin, size = at[:-1], np.diff(at)
    good = valid[begin]
    begin, size = begin[good], size[good]
    value, last = key[begin][:, None], begin + size - 1
    inside = np.arange(width)
    leftmost = begin + np.argmax(grams[begin[:, None] + inside] == value, 1)
    rightmost = last + width - 1 - np.argmax(grams[last[:, None] + width - 1 - inside] == value, 1)
    several = leftmost != rightmost
    parts = -(-size // LONGEST)
    if (parts > 1).any():
        piece = np.arange(int(parts.sum())) - np.repeat(np.cumsum(parts) - parts, parts)
        begin, whole = np.repeat(begin, parts) + piece * LONGEST, np.repeat(size, parts)
        size, several = np.minimum(LONGEST, whole - piece * LONGEST), np.repeat(several, parts)
    return row[begin], begin - first[row[begin]], size, key[begin] & KEY, several


def _keys(kind: Kind):
    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in light_batches(batches):
            k1, k2 = column(batch, "k1").to_numpy(), column(batch, "k2").to_numpy()
            found: list[tuple] = []
            for at, _, buffer, starts in text_slices(column(batch, "text"), b"\n"):
                row, low, size, key, several = segments(*kind.units(buffer, starts), kind)
                found.append((row + at, (low << 9) | (several << 8) | size, key, several))
            if not found:
                continue
            row, seg, key, several = (np.concatenate([f[i] for f in found]) for i in range(4))
            if not len(key):
                continue
            order = np.argsort(key, kind="stable")
            edge = np.flatnonzero(np.concatenate([[True], key[order][1:] != key[order][:-1]]))
            runs = np.diff(np.append(edge, len(order)))
            often = runs >= OFTEN_HERE
            n = 1 + several.astype(np.int32)
            if often.any():
                inside = np.repeat(often, runs)
                some = order[inside]
                n[some] = -1
                lead = order[edge[often]]
                n[lead] = -runs[often]
                rest = np.setdiff1d(some, lead)
                key[rest] = np.random.default_rng(int(key[0])).integers(1 << 48, 1 << 63, len(rest), dtype=np.uint64)  # kept, alone
            yield pa.RecordBatch.from_arrays(
                [pa.array(key.view(np.int64)), pa.array(k1[row]), pa.array(k2[row]), pa.array(seg), pa.array(n)],
                names=["key", "k1", "k2", "seg", "n"],
            )

    return run


def _cutting(kind: Kind):
    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in light_batches(batches):
            k1, k2 = column(batch, "k1").to_pylist(), column(batch, "k2").to_pylist()
            lists = column(batch, "segs")
            inner = lists.flatten()
            seg, key, often = (inner.field(c).to_numpy(zero_copy_only=False) for c in ("seg", "key", "often"))
            bounds = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy())])
            seen: dict[tuple[int, bytes], list] = {}
            gone: list[tuple] = []

            def meet(key: int, payload: bytes, here: tuple, size: int, several: int = 0) -> None:
                old = seen.get((key, payload))
                if old is None:
                    seen[key, payload] = [here, size, several, 1]
                    return
                old[3] += 1
                if kind.keep_first and here == old[0]:
                    return  # a repeated row: the same place once more
                if kind.keep_first and here < old[0]:
                    old[0], here = here, old[0]
                gone.append((*here, size))

            for i, text in enumerate(column(batch, "text")):
                units = kind.pieces(text.as_py().encode())
                for j in range(bounds[i], bounds[i + 1]):
                    low, several, size = int(seg[j]) >> 9, int(seg[j]) >> 8 & 1, int(seg[j]) & 255
                    if often[j]:
                        for w in range(low, low + size):
                            digest = xxhash.xxh3_128_digest(kind.pack(units[w : w + kind.length]))
                            meet(int.from_bytes(digest[:8], "little", signed=True), digest, (k1[i], k2[i], w), 1)
                    else:
                        meet(int(key[j]), kind.pack(units[low : low + size - 1 + kind.length]), (k1[i], k2[i], low), size, several)
            rows = [(k, *here, size, several, count, payload) for (k, payload), (here, size, several, count) in seen.items()]
            rows += _joined(gone, kind.length)
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 8
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["key", "k1", "k2", "low", "size", "several", "copies", "payload"])

    return run


def _joined(gone: list[tuple], length: int) -> list[tuple]:
    """Rows for the spans (k1, k2, first window, windows) that go, those that meet or overlap as one."""
    out: list[list] = []
    for k1, k2, low, size in sorted(gone):
        last = out[-1] if out else None
        if last is not None and last[1] == k1 and last[2] == k2 and low <= last[3] + last[4] - 1 + length:
            last[4] = max(last[4], low + size - last[3])
        else:
            out.append([k2, k1, k2, low, size, 0, 0, None])
    return [tuple(r) for r in out]


class _Shard:
    """Groups of equal key; unequal payloads of a group wait for the index."""

    def __init__(self, kind: Kind):
        self.kind = kind
        self.out: list[tuple[np.ndarray, ...]] = []
        self.waiting: list[tuple] = []
        self.units = 0

    def spans(self, k1, k2, low, windows) -> None:
        self.out.append((np.asarray(k1, np.int64), np.asarray(k2, np.int64), np.asarray(low, np.int64), np.asarray(low, np.int64) + windows - 1 + self.kind.length))

    def groups(self, rows: pa.Table) -> None:
        """Whole groups: equal payloads are settled at once, the earliest stands for each in the index."""
        told = rows.column("payload").is_null().to_numpy()
        if told.any():
            some = rows.filter(pa.array(told))
            self.spans(*(some.column(c).to_numpy() for c in ("k1", "k2", "low", "size")))
            rows = rows.filter(pa.array(~told))
        n = rows.num_rows
        if not n:
            return
        key, k1, k2, low, size, several, copies = (rows.column(c).to_numpy() for c in ("key", "k1", "k2", "low", "size", "several", "copies"))
        payloads = rows.column("payload").combine_chunks().dictionary_encode()
        payloads = payloads.combine_chunks() if isinstance(payloads, pa.ChunkedArray) else payloads
        string, payloads = payloads.indices.to_numpy(), payloads.dictionary
        order = np.lexsort((low, k2, k1, string, key))
        key, string = key[order], string[order]
        new_key = np.concatenate([[True], key[1:] != key[:-1]])
        new_payload = new_key | np.concatenate([[True], string[1:] != string[:-1]])
        lead = np.flatnonzero(new_payload)
        total = np.add.reduceat(copies[order], lead)
        runs = np.diff(np.append(lead, n))
        group = np.cumsum(new_key[lead]) - 1
        chosen = np.bincount(group) > 1
        chosen[group[several[order[lead]] > 0]] = True  # windows of one segment can be equal
        if self.kind.keep_first:
            first = order[np.repeat(lead, runs)]
            at = order[np.repeat(total > 1, runs) & ((k1[order] != k1[first]) | (k2[order] != k2[first]) | (low[order] != low[first]))]
            self.spans(k1[at], k2[at], low[at], size[at])  # the first of equal strings stands for them
            runs = np.ones_like(runs)
        else:
            chosen[group[total > 1]] = True
        last = -1
        for i, n_rows, many, own in zip(lead[chosen[group]].tolist(), runs[chosen[group]].tolist(), (total > 1)[chosen[group]].tolist(), group[chosen[group]].tolist(), strict=True):
            if own != last and self.units >= INDEX_UNITS:
                self.flush()
            last = own
            rows_ = order[i : i + n_rows]
            self.waiting.append((payloads[int(string[i])].as_py(), int(size[order[i]]), many, k1[rows_], k2[rows_], low[rows_]))
            self.units += int(size[order[i]]) + self.kind.length

    def flush(self) -> None:
        if not self.waiting:
            return
        payloads, sizes, many, k1, k2, low = zip(*self.waiting, strict=True)
        sizes, many, places = np.array(sizes), np.array(many), np.array([len(x) for x in k1])
        k1, k2, low = np.concatenate(k1), np.concatenate(k2), np.concatenate(low)
        begin = np.cumsum(places) - places
        doc = np.unique(np.rec.fromarrays([k1[begin], k2[begin]]), return_inverse=True)[1]
        goes = self.kind.solve(list(payloads), sizes, many, doc, low[begin])
        owner = np.repeat(np.arange(len(sizes)), sizes)
        offset = np.arange(len(owner)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
        on = goes.astype(np.int8)
        first = np.flatnonzero(goes & ((offset == 0) | np.concatenate([[True], on[:-1] == 0])))
        last = np.flatnonzero(goes & np.concatenate([(offset[1:] == 0) | (on[1:] == 0), [True]]))
        n = places[owner[first]]  # a run goes at all places of its string
        at = np.repeat(begin[owner[first]] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        self.spans(k1[at], k2[at], low[at] + np.repeat(offset[first], n), np.repeat(last - first + 1, n))
        self.waiting, self.units = [], 0

    def batch(self) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.int64(), pa.int64())
        columns = [np.concatenate(c) for c in zip(*self.out, strict=True)] if self.out else [[]] * 4
        self.out = []
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds, strict=True)], names=["k1", "k2", "first", "past"])


def _solving(kind: Kind):
    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shard, rest = _Shard(kind), []
        for batch in batches:
            if not batch.num_rows:
                continue
            key = column(batch, "key").to_numpy()
            cut = int(np.searchsorted(key, key[-1]))  # the last key may go on
            if not cut and rest and column(rest[-1], "key")[-1].as_py() == int(key[-1]):
                rest.append(batch)
                continue
            shard.groups(pa.Table.from_batches([*rest, batch.slice(0, cut)]))
            rest = [batch.slice(cut)]
            yield shard.batch()
        if rest:
            shard.groups(pa.Table.from_batches(rest))
        shard.flush()
        yield shard.batch()

    return run


def _applying(kind: Kind):
    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in light_batches(batches):
            n, removed, runs, kept = [], [], [], []
            for text, spans, all_ in zip(column(batch, "text"), column(batch, "spans").to_pylist(), column(batch, "all").to_pylist(), strict=True):
                units = kind.pieces(text.as_py().encode())
                size = len(units)
                n.append(size)
                if all_ and size >= kind.length:
                    spans = [{"first": 0, "past": size}]
                keep, at, gone, count = [], 0, 0, 0
                for s in sorted(spans or (), key=lambda s: (s["first"], s["past"])):
                    a, b = s["first"], s["past"]
                    if a > at or not count:
                        keep.append(units[at:a])
                        count += 1
                        at = a
                    if b > at:
                        gone += b - at
                        at = b
                keep.append(units[at:])
                removed.append(gone)
                runs.append(count)
                kept.append(kind.join(keep))
            names = [c for c in batch.schema.names if c not in ("spans", "all")]
            new = [pa.array(x, pa.int64()) for x in (n, removed, runs)]
            yield pa.RecordBatch.from_arrays([*[column(batch, c) for c in names], *new, pa.array(kept, pa.binary())], names=[*names, "n_units", "n_removed", "n_spans", "kept_bytes"])

    return run


def remove(docs: DataFrame, kind: Kind, carry: list[str] | None = None) -> DataFrame:
    """doc_id (long), text (null made empty), the columns ``carry``, n_units, n_removed, n_spans and kept_bytes for each row."""
    carry = carry or []
    text = F.coalesce("text", F.lit(""))
    digest = F.md5(text.cast("binary"))
    half = lambda k: F.conv(F.substring(digest, k, 16), 16, -10).cast("long")
    # the lowest bit of k2 tells rows without an id; neither can be null, else joins would filter some of the readings of one exchange
    own = [F.coalesce(F.col("doc_id").cast("long"), half(1), F.lit(0)).alias("k1"), F.coalesce(half(17), F.lit(0)).bitwiseAND(F.lit(-2)).bitwiseOR(F.col("doc_id").isNull().cast("long")).alias("k2")]
    text = text.alias("text")
    keyed = docs.select(*own, text)
    narrow = docs.select(*own, F.unhex(digest).alias("digest"))
    firsts = narrow.groupBy("digest").agg(F.min(F.struct("k1", "k2")).alias("lead"), F.count("*").alias("copies"))
    flags = narrow.distinct().join(firsts, "digest").select("k1", "k2", (F.struct("k1", "k2") == F.col("lead")).alias("lead"), "copies")
    flags = staged(flags.groupBy("k1", "k2").agg(F.max("lead").alias("lead"), F.max("copies").alias("copies")), "flags")

    leads = keyed.join(flags.where("lead").select("k1", "k2"), ["k1", "k2"])
    keys = leads.mapInArrow(_keys(kind), "key long, k1 long, k2 long, seg long, n int")
    same = Window.partitionBy("key")
    keys = keys.select("*", F.sum(F.abs("n")).over(same).alias("all"), (F.min("n").over(same) < 0).alias("frequent"))
    kept = keys.where("all > 1 or n < 0").select("k1", "k2", F.struct("seg", "key", (F.col("frequent") | (F.col("all") > OFTEN)).alias("often")).alias("s"))
    lists = kept.groupBy("k1", "k2").agg(F.collect_list("s").alias("segs"))  # at most the segments of one text
    cut = keyed.join(lists, ["k1", "k2"]).mapInArrow(_cutting(kind), "key long, k1 long, k2 long, low long, size long, several int, copies int, payload binary")
    spans = cut.repartition("key").sortWithinPartitions("key").mapInArrow(_solving(kind), "k1 long, k2 long, first long, past long")
    spans = spans.groupBy("k1", "k2").agg(F.collect_list(F.struct("first", "past")).alias("spans"))

    whole = keyed if not carry else docs.select(*own, text, *[f"`{c}`" for c in carry])
    everything = (~F.col("lead")) if kind.keep_first else (F.col("copies") > 1)
    ready = whole.join(flags.select("k1", "k2", everything.alias("all")), ["k1", "k2"], "left").join(spans, ["k1", "k2"], "left")
    ready = ready.select(F.when(F.col("k2").bitwiseAND(F.lit(1)) == 0, F.col("k1")).alias("doc_id"), "text", *[f"`{c}`" for c in carry], "spans", "all")
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in ready.schema if f.name not in ("spans", "all"))
    return ready.mapInArrow(_applying(kind), f"{kinds}, n_units long, n_removed long, n_spans long, kept_bytes binary")
