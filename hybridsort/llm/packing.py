"""Bounded-space online packing of token ids into fixed-length training sequences.

Every input partition keeps a fixed number of open windows. A document is its token ids and one
separator; whole windows are cut off its front, the rest goes best-fit into an open window. When no
window has room, the fullest leaves: topped up with the front of the waiting piece if its gap is
worth a cut, else as it is. The windows still open at the end of the partitions are merged in
rounds of a fixed fan-in, so that no task ever holds more than ``fan_in * open_windows`` windows and
all but the last sequence of a merge are full.

Defined results: null or empty text is the separator alone; a null id is carried along; repeated
rows are packed once each; an empty table gives no pieces; columns other than the id and the text
are ignored; a very long text fills windows of its own and leaves its rest.
"""

from __future__ import annotations

import base64
import re
import zlib
from array import array
from collections.abc import Iterator
from pathlib import Path

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import column, light_batches, staged, tidy

#: A blank after white space: only there may a split at blanks part what the tokenizer keeps together.
UNEVEN = re.compile(r"\s ")
CACHE = 300_000
FIELDS = "start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, unfinished boolean, ids binary"


class _Ids(dict):
    """Ids (as little-endian unsigned 32-bit bytes) of a word with its blank before it, kept for words already met."""

    def __init__(self, encode, lead: str):
        super().__init__()
        self.encode, self.lead = encode, lead

    def __missing__(self, word: str) -> bytes:
        if len(self) >= CACHE:
            self.clear()
        found = array("I", self.encode(self.lead + word)).tobytes()
        if len(word) < 48:
            self[word] = found
        return found


#: Fixed value: the special token of the vocabulary, which is one id wherever its string stands in a text.
SPECIAL, SPECIAL_ID = "<|endoftext|>", 50256


class Encoder:
    """Byte-level BPE ids from a public vocabulary file; the same ids as the ``tokenizers`` file of that vocabulary.

    The special token parts a text, and each part is encoded by itself. A blank after a character that is no white space always begins a new pre-token, so a text
    without doubled white space can be cut at its blanks and each word looked up.
    """

    def __init__(self, ranks_path: str, pattern: str):
        import tiktoken

        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, Path(ranks_path).open("rb"))}
        self.encode = tiktoken.Encoding("byte_bpe", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}).encode_ordinary
        self.first, self.rest = _Ids(self.encode, ""), _Ids(self.encode, " ")

    def forget(self) -> None:
        """Let go of the words met, as the worker lives on."""
        self.first.clear()
        self.rest.clear()

    def __call__(self, text: str) -> bytes:
        if SPECIAL in text:
            return array("I", [SPECIAL_ID]).tobytes().join(map(self.plain, text.split(SPECIAL)))
        return self.plain(text)

    def plain(self, text: str) -> bytes:
        if UNEVEN.search(text):
            return array("I", self.encode(text)).tobytes()
        head, *rest = text.split(" ")
        if not text:
            return b""
        return self.first[head] + b"".join(map(self.rest.__getitem__, rest))


_encoders: dict[str, Encoder] = {}


def encoder(vocabulary: str | None) -> Encoder:
    """One encoder per worker and vocabulary; None is the installed public one."""
    if (key := vocabulary or "") not in _encoders:
        import public_tokenizers as public

        _encoders[key] = Encoder(vocabulary or public.path("byte_bpe_50k.tiktoken"), public.PATTERN)
    return _encoders[key]


class _Rows:
    """Finished rows, gathered by column."""

    def __init__(self, keep_ids: bool):
        self.keep_ids = keep_ids
        self.columns: list[list] = [[] for _ in range(9)]

    def window(self, sequence: int, pieces: list, unfinished: bool) -> None:
        at = 0
        for key, start, ids, total in pieces:
            length = len(ids) >> 2
            for c, v in zip(self.columns, (key, start, length, zlib.crc32(ids), total, sequence, at, unfinished, ids if unfinished or self.keep_ids else None), strict=True):
                c.append(v)
            at += length

    def batch(self, schema: pa.Schema) -> pa.RecordBatch:
        out = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(self.columns, schema, strict=True)], schema=schema)
        self.columns = [[] for _ in range(9)]
        return out


def _schema(key_type: pa.DataType) -> pa.Schema:
    long = pa.int64()
    return pa.schema([("doc_id", key_type), ("start", long), ("length", long), ("ids_crc32", long), ("doc_tokens", long), ("sequence_id", long), ("offset", long), ("unfinished", pa.bool_()), ("ids", pa.binary())])


def _pack_partition(batches: Iterator[pa.RecordBatch], size: int, open_windows: int, least_cut: int, vocabulary: str | None, keep_ids: bool) -> Iterator[pa.RecordBatch]:
    encode = encoder(vocabulary)
    number = TaskContext.get().partitionId() << 32
    windows: list[list] = []  # [gap, sequence id, pieces]
    rows, schema = _Rows(keep_ids), None

    for batch in light_batches(batches):
        schema = schema or _schema(column(batch, "doc_id").type)
        for key, text in zip(column(batch, "doc_id").to_pylist(), column(batch, "text"), strict=True):
            ids = encode(text.as_py() or "") + b"\0\0\0\0"
            total, start = len(ids) >> 2, 0
            while total - start >= size:
                rows.window(number, [(key, start, ids[4 * start : 4 * (start + size)], total)], False)
                start, number = start + size, number + 1
            while start < total:
                need = total - start
                best = min((w for w in windows if w[0] >= need), default=None, key=lambda w: w[0])
                if best is None and len(windows) == open_windows:
                    fullest = min(windows, key=lambda w: w[0])
                    windows.remove(fullest)
                    if fullest[0] >= least_cut:
                        fullest[2].append((key, start, ids[4 * start : 4 * (start + fullest[0])], total))
                        start += fullest[0]
                    rows.window(fullest[1], fullest[2], False)
                    continue
                if best is None:
                    best = [size, number, []]
                    number += 1
                    windows.append(best)
                best[2].append((key, start, ids[4 * start :], total))
                best[0] -= need
                start = total
                if not best[0]:
                    windows.remove(best)
                    rows.window(best[1], best[2], False)
            if len(rows.columns[0]) >= 4096:
                yield rows.batch(schema)
    encode.forget()
    if schema is not None:
        for _, sequence, pieces in windows:
            rows.window(sequence, pieces, True)
        yield rows.batch(schema)


def _merge(group: pa.Table, size: int, last: bool, keep_ids: bool) -> pa.Table:
    """Fill the fullest windows of a group with pieces of the emptiest, cut where needed."""
    schema = pa.schema([f for f in group.schema if f.name != "merge_group"])
    open_: dict[int, list] = {}
    for r in group.sort_by([("sequence_id", "ascending"), ("offset", "ascending")]).select(["sequence_id", "doc_id", "start", "ids", "doc_tokens"]).to_pylist():
        open_.setdefault(r["sequence_id"], []).append((r["doc_id"], r["start"], r["ids"], r["doc_tokens"]))
    windows = sorted(([size - sum(len(p[2]) >> 2 for p in pieces), s, pieces] for s, pieces in open_.items()), key=lambda w: (w[0], w[1]))
    i, j = 0, len(windows) - 1
    while i < j:
        fullest, emptiest = windows[i], windows[j]
        if not fullest[0]:
            i += 1
            continue
        if not emptiest[2]:
            j -= 1
            continue
        key, start, ids, total = emptiest[2].pop()
        take = min(fullest[0], len(ids) >> 2)
        fullest[2].append((key, start, ids[: 4 * take], total))
        fullest[0] -= take
        emptiest[0] += take
        if take < len(ids) >> 2:
            emptiest[2].append((key, start + take, ids[4 * take :], total))
    rows = _Rows(keep_ids)
    for gap, sequence, pieces in windows:
        if pieces:
            rows.window(sequence, pieces, bool(gap) and not last)
    return pa.Table.from_batches([rows.batch(schema)])


def _merging(size: int, last: bool, keep_ids: bool):
    def merge(group):
        return _merge(group, size, last, keep_ids)

    return merge


def pack(docs: DataFrame, size: int = 1024, open_windows: int = 32, least_cut: int = 8, fan_in: int = 64, vocabulary: str | None = None, keep_ids: bool = True) -> DataFrame:
    """Pieces of all documents: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset, ids.

    ``ids`` holds little-endian unsigned 32-bit ids (null unless keep_ids). The pieces are staged,
    as the merging of leftovers reads them again.
    """
    source = docs.select("doc_id", "text")
    key = source.schema["doc_id"].dataType.simpleString()
    parts = source.rdd.getNumPartitions()
    out = f"doc_id {key}, {FIELDS}"

    @tidy
    def pack_partition(batches):
        return _pack_partition(batches, size, open_windows, least_cut, vocabulary, keep_ids)

    left = staged(source.mapInArrow(pack_partition, out), "packed")
    done, groups = [left.where(~F.col("unfinished"))], parts
    left = left.where("unfinished")
    while True:
        groups = -(-groups // fan_in)
        last = groups <= 1

        step = left.withColumn("merge_group", F.shiftright("sequence_id", 32) % groups).groupBy("merge_group").applyInArrow(_merging(size, last, keep_ids), out)
        if last:
            done.append(step)
            break
        step = staged(step, "merged")
        done.append(step.where(~F.col("unfinished")))
        left = step.where("unfinished")
    whole = done[0]
    for part in done[1:]:
        whole = whole.unionByName(part)
    return whole.drop("unfinished")
