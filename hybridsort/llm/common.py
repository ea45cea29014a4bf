"""What the training-data operators share: staged tables, text buffers, word splitting."""

from __future__ import annotations

import contextlib
import ctypes
import functools
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import delete, scratch

#: The six ASCII white-space bytes; every other byte belongs to a word.
SPACE = np.zeros(256, dtype=bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True

#: Text bytes that a Python worker turns into arrays at once.
CHUNK_BYTES = 2 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Paths staged since they were last deleted, by application.
_staged: dict[str, list[str]] = {}


def staged(df: DataFrame, tag: str) -> DataFrame:
    """Write df to the shared folder and read it back: lineage is cut, and a lost executor costs nothing."""
    spark = df.sparkSession
    path = scratch(spark, tag)
    df.write.parquet(path)
    _staged.setdefault(spark.sparkContext.applicationId, []).append(path)
    return spark.read.schema(df.schema).parquet(path)


def repeatable(df: DataFrame) -> bool:
    """Whether df is read from files without an exchange, so that each partition has the same rows in the same order whenever it is computed."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    return "Scan" in plan and not any(x in plan for x in ("Exchange", "Sample", "rand(", "Python", "InArrow", "InPandas", "Scan ExistingRDD"))


def delete_staged(spark: SparkSession, keep: DataFrame) -> None:
    """Delete what was staged so far but the table ``keep``, whose rows must depend on no other."""
    files = set(keep.inputFiles())
    paths = _staged.get(spark.sparkContext.applicationId, [])
    for path in list(paths):
        name = path.rsplit("/", 1)[-1]
        if not any(f"/{name}/" in f for f in files):
            delete(spark, path)
            paths.remove(path)


def give_back() -> None:
    """Return freed memory to the system, as Python workers live on from task to task."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # other C libraries
        ctypes.CDLL(None).malloc_trim(0)


def tidy(run):
    """A function for mapInArrow that gives memory back when its task ends."""

    @functools.wraps(run)
    def tidied(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            give_back()

    return tidied


def without(df: DataFrame, *names: str) -> DataFrame:
    """df less the columns (in any case) that an operator is about to add."""
    taken = {n.lower() for n in names}
    return df.select(*[f"`{c}`" for c in df.columns if c.lower() not in taken])


def held_out(key: Column, modulus: int, remainder: int) -> Column:
    """Whether crc32 of the id as text falls in the fold that nothing is learned from; a null id never does."""
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % modulus == remainder, F.lit(False))


def text_slices(texts: pa.Array, gap: bytes = b"\n", limit: int = CHUNK_BYTES) -> Iterator[tuple[int, int, bytes, np.ndarray]]:
    """Runs of rows as one buffer: (first row, rows, bytes, starts).

    Row i of a run is bytes[starts[i] : starts[i + 1] - len(gap)]; null counts as empty. A run
    ends once it holds ``limit`` bytes, so that a batch of long texts is taken in pieces, and a
    single text is never cut.
    """
    texts = pc.fill_null(texts, "") if texts.null_count else texts
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    wide = pa.types.is_large_string(texts.type)
    _, offsets, data = texts.buffers()
    n = len(texts)
    if not n:
        return
    ends = np.frombuffer(offsets, np.int64 if wide else np.int32)[texts.offset : texts.offset + n + 1].astype(np.int64)
    raw = memoryview(data) if data is not None else memoryview(b"")
    at = 0
    while at < n:
        to = max(at + 1, int(np.searchsorted(ends, ends[at] + limit, side="right")) - 1)
        to = min(n, to)
        parts = [raw[a:b] for a, b in zip(ends[at:to].tolist(), ends[at + 1 : to + 1].tolist(), strict=True)]
        starts = np.zeros(to - at + 1, np.int64)
        np.cumsum(np.diff(ends[at : to + 1]) + len(gap), out=starts[1:])
        yield at, to - at, gap.join(parts) + gap, starts
        at = to


def light_batches(batches: Iterator[pa.RecordBatch], name: str = "text", limit: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """The same rows in batches of about ``limit`` bytes of text, so that what is made of a batch stays small."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(column(batch, name)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        parts = np.cumsum(sizes) // limit
        edges = [0, *(np.flatnonzero(np.diff(parts)) + 1).tolist(), batch.num_rows]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            yield batch.slice(a, b - a)


def split_words(buffer: bytes, starts: np.ndarray) -> tuple[list[bytes], np.ndarray, np.ndarray]:
    """Words between white space, the byte where each begins, and the first word of each row (one more at the end)."""
    space = SPACE[np.frombuffer(buffer, np.uint8)]
    begins = ~space
    begins[1:] &= space[:-1]
    at = np.flatnonzero(begins)
    return buffer.split(), at, np.searchsorted(at, starts)


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64 bits."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def gram_hashes(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` consecutive word hashes, over the whole array."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for k in range(width):
        out = out * np.uint64(0x9E3779B97F4A7C15) + hashes[k : k + n]
    return mix(out)


def packed(values: np.ndarray) -> bytes:
    """64-bit integers, compressed: all lowest bytes, then all second ones, and so on."""
    return pa.Codec("zstd", compression_level=3).compress(np.ascontiguousarray(values.view(np.uint8).reshape(-1, 8).T).tobytes(), asbytes=True) + len(values).to_bytes(8, "little")


def unpacked(value: bytes) -> np.ndarray:
    n = int.from_bytes(value[-8:], "little")
    raw = pa.Codec("zstd").decompress(value[:-8], 8 * n, asbytes=True)
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(8, n).T).reshape(-1).view(np.int64)


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def plain_names(df: DataFrame, known: tuple[str, ...] = ("doc_id", "text", "lang", "n_chars")) -> tuple[DataFrame, dict[str, str]]:
    """df with neutral names for the columns that no operator knows, and the old name of each."""
    old = {f"__c{i}": c for i, c in enumerate(df.columns) if c not in known}
    new = {c: n for n, c in old.items()}
    return df.select(*[F.col(f"`{c}`").alias(new.get(c, c)) for c in df.columns]), old


def old_names(df: DataFrame, old: dict[str, str]) -> DataFrame:
    return df.select(*[F.col(c).alias(old.get(c, c)) for c in df.columns])
