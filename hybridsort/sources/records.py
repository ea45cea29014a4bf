"""Fixed-width record files: a source that reads aligned byte ranges in parallel, a sink, and a generator."""

from __future__ import annotations

import os
from collections import deque
from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceArrowWriter, DataSourceReader, InputPartition, WriterCommitMessage


@dataclass
class ByteRange(InputPartition):
    path: str
    start: int
    length: int


@dataclass
class PartFile(WriterCommitMessage):
    path: str
    rows: int


def local(path: str) -> str:
    """A path for ``open``: the scheme of local files is taken off, any other is refused."""
    scheme, colon, rest = path.partition(":")
    if not colon or "/" in scheme:
        return path
    if scheme != "file":
        raise ValueError(f"{path}: the workers open this path themselves, so it has to be one of theirs, such as a mounted folder")
    return "/" + rest.lstrip("/")


class FixedRecords(DataSource):
    """Format ``fixed_records``: options path, record_bytes (100), key_bytes (10), request_bytes (262144), queue_depth (4), split_bytes.

    The path must be one that the workers can open. ``request_bytes`` is what one read asks for, ``queue_depth`` how many reads a task has under way;
    ``split_bytes`` is what one task reads; both are rounded down to whole records.
    """

    @classmethod
    def name(cls) -> str:
        return "fixed_records"

    def schema(self) -> str:
        return "key binary, value binary"

    def reader(self, schema) -> "FixedReader":
        return FixedReader(self.options)

    def writer(self, schema, overwrite: bool) -> "FixedWriter":
        return FixedWriter(self.options)


class FixedReader(DataSourceReader):
    def __init__(self, options):
        self.path = local(options["path"])
        self.record, self.key = int(options.get("record_bytes", 100)), int(options.get("key_bytes", 10))
        whole = lambda n: max(1, n // self.record) * self.record
        self.depth = max(1, int(options.get("queue_depth", 4)))
        self.request, self.split = whole(int(options.get("request_bytes", 262144))), whole(int(options.get("split_bytes", 128 << 20)))

    def partitions(self) -> list[InputPartition]:
        from pathlib import Path

        root = Path(self.path)
        files = sorted(root.glob("part-*")) if root.is_dir() else [root]
        out = []
        for f in files:
            size = f.stat().st_size
            if size % self.record:
                raise ValueError(f"{f} has {size} bytes, no whole number of {self.record}-byte records")
            out += [ByteRange(str(f), at, min(self.split, size - at)) for at in range(0, size, self.split)]
        return out

    def read(self, partition: ByteRange) -> Iterator[pa.RecordBatch]:
        with open(partition.path, "rb") as f, ThreadPoolExecutor(self.depth) as pool:
            end = partition.start + partition.length
            waiting: deque = deque()
            at = partition.start
            while at < end or waiting:
                while at < end and len(waiting) < self.depth:  # so many requests are under way together
                    waiting.append(pool.submit(os.pread, f.fileno(), min(self.request, end - at), at))
                    at += self.request
                data = waiting.popleft().result()
                n = len(data) // self.record
                rows = np.frombuffer(data, np.uint8).reshape(n, self.record)
                yield pa.RecordBatch.from_arrays([_fixed(rows[:, : self.key]), _fixed(rows[:, self.key :])], names=["key", "value"])


def _fixed(rows: np.ndarray) -> pa.Array:
    """Rows of bytes as binary values, without a Python object for each."""
    n, size = rows.shape
    offsets = np.arange(n + 1, dtype=np.int32) * np.int32(size)
    return pa.BinaryArray.from_buffers(pa.binary(), n, [None, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(rows))])


def _rows(values: pa.Array, size: int) -> np.ndarray:
    """Binary values of one size, none of them null, as rows of bytes."""
    _, offsets, data = values.buffers()
    first = int(np.frombuffer(offsets, np.int32)[values.offset])
    return np.frombuffer(data, np.uint8, len(values) * size, first).reshape(-1, size)


class FixedWriter(DataSourceArrowWriter):
    """Part files in partition order; the names sort as the partitions do."""

    def __init__(self, options):
        self.path, self.record = local(options["path"]), int(options.get("record_bytes", 100))

    def write(self, batches: Iterator[pa.RecordBatch]) -> PartFile:
        from pathlib import Path

        from pyspark import TaskContext

        root = Path(self.path)
        root.mkdir(parents=True, exist_ok=True)
        context = TaskContext.get()
        to = root / f".{context.partitionId():06d}-{context.taskAttemptId()}"
        rows = 0
        with to.open("wb") as f:
            for batch in batches:
                if not batch.num_rows:
                    continue
                sizes = [pc.unique(pc.binary_length(c)).to_pylist() for c in batch.columns[:2]]
                if any(len(n) != 1 or n[0] is None for n in sizes) or sizes[0][0] + sizes[1][0] != self.record:
                    raise ValueError(f"records have keys of {sizes[0]} and values of {sizes[1]} bytes, which is not {self.record} together")
                f.write(np.hstack([_rows(c, n[0]) for c, n in zip(batch.columns[:2], sizes, strict=True)]).tobytes())
                rows += batch.num_rows
        return PartFile(str(to), rows)

    def commit(self, messages) -> None:
        from pathlib import Path

        for m in messages:
            if m is not None:
                at = Path(m.path)
                at.rename(at.with_name(f"part-{at.name[1:7]}"))

    def abort(self, messages) -> None:
        from pathlib import Path

        for m in messages:
            if m is not None:
                Path(m.path).unlink(missing_ok=True)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(FixedRecords)


def records(df: DataFrame, key: Column, payload: list[str], value_bytes: int = 90) -> DataFrame:
    """key (bytes of a hex key) and a value of fixed size: the columns joined by bars, padded with blanks."""
    text = F.rpad(F.concat_ws("|", *[F.col(c).cast("string") for c in payload]), value_bytes, " ")
    return df.select(F.unhex(key).alias("key"), text.cast("binary").alias("value"))
