"""Other formats: round trips through Spark's writers, and whole or fixed-length binary files."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import scratch


def roundtrip(df: DataFrame, kind: str) -> DataFrame:
    """df written as csv, json, orc or text and read back; ``text`` has one column, the row as JSON."""
    path = scratch(df.sparkSession, f"as-{kind}")
    if kind == "text":
        df.select(F.to_json(F.struct(*[f"`{c}`" for c in df.columns])).alias("value")).write.text(path)
        found = df.sparkSession.read.text(path).select(F.from_json("value", df.schema).alias("r"))
        return found.select(*[F.col("r")[c].alias(c) for c in df.columns])
    writer = df.write.format(kind)
    (writer.option("header", True) if kind == "csv" else writer).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).option("header", True).load(path)


def whole_files(spark: SparkSession, path: str) -> DataFrame:
    """path, length and content of every file below a path."""
    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path)


def binary_records(spark: SparkSession, path: str, size: int) -> DataFrame:
    """Every ``size`` bytes of the files as a row ``record``; a last piece may be shorter.

    Files of whole records are read by Spark's fixed-length input format, in splits and as a stream. It knows
    neither a shorter piece nor names with marks of patterns, so a task takes such a file as one row and cuts it.
    """
    files = whole_files(spark, path).where("length > 0")
    plain = (F.col("length") % size == 0) & ~F.col("path").rlike(r"[,*?{}\[\]\\^]")
    found = files.select("path", plain.alias("plain")).collect()  # one row a file, without its content
    out = files.where(~plain).select("content").mapInArrow(_cut(size), "record binary") if not all(r["plain"] for r in found) else None
    if names := [r["path"] for r in found if r["plain"]]:
        conf = spark._jsparkSession.sessionState().newHadoopConf()  # a copy, as the size is set in it
        pieces = spark._jsc.sc().binaryRecords(",".join(names), size, conf)
        streamed = DataFrame(spark._jsparkSession.createDataset(pieces, spark._jvm.org.apache.spark.sql.Encoders.BINARY()).toDF(), spark).toDF("record")
        out = out.unionByName(streamed) if out else streamed
    return spark.createDataFrame([], "record binary") if out is None else out


def _cut(size: int):
    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for content in batch.column(0):
                data, step = content.as_buffer(), size * 10_000
                for at in range(0, data.size, step):
                    part = data.slice(at, min(step, data.size - at))
                    ends = [*range(0, part.size, size), part.size]
                    yield pa.RecordBatch.from_arrays([pa.BinaryArray.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(np.array(ends, np.int32)), part])], names=["record"])

    return cut
