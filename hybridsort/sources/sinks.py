"""Sorted output: files by range with a manifest, and bucketed tables."""

from __future__ import annotations

import uuid

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..measures import checksum
from .tables import scratch


def write_sorted(ordered: DataFrame, path: str, key: str, rows_per_part: int = 2_000_000, durability: str = "durable") -> DataFrame:
    """Write an ordered result as one sorted file a part, and return its manifest: part, rows, low, high, checksum.

    ``cached`` keeps the rows in executor memory and disk while they are written, which is no
    durability; ``durable`` relies on the committed files alone.
    """
    out = ordered.withColumn("part", F.floor((F.col("position") - 1) / rows_per_part).cast("int"))
    if durability == "cached":
        out = out.persist(StorageLevel.MEMORY_AND_DISK)
    parts = (out.agg(F.max("part")).first()[0] or 0) + 1
    out.repartitionById(parts, F.col("part")).sortWithinPartitions("position").write.mode("overwrite").partitionBy("part").parquet(path)
    if durability == "cached":
        out.unpersist()
    return manifest(ordered.sparkSession.read.parquet(path), key)


def manifest(written: DataFrame, key: str) -> DataFrame:
    return written.groupBy("part").agg(F.count("*").alias("rows"), F.min(key).alias("low"), F.max(key).alias("high"), checksum(F.col(key)).alias("checksum"))


def write_bucketed(df: DataFrame, buckets: int, *columns: str, name: str | None = None) -> DataFrame:
    """A table whose later joins and groupings on the columns need no exchange, nor a sort where a bucket is one file."""
    name = name or f"bucketed_{uuid.uuid4().hex}"
    spread = df.repartition(buckets, *columns)
    spread.write.mode("overwrite").bucketBy(buckets, *columns).sortBy(*columns).option("path", scratch(df.sparkSession, "bucketed")).saveAsTable(name)
    return df.sparkSession.table(name)


def with_pointer(df: DataFrame) -> DataFrame:
    """A scan of files with the pointer ``file`` and ``row`` of each record."""
    return df.select("*", F.col("_metadata.file_path").alias("file"), F.col("_metadata.row_index").alias("row"))
