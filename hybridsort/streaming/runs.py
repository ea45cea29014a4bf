"""Streams: chunks in, runs out, merged later; windows, histograms and dedup over events."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.keys import uniform_binary
from ..operators.external import make_runs, merge_runs
from ..sources.tables import scratch, table


def source(spark: SparkSession, sf_dir: str, name: str, files: int = 4) -> DataFrame:
    """A stream over a table that is first laid out as several files."""
    batch = table(spark, sf_dir, name)
    path = scratch(spark, f"stream-{name}")
    batch.repartition(files).write.parquet(path)
    return spark.readStream.schema(batch.schema).option("maxFilesPerTrigger", 1).parquet(path)


def _drain(stream: DataFrame, spark: SparkSession, tag: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there, into files, and read the result."""
    path, marks = scratch(spark, tag), scratch(spark, f"{tag}-marks")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/{number % 2}")
        put.last = number % 2

    stream.writeStream.outputMode(mode).foreachBatch(put).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/{put.last}")


def sorted_from_stream(spark: SparkSession, sf_dir: str, most: int = 500) -> DataFrame:
    """Each micro-batch becomes a sorted run; the runs are merged by range at the end, in rounds where more than ``most`` meet."""
    stream = source(spark, sf_dir, "events").select(uniform_binary("event_id").alias("k"), "event_id")
    path, marks = scratch(spark, "runs"), scratch(spark, "runs-marks")

    def put(batch: DataFrame, number: int) -> None:
        batch.sortWithinPartitions("k", "event_id").write.mode("overwrite").parquet(f"{path}/batch={number}")

    stream.writeStream.foreachBatch(put).option("checkpointLocation", marks).trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(path)
    target = max(1000, min(2_000_000, rows.count() // 8))
    return merge_runs(make_runs(rows, "k", ["event_id"], 10, target // 10, target, run_of="batch"), "kway", most)


def histogram_from_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of the first digit, kept up to date; the last state."""
    stream = source(spark, sf_dir, "events").select(F.substring(uniform_binary("event_id"), 1, 2).alias("prefix"))
    return _drain(stream.groupBy("prefix").agg(F.count("*").alias("n")), spark, "histogram", "complete")


def windows_from_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events an hour and type, with a watermark that is later than any delay between files."""
    stream = source(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "3650 days")
    out = _drain(stream.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")), spark, "windows", "complete")
    return out.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def dedup_from_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events sent twice, kept once."""
    events = source(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "3650 days")
    return _drain(events.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"), spark, "dedup")
