"""Streams over event time: ordered emission, late rows, sliding and session windows, joins.

The inputs are tables laid out as files. A last file holds one row far in the future, which moves the
watermark past all others, so that whatever waits for it is given out; that row is not.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..sources.tables import scratch, table
from .runs import _drain

#: How much later than its time a row may come here, and where the last row stands beyond the others.
DELAY, BEYOND = "3650 days", 8000


def _laid_out(spark: SparkSession, batches: list[DataFrame], tag: str) -> DataFrame:
    """A stream that reads the batches in turn, a file each."""
    path = scratch(spark, f"stream-{tag}")
    for i, batch in enumerate(batches):
        batch.coalesce(1).write.mode("append").parquet(f"{path}/part={i:04d}")
    return spark.readStream.schema(batches[0].schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/*")


def _events(spark: SparkSession, sf_dir: str, files: int = 3) -> tuple[list[DataFrame], DataFrame]:
    """The events as some batches, and the row that ends the stream."""
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type")
    last = events.agg(F.max("ts").alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), F.date_add("ts", BEYOND).cast("timestamp").alias("ts"), F.lit(-1).cast("long").alias("user_id"), F.lit("end").alias("event_type"))
    return [events.where(F.pmod("event_id", F.lit(files)) == i) for i in range(files)], last


def ordered_emission(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of an hour wait until the watermark has passed it, and come out in order: hour, place, event_id."""
    batches, last = _events(spark, sf_dir)
    stream = _laid_out(spark, [*batches, last], "ordered").withWatermark("ts", DELAY)
    stream = stream.withColumn("hour", F.date_trunc("hour", "ts"))

    def hold(key: tuple, rows: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            ids, times = state.get
            state.remove()
            order = sorted(range(len(ids)), key=lambda i: (times[i], ids[i]))
            yield pd.DataFrame({"hour": [key[0]] * len(ids), "place": range(1, len(ids) + 1), "event_id": [ids[i] for i in order]})
            return
        ids, times = map(list, state.get) if state.exists else ([], [])
        for part in rows:
            ids += part["event_id"].tolist()
            times += part["us"].tolist()
        state.update((ids, times))
        state.setTimeoutTimestamp(int(key[0].timestamp() * 1000) + 3_600_000)

    keyed = stream.withColumn("us", F.unix_micros("ts")).groupBy("hour")
    out = keyed.applyInPandasWithState(hold, "hour timestamp, place long, event_id long", "ids array<long>, times array<long>", "append", GroupStateTimeout.EventTimeTimeout)
    return _drain(out, spark, "ordered").where("event_id >= 0").select(F.col("hour").cast("timestamp_ntz").alias("hour"), "place", "event_id")


def late_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events an hour and type with a watermark of a day; the first thousand are sent again when all others have been, and are dropped as late."""
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type")
    last = events.agg(F.max("ts").alias("ts")).select(F.lit(-1).cast("long").alias("event_id"), F.date_add("ts", BEYOND).cast("timestamp").alias("ts"), F.lit("end").alias("event_type"))
    again = events.where("event_id <= 1000")
    stream = _laid_out(spark, [events, last, again], "late").withWatermark("ts", "1 day")
    out = _drain(stream.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")), spark, "late")
    return out.where("event_type != 'end'").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events of two hours, every hour."""
    batches, last = _events(spark, sf_dir)
    stream = _laid_out(spark, [*batches, last], "sliding").withWatermark("ts", DELAY).where("event_id >= 0 or event_type = 'end'")
    out = _drain(stream.groupBy(F.window("ts", "2 hours", "1 hour").alias("w"), (F.col("event_id") < 0).alias("end")).agg(F.count("*").alias("n")), spark, "sliding")
    return out.where("not end").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A user's events with less than 30 minutes between them."""
    batches, last = _events(spark, sf_dir)
    stream = _laid_out(spark, [*batches, last], "sessions").withWatermark("ts", DELAY)
    out = _drain(stream.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n")), spark, "sessions")
    return out.where("user_id >= 0").select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two streams: a click and the views of the same user in the hour before it."""
    batches, _ = _events(spark, sf_dir)
    clicks = _laid_out(spark, [b.where("event_type = 'click'") for b in batches], "clicks").withWatermark("ts", DELAY).select(F.col("event_id").alias("click"), F.col("ts").alias("at"), F.col("user_id").alias("u"))
    views = _laid_out(spark, [b.where("event_type = 'view'") for b in batches], "views").withWatermark("ts", DELAY).select(F.col("event_id").alias("view"), "ts", "user_id")
    out = clicks.join(views, F.expr("u = user_id and ts between at - interval 1 hour and at"))
    return _drain(out.select("click", "view"), spark, "joined")


def static_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stream and a table: events with the segment of the customer of the same number."""
    batches, _ = _events(spark, sf_dir)
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    out = _laid_out(spark, batches, "static").join(customers, F.col("user_id") == F.col("c_custkey"))
    return _drain(out.select("event_id", "c_mktsegment"), spark, "static")
