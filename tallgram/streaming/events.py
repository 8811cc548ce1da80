"""Event streams: windows, sessions, de-duplication, and rows assembled from a stream."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tallgram.sources.tables import SCHEMAS
from tallgram.sources.workloads import user_day


def stream_events(spark: SparkSession, path: str, files_per_trigger: int | None = None) -> DataFrame:
    """The events files of a folder as a stream, ts as a timestamp (UTC) so that it can be watermarked."""
    reader = spark.readStream.schema(SCHEMAS["events"])
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def watermarked(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late)


def emissions_per_day(events: DataFrame) -> DataFrame:
    """(day, n, users): events of each day; users approximately."""
    return events.groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("day"), "n")


def activity_sliding(events: DataFrame, size: str = "1 day", step: str = "6 hours") -> DataFrame:
    """(start, event_type, n, total) of sliding windows."""
    grouped = events.groupBy(F.window("ts", size, step).alias("w"), "event_type")
    return grouped.agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "event_type", "n", "total")


def user_sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, n) of sessions: runs of events of one user without a longer gap."""
    return events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def dedup_events(events: DataFrame) -> DataFrame:
    """Each event_id once, among those within the watermark."""
    return events.dropDuplicatesWithinWatermark(["event_id"])


def click_to_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """(click, purchase) pairs of one user, the purchase at most ``within`` after the click: a stream-stream join."""
    click = events.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u"), F.col("ts").alias("click_ts"))
    bought = events.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("v"), F.col("ts").alias("buy_ts"))
    return click.join(bought, F.expr(f"u = v and buy_ts >= click_ts and buy_ts <= click_ts + interval {within}")).select("click", "purchase")


def with_norms(events: DataFrame, norms: DataFrame) -> DataFrame:
    """Events with the norm of their column (label, norm) from a static snapshot: a stream-static join."""
    label = F.get_json_object("props", "$.k").cast("int")
    return events.withColumn("label", label).join(F.broadcast(norms.select("label", "norm")), "label")


def assemble_rows(events: DataFrame) -> DataFrame:
    """(row_id, labels): the distinct keys of each user and day (of UTC) as a matrix row, put out when the day is over.

    A day's window is the state of an open row; the watermark closes it.
    """
    keyed = events.select("user_id", "ts", F.get_json_object("props", "$.k").cast("int").alias("label"))
    rows = keyed.groupBy("user_id", F.window("ts", "1 day").alias("w")).agg(F.sort_array(F.collect_set("label")).alias("labels"))
    return rows.select((F.shiftleft("user_id", 20) + F.expr("unix_micros(w.start) div 86400000000")).alias("row_id"), "labels")
