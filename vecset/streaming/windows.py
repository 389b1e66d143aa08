"""Vector sets from events: tumbling, sliding and session windows, for batch and for streams; streaming inserts into an index."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def _micros(ts: str):
    return F.unix_micros(F.col(ts).cast("timestamp"))


def tumbling(events: DataFrame, seconds: int, ts: str = "ts") -> DataFrame:
    """(user_id, week, n): windows of `seconds` since the epoch."""
    return events.groupBy("user_id", F.floor(_micros(ts) / (seconds * 1_000_000)).alias("week")).agg(F.count("*").alias("n"))


def sliding(events: DataFrame, days: int, ts: str = "ts") -> DataFrame:
    """(user_id, start_day, n): windows of `days` that start every day."""
    day = F.floor(_micros(ts) / 86_400_000_000)
    return events.select("user_id", F.explode(F.sequence(day - (days - 1), day)).alias("start_day")).groupBy("user_id", "start_day").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap_seconds: int, ts: str = "ts") -> DataFrame:
    """(user_id, s, n): a session ends where the next event is at least gap_seconds later."""
    w = Window.partitionBy("user_id").orderBy(ts, "event_id")
    new = F.coalesce((_micros(ts) - F.lag(_micros(ts)).over(w)) >= gap_seconds * 1_000_000, F.lit(False)).cast("int")
    return events.select("user_id", "event_id", ts, new.alias("new")).withColumn("s", F.sum("new").over(w.rowsBetween(Window.unboundedPreceding, 0))).groupBy("user_id", "s").agg(F.count("*").alias("n"))


def stream_sessions(stream: DataFrame, gap: str = "12 hours", late: str = "1 hour", ts: str = "ts") -> DataFrame:
    """The same for a stream: rows later than the watermark are dropped, closed sessions are emitted once."""
    timed = stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, late).dropDuplicatesWithinWatermark(["event_id"])
    return timed.groupBy("user_id", F.session_window(ts, gap).alias("w")).agg(F.count("*").alias("n"))


def stream_tumbling(stream: DataFrame, width: str = "1 week", late: str = "1 hour", ts: str = "ts") -> DataFrame:
    timed = stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, late)
    return timed.groupBy("user_id", F.window(ts, width).alias("w")).agg(F.count("*").alias("n"))


def stream_inserts(stream: DataFrame, insert, checkpoint: str, trigger: dict | None = None):
    """Starts a query that hands each micro-batch of new sets to insert(batch, epoch); the checkpoint folder makes a restart exact."""
    return stream.writeStream.foreachBatch(insert).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()
