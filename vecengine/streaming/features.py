"""Feature vectors of event windows, over batches or streams alike."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The event types of the table, in order.
TYPES = ("click", "error", "purchase", "signup", "view")


def types_of(events: DataFrame) -> list[str]:
    """The event types of a batch, in order; a stream takes a given list."""
    return [r.event_type for r in events.select("event_type").distinct().orderBy("event_type").collect()]


def features(events: DataFrame, types: list[str], length: str = "1 day", slide: str | None = None, session_gap: str | None = None, watermark: str | None = None) -> DataFrame:
    """(user_id, start_ts, end_ts, n, vec) for each user and window of events (ts timestamp, user_id, event_type, value, props).

    vec holds counts by type, sums of value by type, and the mean of the k in props. With a watermark
    late rows of a stream are dropped and counted by Spark. Partial aggregates come before the shuffle.
    """
    rows = events.withColumn("ts", F.col("ts").cast("timestamp"))  # watermarks need an instant
    if watermark:
        rows = rows.withWatermark("ts", watermark)
    window = F.session_window("ts", session_gap) if session_gap else F.window("ts", length, slide) if slide else F.window("ts", length)
    k = F.get_json_object("props", "$.k").cast("double")
    counts = [F.sum((F.col("event_type") == t).cast("double")) for t in types]
    sums = [F.sum(F.when(F.col("event_type") == t, F.col("value")).otherwise(0.0)) for t in types]
    vec = F.array(*counts, *sums, F.coalesce(F.avg(k), F.lit(0.0)))
    out = rows.groupBy("user_id", window.alias("w")).agg(F.count(F.lit(1)).alias("n"), vec.alias("vec"))
    return out.select("user_id", F.col("w.start").alias("start_ts"), F.col("w.end").alias("end_ts"), "n", "vec")
