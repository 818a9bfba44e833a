"""Windowed degrees of an event stream, with batch twins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..workloads import table

LATE = "1 hour"


def windowed(events: DataFrame, kind: str) -> DataFrame:
    """Events per user and window; ``events`` may be a stream with a watermark."""
    when = {
        "tumbling": F.window("ts", "1 day"),
        "sliding": F.window("ts", "2 days", "1 day"),
        "session": F.session_window("ts", "6 hours"),
    }[kind]
    counted = events.groupBy("user_id", when.alias("w")).agg(F.count(F.lit(1)).alias("degree"))
    return counted.select("user_id", F.col("w.start").alias("opens"), F.col("w.end").alias("closes"), "degree")


def with_watermark(stream: DataFrame) -> DataFrame:
    """Rows that come later than ``LATE`` behind the newest are dropped."""
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", LATE)


def _batch(kind):
    """The batch twin; times as microseconds of the clock, in no time zone."""

    def query(s, d):
        rows = table(s, d, "events").select("user_id", "ts")

        def micros(c):
            minutes = (F.datediff(c, F.lit("1970-01-01")) * 24 + F.hour(c)).cast("long") * 60 + F.minute(c)
            return (minutes * 60_000_000 + (F.date_part(F.lit("SECOND"), F.col(c)) * 1_000_000).cast("long")).alias(c)

        return windowed(rows, kind).select("user_id", micros("opens"), micros("closes"), "degree")

    return query


_DAY = 86_400_000_000
_T = "SELECT user_id, epoch_us(ts) AS t FROM events"
_SESSION = f"""
WITH e AS ({_T}), m AS (SELECT *, t - lag(t) OVER (PARTITION BY user_id ORDER BY t) AS gap FROM e),
n AS (SELECT *, sum(CASE WHEN gap IS NULL OR gap >= 21600000000 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING) AS s FROM m)
SELECT user_id, min(t) AS opens, max(t) + 21600000000 AS closes, count(*) AS degree FROM n GROUP BY user_id, s"""

QUERIES = {
    "win_tumbling": (_batch("tumbling"), f"SELECT user_id, t // {_DAY} * {_DAY} AS opens, t // {_DAY} * {_DAY} + {_DAY} AS closes, count(*) AS degree FROM ({_T}) GROUP BY ALL"),
    "win_sliding": (
        _batch("sliding"),
        f"SELECT user_id, (t // {_DAY} - k) * {_DAY} AS opens, (t // {_DAY} - k + 2) * {_DAY} AS closes, count(*) AS degree FROM ({_T}), (VALUES (0), (1)) AS o(k) GROUP BY ALL",
    ),
    "win_session": (_batch("session"), _SESSION),
}
