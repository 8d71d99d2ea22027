"""Streams, drained and compared as tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..session import table
from ..streaming import streams


def _plain(df: DataFrame) -> DataFrame:
    return df.withColumn("start", F.col("start").cast("timestamp_ntz")) if "start" in df.columns else df


def _stream(make, mode: str = "complete"):
    return lambda spark, d: _plain(streams.drained(make(streams.source(spark, d)), mode))


def st_sorted_runs(spark: SparkSession, d: str) -> DataFrame:
    return streams.sorted_runs(streams.source(spark, d))


def st_late_rows(spark: SparkSession, d: str) -> DataFrame:
    return _plain(streams.drained(streams.closed_windows(streams.source(spark, d, again="2 HOURS")), "append"))


def st_window_topk(spark: SparkSession, d: str) -> DataFrame:
    """The two most frequent types of each hour, ties by name."""
    counts = _plain(streams.drained(streams.tumbling(streams.source(spark, d))))
    return counts.withColumn("place", F.row_number().over(Window.partitionBy("start").orderBy(F.desc("n"), "event_type"))).filter("place <= 2").select("start", "place", "event_type", "n")


def st_static_join(spark: SparkSession, d: str) -> DataFrame:
    return streams.drained(streams.with_customers(streams.source(spark, d), table(spark, d, "customer")), "append")


def st_state(spark: SparkSession, d: str) -> DataFrame:
    """What the state held last."""
    return streams.drained(streams.running_counts(streams.source(spark, d)), "append").groupBy("user_id").agg(F.max("seen").alias("seen"), F.max("last_id").alias("last_id"))


QUERIES = {
    "st_late_rows": st_late_rows,
    "st_window_topk": st_window_topk,
    "st_static_join": st_static_join,
    "st_state": st_state,
    "st_tumbling": _stream(streams.tumbling),
    "st_sliding": _stream(streams.sliding),
    "st_session": _stream(streams.session),
    "st_digit_hist": _stream(streams.digit_counts),
    "st_dedup": _stream(streams.deduplicated, "append"),
    "st_sorted_runs": st_sorted_runs,
}
_HOUR = "time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01')"
SQL = {
    "st_late_rows": f"SELECT {_HOUR} AS start, count(*) AS n FROM events GROUP BY 1 HAVING {_HOUR} + INTERVAL 2 HOUR <= (SELECT max(ts) FROM events)",
    "st_window_topk": f"SELECT * FROM (SELECT start, row_number() OVER (PARTITION BY start ORDER BY n DESC, event_type) AS place, event_type, n FROM (SELECT {_HOUR} AS start, event_type, count(*) AS n FROM events GROUP BY ALL)) WHERE place <= 2",
    "st_static_join": "SELECT event_id, user_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey",
    "st_state": "SELECT user_id, count(*) AS seen, max(event_id) AS last_id FROM events GROUP BY 1",
    "st_tumbling": "SELECT time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01') AS start, event_type, count(*) AS n, min(event_id) AS first_id FROM events GROUP BY ALL",
    "st_sliding": "SELECT time_bucket(INTERVAL 1 HOUR, ts, TIMESTAMP '1970-01-01') - k * INTERVAL 1 HOUR AS start, count(*) AS n FROM events, (VALUES (0), (1)) AS t(k) GROUP BY ALL",
    "st_session": "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s",
    "st_digit_hist": "SELECT user_id % 256 AS digit, count(*) AS n FROM events GROUP BY 1",
    "st_dedup": "SELECT event_id, user_id FROM events",
    "st_sorted_runs": "SELECT event_id, value, row_number() OVER (ORDER BY value, event_id) - 1 AS pos FROM events",
}
