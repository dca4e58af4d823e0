"""Streaming queries run to the end of the events table; SQL restates those whose result doesn't hang on the watermark."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import arrow, frames
from ..sources import tables
from ..streaming import lists

Q: dict = {}
SQL: dict[str, str] = {}


def stream_type_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lists.run(lists.counts(lists.events(spark, sf_dir)), "complete")


Q["stream_type_counts"], SQL["stream_type_counts"] = stream_type_counts, "SELECT event_type, count(*) AS n FROM events GROUP BY event_type"


def stream_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lists.run(lists.distinct_events(lists.events(spark, sf_dir)).select("event_id", "user_id"))


Q["stream_distinct"], SQL["stream_distinct"] = stream_distinct, "SELECT DISTINCT event_id, user_id FROM events"


def stream_interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lists.run(lists.click_then(lists.events(spark, sf_dir), lists.events(spark, sf_dir)))


Q["stream_interval_join"] = stream_interval_join
SQL["stream_interval_join"] = "SELECT a.event_id AS click_id, b.event_id AS then_id, a.user_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"


def stream_static_probe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors joined to the number of events their user has, from a static table."""
    static = tables.table(spark, sf_dir, "events", ["user_id"]).groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))
    return lists.run(lists.probe_static(lists.events(spark, sf_dir).filter("event_type = 'error'").select("event_id", "user_id"), static, "user_id"))


Q["stream_static_probe"] = stream_static_probe
SQL["stream_static_probe"] = "SELECT user_id, event_id, n FROM events JOIN (SELECT user_id, count(*) AS n FROM events GROUP BY user_id) USING (user_id) WHERE event_type = 'error'"


def stream_type_counts_update(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same counts in update mode: each micro-batch tells what it has changed, and the largest of a type is the last."""
    return lists.run(lists.counts(lists.events(spark, sf_dir)), "update").groupBy("event_type").agg(F.max("n").alias("n"))


Q["stream_type_counts_update"], SQL["stream_type_counts_update"] = stream_type_counts_update, SQL["stream_type_counts"]


def _closed(df: DataFrame) -> DataFrame:
    return lists.run(df).select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "n")


def stream_tumbling_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of a day that the watermark has closed: those that end by the last event's time."""
    return _closed(lists.tumbling(lists.events(spark, sf_dir)))


def stream_sliding_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of a day, a window every six hours, that the watermark has closed."""
    return _closed(lists.sliding(lists.events(spark, sf_dir)))


def stream_session_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of sessions with gaps under 30 minutes that the watermark has closed."""
    return _closed(lists.sessions(lists.events(spark, sf_dir)))


_LAST = "(SELECT date_trunc('millisecond', max(ts)) FROM events)"  # watermarks count milliseconds
for _f in (stream_tumbling_sets, stream_sliding_sets, stream_session_sets):
    Q[_f.__name__] = _f
SQL["stream_tumbling_sets"] = f"SELECT date_trunc('day', ts)::TIMESTAMP AS start, user_id, count(DISTINCT event_id) AS n FROM events GROUP BY 1, 2 HAVING date_trunc('day', min(ts)) + INTERVAL 1 DAY <= {_LAST}"
SQL["stream_sliding_sets"] = f"""WITH w AS (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - i * INTERVAL 6 HOUR AS start, user_id, event_id FROM events, range(4) r(i))
SELECT start, user_id, count(DISTINCT event_id) AS n FROM w GROUP BY start, user_id HAVING start + INTERVAL 1 DAY <= {_LAST}"""
SQL["stream_session_sets"] = f"""WITH o AS (SELECT *, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events),
s AS (SELECT *, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS session FROM o)
SELECT min(ts)::TIMESTAMP AS start, user_id, count(DISTINCT event_id) AS n FROM s GROUP BY user_id, session HAVING max(ts) + INTERVAL 30 MINUTE <= {_LAST}"""


def stream_growing_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sealed Elias-Fano segments of users' lists, decoded, without the open tails (stream_whole_lists has both); needs the RocksDB state store, set for the query alone."""
    key = "spark.sql.streaming.stateStore.providerClass"
    had = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        got = lists.run(lists.growing_lists(lists.events(spark, sf_dir)))
    finally:
        spark.conf.unset(key) if had is None else spark.conf.set(key, had)
    rows = got.select(F.col("user_id").alias("k"), "seg", "n", F.lit(0).cast("long").alias("lo"), "universe", F.lit("ef").alias("codec"), "payload", "bits")
    return frames.decode_lists(rows)


def stream_whole_lists(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users' whole lists: the sealed segments decoded, and the open tails as the state holds them at the end of the run."""
    key = "spark.sql.streaming.stateStore.providerClass"
    had = spark.conf.get(key, None)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        got, tails = lists.run_with_state(lists.growing_lists(lists.events(spark, sf_dir)), "tail")
        tails = arrow.stage(tails.select("key.user_id", F.explode("value.ids").alias("event_id")), "open-tails")
    finally:
        spark.conf.unset(key) if had is None else spark.conf.set(key, had)
    rows = got.select(F.col("user_id").alias("k"), "seg", "n", F.lit(0).cast("long").alias("lo"), "universe", F.lit("ef").alias("codec"), "payload", "bits")
    sealed = frames.decode_lists(rows).select(F.col("k").alias("user_id"), F.col("id").alias("event_id"))
    return sealed.unionByName(tails)


Q["stream_whole_lists"], SQL["stream_whole_lists"] = stream_whole_lists, "SELECT user_id, event_id FROM events"

