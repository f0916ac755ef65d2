"""Streaming queries: windows, sessions, deduplication, scoring and merging of sketches."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import functions as F

from augspark.cluster import scratch_path, table
from augspark.queries.registry import register
from augspark.ring import gram
from augspark.streaming import sketches as st


def _stream(spark, d):
    return st.event_stream(spark, d, table(spark, d, "events").schema)


def _drain(spark, df, mode="complete"):
    return st.drain(df, f"s{uuid.uuid4().hex}", scratch_path(spark, "stream"), mode)


def _utc(run):
    """Windows are cut in UTC, whatever the session's time zone."""

    def wrapped(spark, d):
        spark.conf.set("spark.sql.session.timeZone", "UTC")
        return run(spark, d)

    return wrapped


_SUMS = "count(*)::DOUBLE AS c, round(sum(value) / count(*), 6) AS mean"


def _mean():
    return [F.col("g.c").alias("c"), F.round(F.col("g.s")[0] / F.col("g.c"), 6).alias("mean")]


@register("stream_tumbling_gram", f"SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, {_SUMS} FROM events GROUP BY 1, 2")
@_utc
def stream_tumbling_gram(spark, d):
    df = st.windowed(_stream(spark, d), ["value"], F.window("t", "1 day"), by=["event_type"])
    return _drain(spark, df).select("start", "event_type", *_mean())


@register("stream_sliding", "SELECT b - (k * INTERVAL 6 HOUR) AS start, count(*)::DOUBLE AS c, round(sum(value) / count(*), 6) AS mean FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts) AS b, value FROM events), range(0, 4) AS t(k) GROUP BY 1")
@_utc
def stream_sliding(spark, d):
    return _drain(spark, st.windowed(_stream(spark, d), ["value"], F.window("t", "1 day", "6 hours"))).select("start", *_mean())


@register(
    "stream_session",
    "WITH e AS (SELECT user_id, ts, value, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events), s AS (SELECT *, sum(CASE WHEN before IS NULL OR ts >= before + INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM e) "
    f"SELECT user_id, min(ts) AS start, {_SUMS} FROM s GROUP BY user_id, n",
)
@_utc
def stream_session(spark, d):
    return _drain(spark, st.windowed(_stream(spark, d), ["value"], F.session_window("t", "30 minutes"), by=["user_id"])).select("user_id", "start", *_mean())


@register("stream_dedup", "SELECT user_id, event_type, count(*)::BIGINT AS n FROM (SELECT DISTINCT event_id, user_id, event_type FROM events) GROUP BY 1, 2")
@_utc
def stream_dedup(spark, d):
    once = _stream(spark, d).withWatermark("t", "40 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type")
    return _drain(spark, once, "append").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))


@register("stream_state_gram", f"SELECT user_id, {_SUMS} FROM events GROUP BY 1")
@_utc
def stream_state_gram(spark, d):
    """A sketch per user kept as streaming state."""
    grouped = _stream(spark, d).groupBy("user_id").agg(F.count(F.lit(1)).alias("_c"), F.sum("value").alias("_s0"), F.sum(F.col("value") * F.col("value")).alias("_q0_0"))
    return _drain(spark, grouped.select("user_id", gram.pack(1).alias("g"))).select("user_id", *_mean())


@register("stream_ivm_merge", f"SELECT user_id, {_SUMS} FROM events GROUP BY 1")
@_utc
def stream_ivm_merge(spark, d):
    """Batches merged into a sketch store under their ids."""
    store = scratch_path(spark, "merged")
    st.for_each_batch(_stream(spark, d), st.merge_into(store, ["value"], ["user_id"]), scratch_path(spark, "stream"))
    return st.read_store(spark, store, 1, ["user_id"]).select("user_id", *_mean())


@register("score_stream", "SELECT event_id, round(1 + 0.01::DOUBLE * value + 0.001::DOUBLE * c_acctbal, 5) AS prediction FROM events JOIN customer ON user_id = c_custkey")
@_utc
def score_stream(spark, d):
    from augspark.serve.scorer import Scorer

    s = Scorer([1.0, 0.01, 0.001], ["value", "c_acctbal"], [("user_id", table(spark, d, "customer").select("c_custkey", "c_acctbal"), "c_custkey")])
    scored = s.score_stream(_stream(spark, d)).select("event_id", F.round("prediction", 5).alias("prediction"))
    return _drain(spark, scored, "append")


@register("stream_stream_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
@_utc
def stream_stream_join(spark, d):
    a = _stream(spark, d).filter("event_type = 'view'").select(F.col("event_id").alias("a"), F.col("user_id").alias("ua"), F.col("t").alias("ta")).withWatermark("ta", "40 days")
    b = _stream(spark, d).filter("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("ub"), F.col("t").alias("tb")).withWatermark("tb", "40 days")
    return _drain(spark, a.join(b, F.expr("ua = ub and tb >= ta and tb <= ta + interval 1 hour")).select("a", "b"), "append")


@register("stream_late_data")
@_utc
def stream_late_data(spark, d):
    """Three files; the last is older than the watermark that the first has set, so its rows are dropped.

    A batch's late rows are judged by the watermark of the batch before, hence the file in between.
    """
    e = table(spark, d, "events")
    path = scratch_path(spark, "late")
    newest = e.agg(F.max("ts")).first()[0]
    age = lambda days: F.lit(newest) - F.expr(f"interval {days} days")
    for part in (F.col("ts") >= age(1), (F.col("ts") < age(1)) & (F.col("ts") >= age(2)), F.col("ts") < age(20)):
        e.filter(part).coalesce(1).write.mode("append").parquet(path)
        time.sleep(1.1)  # files are taken in the order of their seconds
    raw = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path).withColumn("t", F.col("ts").cast("timestamp"))
    return _drain(spark, st.windowed(raw, ["value"], F.window("t", "1 day")), "append").select("start", *_mean())
