"""Streaming queries on the events table, run to the end of what is there."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import window as W

from rankspark import engine, exact
from rankspark.frames import digest_frame
from rankspark.params import MethodSpec, cents
from rankspark.sources import load_table

from . import quantiles as q

PHIS = [(1, 4), (1, 2), (3, 4)]
SPEND = "CAST(round(value * 100) AS BIGINT)"


def _from_counts(counts: DataFrame, by: str) -> DataFrame:
    """Quantiles of each window from its counts: one window over a window's distinct values."""
    run = counts.withColumn("upto", F.sum("cnt").over(W.Window.partitionBy(by).orderBy("idx").rowsBetween(W.Window.unboundedPreceding, 0))).withColumn("n", F.sum("cnt").over(W.Window.partitionBy(by)))
    met = run.join(F.broadcast(exact.phi_rows(counts, PHIS))).where("upto - cnt <= phi_num * n div phi_den and phi_num * n div phi_den < upto")
    return met.select(by, "phi_num", "phi_den", F.col("idx").alias("value"), "n")


def window_quantiles(spark: SparkSession, d: str) -> DataFrame:
    load_table(spark, d, "events")
    counts = q.drained(q.window_counts(q.event_stream(spark, d), "ts", cents("value"), "1 day"), "daily", "complete")
    return _from_counts(counts.withColumn("day", F.date_format("start", "yyyy-MM-dd")), "day")


def sliding_digest(spark: SparkSession, d: str) -> DataFrame:
    load_table(spark, d, "events")
    return q.drained(q.window_counts(q.event_stream(spark, d), "ts", cents("value"), "2 days", "1 day"), "sliding", "complete").groupBy(F.date_format("start", "yyyy-MM-dd").alias("day")).agg(F.sum("cnt").alias("n"), F.count(F.lit(1)).alias("leaves"))


def session_counts(spark: SparkSession, d: str) -> DataFrame:
    load_table(spark, d, "events")
    s = q.event_stream(spark, d).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return q.drained(s.select("user_id", "n"), "sessions", "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("events"))


def dedup(spark: SparkSession, d: str) -> DataFrame:
    load_table(spark, d, "events")
    return q.drained(q.deduplicated(q.event_stream(spark, d).select("event_id", "event_type", "ts"), "ts", "event_id", "40 days"), "dedup").groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def static_join(spark: SparkSession, d: str) -> DataFrame:
    c = load_table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    s = q.event_stream(spark, d).join(c, F.col("user_id") == F.col("c_custkey"))
    counts = q.drained(s.groupBy("c_mktsegment", cents("value").alias("idx")).agg(F.count(F.lit(1)).alias("cnt")), "static", "complete")
    return _from_counts(counts, "c_mktsegment")


def equals_batch(spark: SparkSession, d: str) -> DataFrame:
    """The digest of the stream's counts and that of the table: the same nodes, neither with one more, and not none."""
    rows = load_table(spark, d, "events").select(cents("value").alias("v"))
    s = q.event_stream(spark, d).groupBy(cents("value").alias("idx")).agg(F.count(F.lit(1)).alias("cnt"))
    live = digest_frame.compress(q.drained(s, "equal", "complete").select(F.lit(0).alias("level"), "idx", "cnt"), "0.01", 16)
    batch = digest_frame.build(rows, "v", "0.01", 16)
    apart = live.exceptAll(batch).unionByName(batch.exceptAll(live))
    return apart.agg(F.count(F.lit(1)).alias("c")).join(F.broadcast(batch.agg(F.count(F.lit(1)).alias("nodes")))).select(((F.col("c") == 0) & (F.col("nodes") > 0)).alias("same"))


def windowed_summaries(spark: SparkSession, d: str) -> DataFrame:
    """Windows whose state is a packed summary: the last row of each window, so the ones still open at the end are there too."""
    load_table(spark, d, "events")
    rows = q.drained(q.windowed_summaries(q.event_stream(spark, d), "ts", "value", MethodSpec.of("gap", "0.01"), "1 day"), "packed", "update")
    return rows.groupBy("start").agg(F.max_by("n", "batch").alias("n"))


def refreshed_table(spark: SparkSession, d: str) -> DataFrame:
    import uuid

    load_table(spark, d, "events")
    path = f"{q.scratch(spark)}/streams/table_{uuid.uuid4().hex[:8]}"
    q.refreshed(q.event_stream(spark, d), "value", MethodSpec.of("gap", "0.01"), path)
    merged = engine.merge_summaries(spark.read.parquet(path).drop("batch"), nodes=1)
    rows = load_table(spark, d, "events")
    return engine.guaranteed(rows, "value", PHIS, "0.01", engine.answer(merged, PHIS))


_day = "strftime(ts, '%Y-%m-%d')"
ENTRIES: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str | None]] = {
    "stream_window_quantiles": (window_quantiles, exact.quantile_sql(f"(SELECT {_day} AS day, {SPEND} AS v FROM events)", "v", PHIS, ["day"])),
    "stream_sliding_digest": (sliding_digest, f"SELECT strftime(s, '%Y-%m-%d') AS day, CAST(count(*) AS BIGINT) AS n, count(DISTINCT v) AS leaves FROM (SELECT date_trunc('day', ts) - INTERVAL (k) DAY AS s, {SPEND} AS v FROM events, range(0, 2) r(k)) GROUP BY 1"),
    "stream_session_counts": (session_counts, "SELECT user_id, CAST(sum(fresh) AS BIGINT) AS sessions, count(*) AS events FROM (SELECT user_id, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w > INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)) GROUP BY 1"),
    "stream_dedup": (dedup, "SELECT event_type, count(DISTINCT event_id) AS n FROM events GROUP BY 1"),
    "stream_static_join": (static_join, exact.quantile_sql(f"(SELECT c_mktsegment, {SPEND} AS v FROM events JOIN customer ON user_id = c_custkey)", "v", PHIS, ["c_mktsegment"])),
    "stream_equals_batch": (equals_batch, "SELECT TRUE AS same"),
    "stream_windowed_summaries": (windowed_summaries, None),
    "stream_refreshed_table": (refreshed_table, "SELECT phi_num, phi_den, CAST(value AS DOUBLE) AS exact_value, TRUE AS within_eps FROM (" + exact.quantile_sql("events", "value", PHIS) + ")"),
}
