"""Streams run to their end, beside the SQL of the batch answer."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seedspread.runtime import table
from seedspread.streaming import streams

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def register(name: str, sql: str | None = None):
    def add(query):
        QUERIES[name] = query
        if sql is not None:
            ORACLES[name] = sql
        return query
    return add


def last_batch(rows: DataFrame) -> DataFrame:
    return rows.join(rows.agg(F.max("_batch").alias("_batch")), "_batch").drop("_batch")


@register("stream_tumbling", "SELECT epoch_us(time_bucket(INTERVAL 1 HOUR, ts)) AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark, sf):
    rows = last_batch(streams.run_to_end(streams.tumbling(streams.event_stream(spark, sf)), "complete"))
    return rows.select(F.unix_micros("start").alias("start"), "event_type", "n")


@register("stream_sliding", "SELECT epoch_us(time_bucket(INTERVAL 15 MINUTE, ts)) - k * 900000000 AS start, count(*)::BIGINT AS n FROM events, range(4) AS r(k) GROUP BY 1")
def stream_sliding(spark, sf):
    rows = last_batch(streams.run_to_end(streams.sliding(streams.event_stream(spark, sf)), "complete"))
    return rows.select(F.unix_micros("start").alias("start"), "n")


@register("stream_sessions", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS cut FROM events),
s AS (SELECT user_id, ts, sum(cut) OVER (PARTITION BY user_id ORDER BY ts, cut DESC ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, epoch_us(min(ts)) AS start, count(*)::BIGINT AS n FROM s GROUP BY user_id, k""")
def stream_sessions(spark, sf):
    rows = last_batch(streams.run_to_end(streams.sessions(streams.event_stream(spark, sf)), "complete"))
    return rows.select("user_id", F.unix_micros("start").alias("start"), "n")


@register("stream_dedup", "SELECT event_id, user_id FROM events")
def stream_dedup(spark, sf):
    return streams.run_to_end(streams.deduplicated(streams.event_stream(spark, sf))).select("event_id", "user_id")


@register("stream_edges", "SELECT DISTINCT user_id * 2 AS src, (epoch_us(ts) // 3600000000) * 2 + 1 AS dst FROM events")
def stream_edges(spark, sf):
    return streams.EdgeUpkeep(spark).run(streams.event_stream(spark, sf))


@register("stream_degrees", "SELECT user_id, count(DISTINCT epoch_us(ts) // 3600000000)::BIGINT AS deg FROM events GROUP BY 1")
def stream_degrees(spark, sf):
    rows = streams.run_to_end(streams.degree_counter(streams.event_stream(spark, sf)), "update")
    return rows.groupBy("user_id").agg(F.max_by("deg", "_batch").alias("deg"))


@register("stream_static_join", "SELECT event_id, c_nationkey FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf):
    static = table(spark, sf, "customer").select(F.col("c_custkey").alias("user_id"), "c_nationkey")
    return streams.run_to_end(streams.with_static(streams.event_stream(spark, sf), static).select("event_id", "c_nationkey"))


@register("stream_stream_join", "SELECT a.event_id AS click, b.event_id AS view FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'view' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 30 MINUTE")
def stream_stream_join(spark, sf):
    return streams.run_to_end(streams.followed_by(streams.event_stream(spark, sf)))


@register("stream_cluster_queries")
def stream_cluster_queries(spark, sf):
    """Every customer of nation 0 that arrives is answered with its cluster's summary."""
    from seedspread.operators.profile import local_cluster
    from seedspread.sources.builders import geo

    graph = geo(spark, sf).persist()
    schema = table(spark, sf, "customer").schema
    arriving = spark.readStream.schema(schema).option("pathGlobFilter", "customer.parquet*").parquet(sf).filter("c_nationkey = 0")

    def answer(batch: DataFrame) -> DataFrame:
        start = batch.select(F.col("c_custkey").alias("run_id"), (F.col("c_custkey") * 4).alias("v"), F.lit(1.0).alias("w"))
        return local_cluster(graph, start, "push", alpha=0.05, eps=1e-4).summary()

    out = streams.answer_queries(arriving, answer)
    graph.unpersist()
    return out.select("run_id", "size", "vol", "cut", F.round("phi", 9).alias("phi"))
