"""Streaming queries, each run over the whole table and held against batch SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.counter import mix_sql
from ..sources import tables
from ..streaming import events as E
from .base import query



@query("op_stream_tumbling", "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark: SparkSession, d: str) -> DataFrame:
    return E.drained(E.tumbling(E.source(spark, d)), "complete")


@query("op_stream_sliding", "SELECT s AS start, count(*) AS n FROM (SELECT unnest([date_trunc('hour', ts), date_trunc('hour', ts) - INTERVAL 1 HOUR]) AS s FROM events) GROUP BY s")
def stream_sliding(spark: SparkSession, d: str) -> DataFrame:
    return E.drained(E.sliding(E.source(spark, d)), "complete")


@query("op_stream_session", "WITH g AS (SELECT user_id, ts, sum(CASE WHEN p IS NULL OR ts >= p + INTERVAL 2 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS p FROM events)) SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, k")
def stream_session(spark: SparkSession, d: str) -> DataFrame:
    return E.drained(E.sessions(E.source(spark, d)), "complete")


@query("op_stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark: SparkSession, d: str) -> DataFrame:
    """One row a key over several micro-batches, by state alone."""
    parts = E.by_day(tables.table(spark, d, "events"))
    return E.drained(E.in_files(spark, parts).dropDuplicates(["user_id", "event_type"]).select("user_id", "event_type"))


@query("op_stream_watermark_late", "SELECT start, event_type, count(*) AS n FROM (SELECT date_trunc('hour', ts) AS start, event_type FROM events) WHERE start + INTERVAL 1 HOUR <= (SELECT max(ts) FROM events) - INTERVAL 1 HOUR GROUP BY start, event_type")
def stream_watermark_late(spark: SparkSession, d: str) -> DataFrame:
    """All events arrive in order, then the first part once more: too late, so no window counts it twice."""
    parts = E.by_day(tables.table(spark, d, "events"))
    return E.drained(E.tumbling(E.in_files(spark, [*parts, parts[0]])), "append")


@query("op_sink_foreachbatch", "SELECT event_type, count(*) AS n, sum(CAST(floor(value) AS BIGINT)) AS total FROM events GROUP BY 1")
def sink_foreachbatch(spark: SparkSession, d: str) -> DataFrame:
    """Batches go to a sink by number, so one that runs again replaces itself."""
    from ..sources.storage import new_path

    path = new_path(spark, "sink")
    E.run_batches(E.in_files(spark, E.by_day(tables.table(spark, d, "events"))), lambda batch, number: batch.write.mode("overwrite").parquet(f"{path}/{number}"))
    return spark.read.parquet(f"{path}/*").groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.floor("value")).alias("total"))


@query("op_stream_static_join", "SELECT c_mktsegment AS segment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1")
def stream_static_join(spark: SparkSession, d: str) -> DataFrame:
    static = tables.table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    met = E.source(spark, d).join(static, F.col("user_id") == F.col("c_custkey")).groupBy(F.col("c_mktsegment").alias("segment")).agg(F.count("*").alias("n"))
    return E.drained(met, "complete")


@query("op_stream_stream_join", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def stream_stream_join(spark: SparkSession, d: str) -> DataFrame:
    left = E.source(spark, d).filter("event_type = 'click'").select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 hour")
    right = E.source(spark, d).filter("event_type = 'purchase'").select(F.col("event_id").alias("b"), F.col("user_id").alias("w"), "ts").withWatermark("ts", "1 hour")
    return E.drained(left.join(right, F.expr("u = w AND ts >= t AND ts <= t + INTERVAL 6 HOURS")).select("a", "b"))


def _signed(r: int) -> str:
    return f"CAST(sum(1 - 2 * ({mix_sql(9, ['ascii(substr(event_type, 1, 1))', 'hour(ts)', str(r)])} % 2)) AS BIGINT) AS z{r}"


@query("op_stream_state_sketch", "SELECT user_id, " + ", ".join(_signed(r) for r in range(4)) + " FROM events GROUP BY user_id")
def stream_state_sketch(spark: SparkSession, d: str) -> DataFrame:
    state = E.SketchState(spark)
    E.run_batches(E.source(spark, d), state.fold)
    return state.total()
