"""Streaming queries, run over what is available, with their batch counterparts as DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from fadegossip import methods, planner
from fadegossip.decay import DecaySpec
from fadegossip.sources import read_table
from fadegossip.streaming import grids, io

LINEAR = DecaySpec("poly", b=1)


def late_rows(spark, d):
    """Forward weights need the arrival stamp only: late rows get theirs, and the watermark just closes days."""
    df = io.read_stream(spark, d, "lineitem").withWatermark("l_shipdate", "30 days")
    tick = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date"))
    out = df.groupBy(F.window("l_shipdate", "30 days")).agg(F.sum(tick).alias("mass"), F.count(F.lit(1)).alias("n"))
    return io.drain(out.select(F.col("window.start").cast("date").cast("string").alias("day"), "mass", "n"), "complete")


def tumbling(spark, d):
    df = io.read_stream(spark, d, "events").withWatermark("ts", "1 day")
    out = df.groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return io.drain(out.select(F.col("window.start").cast("date").cast("string").alias("day"), "event_type", "n"), "complete")


def sliding(spark, d):
    df = io.read_stream(spark, d, "events").withWatermark("ts", "1 day")
    out = df.groupBy(F.window("ts", "2 days", "1 day")).agg(F.count(F.lit(1)).alias("n"))
    return io.drain(out.select(F.col("window.start").cast("date").cast("string").alias("day"), "n"), "complete")


def sessions(spark, d):
    df = io.read_stream(spark, d, "events").withWatermark("ts", "1 day")
    out = df.groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return io.drain(out.select("user_id", "n"), "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))


def decayed_sums(spark, d):
    df = grids.canonical_stream(io.read_stream(spark, d, "events"))
    return io.drain(df.groupBy("item_key").agg(F.sum(LINEAR.raw()).alias("mass")), "complete")


def stateful_grid(spark, d):
    """The state store of this query is RocksDB; the session's own setting is restored."""
    key = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(key)
    spark.conf.set(key, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        df = grids.canonical_stream(io.read_stream(spark, d, "events"))
        rows = io.drain(grids.stateful_grid(df, LINEAR, methods.FAMILY), "update")
    finally:
        spark.conf.set(key, before)
    return io.keep_last(rows, ["site", "row", "col"])


def merged_grid(spark, d):
    """Micro-batches of one table file; merging is exact here, as no cell is contended."""
    df = grids.canonical_stream(io.read_stream(spark, d, "events"))
    return grids.MergedGrid(spark, LINEAR, methods.FAMILY).run(df)


def deduplicated(spark, d):
    df = io.read_stream(spark, d, "events").withWatermark("ts", "1 day")
    doubled = df.withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    out = io.drain(doubled.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "event_type"))
    return out.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"))


def with_dictionary(spark, d):
    names = read_table(spark, d, "customer").select("c_custkey", "c_mktsegment")
    df = io.read_stream(spark, d, "events").join(names, F.col("user_id") == F.col("c_custkey"))
    return io.drain(df.groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "complete")


def epochs(spark, d):
    grid = merged_grid(spark, d)
    out = grids.epoch(grid, methods.DEMO, methods.FAMILY, LINEAR, 0.195, planner.slack(8, 12, 0.01), 31)
    return out.select("site", "item_key", *[F.round(c, 6).alias(c) for c in ("est_avg", "est_global", "tau", "c_est", "p_est")])


def click_then_purchase(spark, d):
    df = io.read_stream(spark, d, "events").withWatermark("ts", "2 hours")
    a = df.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("t"), F.col("event_id").alias("clicked"))
    b = io.read_stream(spark, d, "events").withWatermark("ts", "2 hours").where("event_type = 'purchase'").select("user_id", "ts", F.col("event_id").alias("bought"))
    out = a.join(b, (F.col("u") == F.col("user_id")) & (F.col("ts") >= F.col("t")) & (F.col("ts") <= F.col("t") + F.expr("INTERVAL 1 HOUR")))
    return io.drain(out.select("clicked", "bought"))


QUERIES = {f"stream_{f.__name__}": f for f in (late_rows, tumbling, sliding, sessions, decayed_sums, stateful_grid, merged_grid, deduplicated, with_dictionary, epochs, click_then_purchase)}
_GRID = f"WITH {methods._sql_grid('types', 'linear', methods.FAMILY, 'preagg')} SELECT * FROM grid"
ORACLES = {
    "stream_late_rows": "SELECT CAST(CAST(time_bucket(INTERVAL 30 DAY, l_shipdate, TIMESTAMP '1970-01-01') AS DATE) AS VARCHAR) AS day, CAST(sum(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))) AS BIGINT) AS mass, count(*) AS n FROM lineitem GROUP BY 1",
    "stream_tumbling": "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type, count(*) AS n FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT CAST(CAST(ts AS DATE) - k AS VARCHAR) AS day, count(*) AS n FROM events, (VALUES (0), (1)) AS t(k) GROUP BY 1",
    "stream_sessions": "WITH g AS (SELECT user_id, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS s FROM events) SELECT user_id, CAST(sum(s) AS BIGINT) AS sessions, count(*) AS n FROM g GROUP BY 1",
    "stream_decayed_sums": f"WITH {methods._stream('types')} SELECT item_key, sum(tick::DOUBLE) AS mass FROM s GROUP BY 1",
    "stream_stateful_grid": f"WITH {methods._sql_grid('types', 'linear', methods.FAMILY, 'arrival')} SELECT * FROM grid",
    "stream_merged_grid": _GRID,
    "stream_deduplicated": "SELECT event_type, count(*) AS n FROM events GROUP BY 1",
    "stream_with_dictionary": "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1",
    "stream_epochs": methods.ORACLES["gossip_query_types"],
    "stream_click_then_purchase": "SELECT a.event_id AS clicked, b.event_id AS bought FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
}
