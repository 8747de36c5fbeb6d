"""Window functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from fadegossip.operators.registry import registry
from fadegossip.sources import read_table
from fadegossip.sources.streams import days_since

QUERIES, ORACLES, op = registry()
_SUPPLIERS = "SELECT l_suppkey AS s, sum(date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE)))::BIGINT AS mass, any_value(s_nationkey) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1"
#: Seconds of a slot: running sums are made within a slot, and over the totals of the slots.
SLOT = 3600


def range_counts(events: DataFrame, span: int) -> DataFrame:
    """(event_id, n): events of the type in the last `span` seconds up to the event's own second, those after it in that second included.

    Spark adds a sliding frame up anew for every row. So a second's events count from that second on and are taken off
    again after `span`, and n is a running sum. Events without a time count each other, those without a type are a type.
    """
    rows = events.select("event_id", "event_type", F.unix_seconds(F.col("ts").cast("timestamp")).alias("s"))
    own = rows.groupBy("event_type", "s").agg(F.count(F.lit(1)).alias("m"))
    both = F.array(F.struct(F.col("s").alias("at"), F.col("m").alias("x")), F.struct((F.col("s") + span + 1).alias("at"), (-F.col("m")).alias("x")))
    moves = own.where("s IS NOT NULL").select("event_type", F.explode(both).alias("e")).groupBy("event_type", F.col("e.at").alias("at")).agg(F.sum("e.x").alias("x")).withColumn("slot", F.floor(F.col("at") / SLOT))
    within = moves.withColumn("within", F.sum("x").over(Window.partitionBy("event_type", "slot").orderBy("at")))
    earlier = Window.partitionBy("event_type").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    before = moves.groupBy("event_type", "slot").agg(F.sum("x").alias("x")).select(F.col("event_type").alias("t"), F.col("slot").alias("k"), F.coalesce(F.sum("x").over(earlier), F.lit(0)).alias("before"))
    upto = within.join(before, F.col("event_type").eqNullSafe(F.col("t")) & (F.col("slot") == F.col("k"))).select(F.col("event_type").alias("t"), "at", (F.col("within") + F.col("before")).alias("n"))
    counts = own.join(upto, F.col("event_type").eqNullSafe(F.col("t")) & (F.col("s") == F.col("at")), "left").select(F.col("event_type").alias("t"), F.col("s").alias("at"), F.coalesce("n", "m").alias("n"))
    return rows.join(counts, F.col("event_type").eqNullSafe(F.col("t")) & F.col("s").eqNullSafe(F.col("at"))).select("event_id", "n")


@op("ranking", f"WITH m AS ({_SUPPLIERS}) SELECT s, row_number() OVER w AS rn, rank() OVER (PARTITION BY n ORDER BY mass DESC) AS rk, dense_rank() OVER (PARTITION BY n ORDER BY mass DESC) AS dr, ntile(3) OVER w AS nt, round(percent_rank() OVER (PARTITION BY n ORDER BY mass DESC), 9) AS pr, round(cume_dist() OVER (PARTITION BY n ORDER BY mass DESC), 9) AS cd FROM m WINDOW w AS (PARTITION BY n ORDER BY mass DESC, s)")
def _(spark, d):
    m = read_table(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("s")).agg(F.sum(days_since(F.col("l_shipdate"), "1995-01-01")).alias("mass"))
    m = m.join(read_table(spark, d, "supplier").select("s_suppkey", "s_nationkey"), F.col("s") == F.col("s_suppkey"))
    w, t = Window.partitionBy("s_nationkey").orderBy(F.desc("mass"), "s"), Window.partitionBy("s_nationkey").orderBy(F.desc("mass"))
    return m.select("s", F.row_number().over(w).alias("rn"), F.rank().over(t).alias("rk"), F.dense_rank().over(t).alias("dr"), F.ntile(3).over(w).alias("nt"), F.round(F.percent_rank().over(t), 9).alias("pr"), F.round(F.cume_dist().over(t), 9).alias("cd"))


@op("lag_lead", "SELECT event_id, CAST(epoch_us(ts) - lag(epoch_us(ts)) OVER w AS BIGINT) AS gap, lead(event_type) OVER w AS next_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    return read_table(spark, d, "events").select("event_id", (us - F.lag(us).over(w)).alias("gap"), F.lead("event_type").over(w).alias("next_type"))


@op("running_mass", "WITH m AS (SELECT event_type, CAST(ts AS DATE) AS d, sum(date_diff('day', DATE '2023-12-31', CAST(ts AS DATE))) AS x FROM events GROUP BY 1, 2) SELECT event_type, CAST(d AS VARCHAR) AS day, CAST(sum(x) OVER (PARTITION BY event_type ORDER BY d ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS upto FROM m")
def _(spark, d):
    m = read_table(spark, d, "events").groupBy("event_type", F.col("ts").cast("date").alias("d")).agg(F.sum(days_since(F.col("ts"), "2023-12-31")).alias("x"))
    w = Window.partitionBy("event_type").orderBy("d").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return m.select("event_type", F.col("d").cast("string").alias("day"), F.sum("x").over(w).alias("upto"))


@op("range_frame", "SELECT event_id, count(*) OVER (PARTITION BY event_type ORDER BY CAST(floor(epoch(ts)) AS BIGINT) RANGE BETWEEN 604800 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(spark, d):
    return range_counts(read_table(spark, d, "events"), 604800)


@op("first_last_nth", "SELECT DISTINCT user_id, first_value(event_id) OVER w AS a, nth_value(event_id, 2) OVER w AS b, last_value(event_id) OVER w AS z FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
def _(spark, d):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return read_table(spark, d, "events").select("user_id", F.first_value("event_id").over(w).alias("a"), F.nth_value("event_id", 2).over(w).alias("b"), F.last_value("event_id").over(w).alias("z")).distinct()
