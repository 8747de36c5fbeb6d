"""Joins: broadcast, shuffled, outer, semi, theta, range, as-of, cross, self, lateral."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from fadegossip import methods
from fadegossip.operators.registry import registry
from fadegossip.sources import read_table, stream
from fadegossip.sources.streams import days_since

QUERIES, ORACLES, op = registry()


@op("broadcast_join", "SELECT n_name, round(sum(o_totalprice * date_diff('day', DATE '1994-12-31', CAST(o_orderdate AS DATE))), 0) AS revenue FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def _(spark, d):
    o = read_table(spark, d, "orders").select("o_custkey", (F.col("o_totalprice") * days_since(F.col("o_orderdate"), "1994-12-31")).alias("r"))
    c = read_table(spark, d, "customer").select("c_custkey", "c_nationkey")
    n = F.broadcast(read_table(spark, d, "nation").select("n_nationkey", "n_name"))  # 25 rows by definition
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.round(F.sum("r"), 0).alias("revenue"))


for _hint in ("merge", "shuffle_hash"):

    def _shuffled(spark, d, hint=_hint):
        l = read_table(spark, d, "lineitem").select("l_orderkey", "l_quantity")  # noqa: E741
        o = read_table(spark, d, "orders").select("o_orderkey", "o_orderpriority")
        return l.join(o.hint(hint), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.sum("l_quantity").alias("q"))

    op(f"shuffle_join_{_hint}", "SELECT o_orderpriority, sum(l_quantity) AS q FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1")(_shuffled)


@op("skewed_join_salted", "SELECT r_name, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1")
def _(spark, d):
    """Salted keys: the few hot keys of the large side are spread, the small side is repeated for each salt."""
    salts = 8
    c = read_table(spark, d, "customer").select("c_custkey", "c_nationkey")
    n = read_table(spark, d, "nation").join(read_table(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "r_name")
    o = read_table(spark, d, "orders").select("o_custkey", F.pmod("o_orderkey", F.lit(salts)).alias("salt")).join(c, F.col("o_custkey") == F.col("c_custkey"))
    spread = n.withColumn("salt2", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return o.join(spread.hint("merge"), (F.col("c_nationkey") == F.col("n_nationkey")) & (F.col("salt") == F.col("salt2"))).groupBy("r_name").agg(F.count(F.lit(1)).alias("n"))


@op("full_outer_join", f"WITH {methods._stream('users')}, a AS (SELECT item_key, sum(tick)::BIGINT AS faded FROM s GROUP BY 1 HAVING sum(tick) > 1100), b AS (SELECT item_key, count(*) AS plain FROM s GROUP BY 1 HAVING count(*) > 70) SELECT item_key, faded, plain FROM a FULL JOIN b USING (item_key)")
def _(spark, d):
    s = stream(spark, d, "users")
    a = s.groupBy("item_key").agg(F.sum("tick").alias("faded")).where("faded > 1100")
    b = s.groupBy("item_key").agg(F.count(F.lit(1)).alias("plain")).where("plain > 70")
    return a.join(b, "item_key", "full_outer")


@op("left_join", "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
def _(spark, d):
    o = read_table(spark, d, "orders").select("o_custkey", "o_orderkey")
    return read_table(spark, d, "customer").select("c_custkey").join(o, F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n"))


@op("right_join", "SELECT n_name, count(s_suppkey) AS n FROM supplier RIGHT JOIN nation ON s_nationkey = n_nationkey GROUP BY 1")
def _(spark, d):
    n = read_table(spark, d, "nation").select("n_nationkey", "n_name")
    return read_table(spark, d, "supplier").select("s_nationkey", "s_suppkey").join(n, F.col("s_nationkey") == F.col("n_nationkey"), "right").groupBy("n_name").agg(F.count("s_suppkey").alias("n"))


@op("anti_join", "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM events WHERE user_id = c_custkey)")
def _(spark, d):
    return read_table(spark, d, "customer").select("c_custkey").join(read_table(spark, d, "events").select("user_id"), F.col("c_custkey") == F.col("user_id"), "left_anti")


@op("semi_join", "SELECT s_suppkey, s_name FROM supplier WHERE s_suppkey IN (SELECT l_suppkey FROM lineitem GROUP BY 1 HAVING count(*) > 0.0105 * (SELECT count(*) FROM lineitem))")
def _(spark, d):
    from fadegossip.decay import DecaySpec
    from fadegossip.exact import exact_hitters

    hot = exact_hitters(stream(spark, d, "suppliers"), DecaySpec(), 0.0105, methods.DAYS_AT)
    return read_table(spark, d, "supplier").select("s_suppkey", "s_name").join(hot, F.col("s_suppkey") == F.col("item_key"), "left_semi")


@op("theta_join", "SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def _(spark, d):
    n = read_table(spark, d, "nation")
    a, b = n.select("n_nationkey", "n_regionkey", F.col("n_name").alias("a")), n.select(F.col("n_nationkey").alias("k"), F.col("n_regionkey").alias("r"), F.col("n_name").alias("b"))
    return a.join(b, (F.col("n_regionkey") == F.col("r")) & (F.col("n_nationkey") < F.col("k"))).select("a", "b")


@op("range_join", "WITH t AS (SELECT CAST(i AS INTEGER) AS slot, TIMESTAMP '2024-01-01' + INTERVAL 3 DAY * i AS f, TIMESTAMP '2024-01-01' + INTERVAL 3 DAY * i + INTERVAL 1 DAY AS u FROM range(10) t(i)) SELECT slot, count(*) AS n FROM events JOIN t ON ts >= f AND ts < u GROUP BY 1")
def _(spark, d):
    """Arrivals inside sessions: binned by day, so that the range condition follows an equi-join."""
    slots = spark.range(10).select(F.col("id").cast("int").alias("slot"), F.date_add(F.lit("2024-01-01").cast("date"), (3 * F.col("id")).cast("int")).alias("bin"))
    e = read_table(spark, d, "events").select(F.col("ts").cast("date").alias("bin"))
    return e.join(F.broadcast(slots), "bin").groupBy("slot").agg(F.count(F.lit(1)).alias("n"))


@op("as_of_join", "WITH t AS (SELECT c_custkey, x.d FROM customer, (VALUES (TIMESTAMP '1997-01-01'), (TIMESTAMP '2000-01-01')) AS x(d)) SELECT c_custkey, CAST(CAST(d AS DATE) AS VARCHAR) AS day, (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey AND o_orderdate <= d ORDER BY o_orderdate DESC, o_orderkey DESC LIMIT 1) AS last_order FROM t")
def _(spark, d):
    """Last order before given days: both sides in one ordered window per customer, no pair is made."""
    c = read_table(spark, d, "customer").select("c_custkey")
    days = c.crossJoin(spark.sql("SELECT explode(array(TIMESTAMP_NTZ '1997-01-01', TIMESTAMP_NTZ '2000-01-01')) AS at")).select("c_custkey", "at", F.lit(None).cast("long").alias("o"), F.lit(1).alias("ask"))
    orders = read_table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"), F.col("o_orderdate").alias("at"), F.col("o_orderkey").alias("o"), F.lit(0).alias("ask"))
    w = Window.partitionBy("c_custkey").orderBy("at", "ask", "o").rowsBetween(Window.unboundedPreceding, 0)
    return days.unionByName(orders).withColumn("last_order", F.last("o", ignorenulls=True).over(w)).where("ask = 1").select("c_custkey", F.col("at").cast("date").cast("string").alias("day"), "last_order")


@op("cross_join_total", "SELECT event_type, count(*) / (SELECT count(*) FROM events)::DOUBLE AS share FROM events GROUP BY 1")
def _(spark, d):
    e = read_table(spark, d, "events")
    return e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).crossJoin(F.broadcast(e.agg(F.count(F.lit(1)).alias("all")))).select("event_type", (F.col("n") / F.col("all")).alias("share"))


@op("self_join", "WITH l AS (SELECT DISTINCT l_orderkey AS o, l_suppkey AS s FROM lineitem) SELECT a.s AS a, b.s AS b, count(*) AS n FROM l a JOIN l b USING (o) WHERE a.s < b.s GROUP BY 1, 2 HAVING count(*) > 20")
def _(spark, d):
    l = read_table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o"), F.col("l_suppkey").alias("a")).distinct()  # noqa: E741
    return l.join(l.withColumnRenamed("a", "b"), "o").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")).where("n > 20")


@op("lateral_cells", f"WITH {methods._stream('priorities')} {methods._sql_cells(methods.FAMILY, '(SELECT DISTINCT item, item_key FROM s)', 'item')}")
def _(spark, d):
    items = stream(spark, d, "priorities").select("item", "item_key").distinct()
    cell = spark.tvf.explode(methods.FAMILY.cells(F.col("item_key").outer()))
    return items.lateralJoin(cell).select("item", F.col("col.row").alias("row"), F.col("col.col").alias("col"))
