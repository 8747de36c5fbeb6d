"""Scans, sinks, projection, filters, aggregation, sorting, sets, subqueries."""

from __future__ import annotations

from pyspark.sql import functions as F

from fadegossip import methods
from fadegossip.decay import DecaySpec
from fadegossip.local import build_local
from fadegossip.operators.registry import registry
from fadegossip.sources import ZipfSource, read_table, stream
from fadegossip.streaming.io import drain, folder, read_stream

QUERIES, ORACLES, op = registry()
LINEAR = DecaySpec("poly", b=1)
DAY = "date_diff('day', DATE '2023-12-31', CAST(ts AS DATE))"


@op("scan_pruned", "SELECT CAST(epoch_us(ts) AS BIGINT) AS ts_us, user_id FROM events WHERE ts >= TIMESTAMP '2024-01-08' AND ts < TIMESTAMP '2024-01-15'")
def _(spark, d):
    rows = read_table(spark, d, "events").where((F.col("ts") >= F.expr("TIMESTAMP_NTZ '2024-01-08'")) & (F.col("ts") < F.expr("TIMESTAMP_NTZ '2024-01-15'")))
    return rows.select(F.unix_micros(F.col("ts").cast("timestamp")).alias("ts_us"), "user_id")


for _format in ("csv", "json", "orc", "parquet", "text"):

    def _round_trip(spark, d, kind=_format):
        answer = methods.QUERIES["exact_hitters_types"](spark, d).select("item_key", F.round("f", 3).alias("f"))
        at = f"{folder(spark)}/{kind}"
        if kind == "text":
            answer.select(F.concat_ws("\t", "item_key", "f")).write.text(at)
            back = spark.read.text(at).select(F.split("value", "\t").alias("v"))
            return back.select(F.col("v")[0].cast("long").alias("item_key"), F.col("v")[1].cast("double").alias("f"))
        answer.write.format(kind).save(at)
        return spark.read.schema("item_key long, f double").format(kind).load(at)

    op(f"sink_{_format}", methods.ORACLES["exact_hitters_types"].replace("round(f, 6) AS f, round(c, 6) AS c FROM", "round(f, 3) AS f FROM"))(_round_trip)


@op("partitioned_sink", f"WITH {methods._sql_grid('types', 'linear', methods.FAMILY, 'preagg')} SELECT site, col, i1, f1, i2, f2 FROM grid WHERE \"row\" = 0")
def _(spark, d):
    at = f"{folder(spark)}/grid"
    build_local(stream(spark, d, "types"), LINEAR, methods.FAMILY, "preagg").write.partitionBy("row").parquet(at)
    return spark.read.parquet(at).where("row = 0").select("site", "col", "i1", "f1", "i2", "f2")


@op("file_stream", "SELECT event_id, event_type FROM events")
def _(spark, d):
    return drain(read_stream(spark, d, "events").select("event_id", "event_type"))


@op("zipf_source")
def _(spark, d):
    spark.dataSource.register(ZipfSource)
    return spark.read.format("zipf_arrivals").options(rows=5000, rho=1.2, universe=100).load().groupBy("item_key").agg(F.count(F.lit(1)).alias("n"))


@op("canonical", f"WITH {methods._stream('priorities')} SELECT site, item, item_key, tick FROM s")
def _(spark, d):
    return stream(spark, d, "priorities").select("site", "item", "item_key", "tick")


@op("rejected_rows", f"SELECT 0::BIGINT AS dropped_null, count(*) FILTER (WHERE {DAY} - 10 <= 0) AS before_landmark FROM events")
def _(spark, d):
    from fadegossip.sources.streams import days_since, rejected

    return rejected(read_table(spark, d, "events"), F.col("event_type"), days_since(F.col("ts"), "2023-12-31") - 10)


@op("predicates", "SELECT c_custkey, c_acctbal FROM customer WHERE c_mktsegment IN ('BUILDING', 'MACHINERY') AND c_acctbal BETWEEN 0 AND 5000 AND c_name LIKE 'Customer%' AND c_name IS NOT NULL AND NOT c_nationkey = 3")
def _(spark, d):
    c = read_table(spark, d, "customer")
    return c.where(F.col("c_mktsegment").isin("BUILDING", "MACHINERY") & F.col("c_acctbal").between(0, 5000) & F.col("c_name").like("Customer%") & F.col("c_name").isNotNull() & ~(F.col("c_nationkey") == 3)).select("c_custkey", "c_acctbal")


@op("time_slice", f"SELECT event_id, {DAY} AS tick FROM events WHERE ts > TIMESTAMP '2024-01-05' AND ts <= TIMESTAMP '2024-01-20'")
def _(spark, d):
    from fadegossip.sources.streams import days_since

    rows = read_table(spark, d, "events").where((F.col("ts") > F.expr("TIMESTAMP_NTZ '2024-01-05'")) & (F.col("ts") <= F.expr("TIMESTAMP_NTZ '2024-01-20'")))
    return rows.select("event_id", days_since(F.col("ts"), "2023-12-31").alias("tick"))


@op("hash_sample", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem WHERE ('0x' || substr(md5(concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey)), 1, 8))::BIGINT < 429496729")
def _(spark, d):
    from fadegossip.sources import fingerprint

    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
    return read_table(spark, d, "lineitem").select(keys).where(fingerprint(F.concat_ws("|", *keys)) < 429496729)


# -- aggregation -----------------------------------------------------------------------------------------------
@op("hash_aggregate", f"SELECT event_type, sum({DAY})::BIGINT AS mass, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def _(spark, d):
    from fadegossip.sources.streams import days_since

    e = read_table(spark, d, "events")
    return e.groupBy("event_type").agg(F.sum(days_since(F.col("ts"), "2023-12-31")).alias("mass"), F.count(F.lit(1)).alias("n"), F.countDistinct("user_id").alias("users"))


@op("ordered_lists", "SELECT user_id, list(event_type ORDER BY event_id) AS types FROM events GROUP BY 1")
def _(spark, d):
    lists = F.transform(F.array_sort(F.collect_list(F.struct("event_id", "event_type"))), lambda x: x.event_type)
    return read_table(spark, d, "events").groupBy("user_id").agg(lists.alias("types"))


_MASS = "date_diff('day', DATE '1994-12-31', CAST(o_orderdate AS DATE))"


@op("rollup", f"SELECT n_name, o_orderpriority, sum({_MASS})::BIGINT AS mass FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY ROLLUP (n_name, o_orderpriority)")
def _(spark, d):
    from fadegossip.sources.streams import days_since

    o = read_table(spark, d, "orders").select("o_custkey", "o_orderpriority", days_since(F.col("o_orderdate"), "1994-12-31").alias("m"))
    c = read_table(spark, d, "customer").select("c_custkey", "c_nationkey")
    n = read_table(spark, d, "nation").select("n_nationkey", "n_name")
    joined = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.rollup("n_name", "o_orderpriority").agg(F.sum("m").alias("mass"))


@op("cube", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def _(spark, d):
    return read_table(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


@op("grouping_sets", "SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus)::BIGINT AS g, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def _(spark, d):
    l = read_table(spark, d, "lineitem")  # noqa: E741
    return l.groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")], []], "l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count(F.lit(1)).alias("n"))


@op("pivot", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, " + ", ".join(f"nullif(count(*) FILTER (WHERE event_type = '{t}'), 0) AS {t}" for t in ("click", "view", "purchase")) + " FROM events WHERE event_type IN ('click', 'view', 'purchase') GROUP BY 1")
def _(spark, d):
    e = read_table(spark, d, "events").where(F.col("event_type").isin("click", "view", "purchase"))
    return e.groupBy(F.col("ts").cast("date").cast("string").alias("day")).pivot("event_type", ["click", "view", "purchase"]).agg(F.count(F.lit(1)))


@op("statistics", "SELECT event_type, round(stddev_samp(value), 6) AS sd, round(var_samp(value), 4) AS var, round(quantile_cont(value, 0.9), 6) AS p90, round(corr(value, user_id), 6) AS r FROM events GROUP BY 1")
def _(spark, d):
    r = F.round
    return read_table(spark, d, "events").groupBy("event_type").agg(r(F.stddev_samp("value"), 6).alias("sd"), r(F.var_samp("value"), 4).alias("var"), r(F.percentile("value", 0.9), 6).alias("p90"), r(F.corr("value", "user_id"), 6).alias("r"))


@op("max_by", "SELECT user_id, max(event_id) AS last_id, arg_max(event_type, event_id) AS last_type, arg_min(event_type, event_id) AS first_type FROM events GROUP BY 1")
def _(spark, d):
    return read_table(spark, d, "events").groupBy("user_id").agg(F.max("event_id").alias("last_id"), F.max_by("event_type", "event_id").alias("last_type"), F.min_by("event_type", "event_id").alias("first_type"))


@op("approximate", "SELECT true AS near")
def _(spark, d):
    e = read_table(spark, d, "lineitem")
    got = e.agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.countDistinct("l_partkey").alias("b"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("c"))
    return got.select(((F.abs(F.col("a") - F.col("b")) < 0.08 * F.col("b")) & (F.abs(F.col("c") - F.col("b")) < 0.08 * F.col("b"))).alias("near"))


@op("having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 15")
def _(spark, d):
    return read_table(spark, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).where("n > 15")


# -- order, sets, subqueries -----------------------------------------------------------------------------------
@op("global_sort", "SELECT s_suppkey, s_acctbal, row_number() OVER (ORDER BY s_acctbal DESC, s_suppkey) - 1 AS place FROM supplier")
def _(spark, d):
    """A range-partitioned sort; places come from the sizes of the partitions before, not from one task."""
    s = read_table(spark, d, "supplier").select("s_suppkey", "s_acctbal").orderBy(F.desc("s_acctbal"), "s_suppkey")
    marked = s.withColumn("part", F.spark_partition_id()).withColumn("at", F.monotonically_increasing_id().bitwiseAND((1 << 33) - 1))
    sizes = {x.part: x.n for x in marked.groupBy("part").agg(F.count(F.lit(1)).alias("n")).collect()}  # a number per partition
    base, total = {}, 0
    for part in sorted(sizes):
        base[part], total = total, total + sizes[part]
    before = F.create_map(*[F.lit(x) for kv in base.items() for x in kv])
    return marked.select("s_suppkey", "s_acctbal", (before[F.col("part")] + F.col("at")).alias("place"))


@op("sort_in_partitions", "SELECT s_nationkey, s_suppkey FROM supplier")
def _(spark, d):
    return read_table(spark, d, "supplier").select("s_nationkey", "s_suppkey").repartition(4, "s_nationkey").sortWithinPartitions("s_nationkey", "s_suppkey")


@op("top_k", "SELECT l_partkey, sum(l_quantity * date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))) AS mass FROM lineitem GROUP BY 1 ORDER BY mass DESC, l_partkey LIMIT 10")
def _(spark, d):
    from fadegossip.sources.streams import days_since

    mass = F.sum(F.col("l_quantity") * days_since(F.col("l_shipdate"), "1995-01-01")).alias("mass")
    return read_table(spark, d, "lineitem").groupBy("l_partkey").agg(mass).orderBy(F.desc("mass"), "l_partkey").limit(10)


@op("limit_offset", "SELECT c_custkey FROM customer ORDER BY c_acctbal, c_custkey LIMIT 20 OFFSET 30")
def _(spark, d):
    return read_table(spark, d, "customer").orderBy("c_acctbal", "c_custkey").offset(30).limit(20).select("c_custkey")


_A = f"WITH {methods._stream('users')}, c AS (SELECT sum(tick) AS c FROM s), a AS (SELECT item_key FROM s GROUP BY 1 HAVING sum(tick) > 0.0075::DOUBLE * (SELECT c FROM c)), b AS (SELECT item_key FROM s GROUP BY 1 HAVING count(*) > 0.0075::DOUBLE * (SELECT count(*) FROM s))"


def _two(spark, d):
    from fadegossip.exact import exact_hitters

    s = stream(spark, d, "users")
    return exact_hitters(s, LINEAR, 0.0075, 31).select("item_key"), exact_hitters(s, DecaySpec(), 0.0075, 31).select("item_key")


for _name, _word in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
    op(f"set_{_name}", f"{_A} SELECT * FROM a {_word} SELECT * FROM b")(lambda spark, d, n=_name: (lambda a, b: {"union": a.unionByName(b).distinct(), "intersect": a.intersect(b), "except": a.exceptAll(b)}[n])(*_two(spark, d)))


@op("distinct_pairs", "SELECT DISTINCT l_returnflag, l_linestatus FROM lineitem")
def _(spark, d):
    return read_table(spark, d, "lineitem").select("l_returnflag", "l_linestatus").dropDuplicates()


def _views(spark, d, *names):
    for name in names:
        read_table(spark, d, name).createOrReplaceTempView(name)


_SCALAR = "SELECT user_id, count(*) AS n FROM events GROUP BY user_id HAVING count(*) > 0.0078 * (SELECT count(*) FROM events)"
_EXISTS = "SELECT o_orderkey FROM orders o WHERE o_orderpriority IN (SELECT max(o_orderpriority) FROM orders) AND EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_shipdate > o.o_orderdate)"
_CORRELATED = "SELECT c_custkey FROM customer c WHERE c_acctbal > (SELECT avg(c2.c_acctbal) FROM customer c2 WHERE c2.c_nationkey = c.c_nationkey)"
_RECURSIVE = "WITH RECURSIVE r(site, hop) AS (SELECT 0, 0 UNION ALL SELECT (site + 1) % 8, hop + 1 FROM r WHERE hop < 7) SELECT site, hop FROM r"


@op("scalar_subquery", _SCALAR)
def _(spark, d):
    _views(spark, d, "events")
    return spark.sql(_SCALAR)


@op("exists_and_in", _EXISTS)
def _(spark, d):
    _views(spark, d, "orders", "lineitem")
    return spark.sql(_EXISTS)


@op("correlated_subquery", _CORRELATED)
def _(spark, d):
    _views(spark, d, "customer")
    return spark.sql(_CORRELATED)


@op("recursive_reach", _RECURSIVE)
def _(spark, d):
    return spark.sql(_RECURSIVE)
