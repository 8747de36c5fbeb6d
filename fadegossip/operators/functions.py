"""Scalar, array, map, JSON and struct functions; SQL, table and pandas functions of the engine."""

from __future__ import annotations

from pyspark.sql import functions as F

from fadegossip import methods
from fadegossip.functions import fold_udf, register, zipf_rank
from fadegossip.operators.registry import registry
from fadegossip.sources import fingerprint, read_table, stream

QUERIES, ORACLES, op = registry()


@op("word_counts", "SELECT w, count(*) AS n FROM (SELECT unnest(regexp_split_to_array(lower(text), '\\s+')) AS w FROM documents) WHERE w <> '' GROUP BY 1 HAVING count(*) > 50")
def _(spark, d):
    words = F.explode(F.split(F.lower("text"), r"\s+")).alias("w")
    return read_table(spark, d, "documents").select(words).where("w <> ''").groupBy("w").agg(F.count(F.lit(1)).alias("n")).where("n > 50")


@op("string_functions", "SELECT c_custkey, upper(substr(c_name, 1, 4)) AS head, length(trim(c_name)) AS len, regexp_replace(c_name, '[0-9]+', '#') AS masked, concat_ws('/', c_mktsegment, CAST(c_nationkey AS VARCHAR)) AS path, md5(c_name) AS digest FROM customer")
def _(spark, d):
    return read_table(spark, d, "customer").select("c_custkey", F.upper(F.substring("c_name", 1, 4)).alias("head"), F.length(F.trim("c_name")).alias("len"), F.regexp_replace("c_name", "[0-9]+", "#").alias("masked"), F.concat_ws("/", "c_mktsegment", F.col("c_nationkey").cast("string")).alias("path"), F.md5("c_name").alias("digest"))


@op("url_hosts", "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def _(spark, d):
    return read_table(spark, d, "pages").groupBy(F.expr("try_parse_url(url, 'HOST')").alias("host")).agg(F.count(F.lit(1)).alias("n"))


@op("date_functions", "SELECT event_id, date_diff('day', DATE '2023-12-31', CAST(ts AS DATE)) AS days, CAST(floor(epoch(ts) / 3600) AS BIGINT) AS hours, CAST(CAST(date_trunc('month', ts) AS DATE) AS VARCHAR) AS month, CAST(extract(dow FROM ts) + 1 AS INTEGER) AS dow, CAST(CAST(ts + INTERVAL 1 DAY AS DATE) AS VARCHAR) AS tomorrow FROM events")
def _(spark, d):
    t = F.col("ts").cast("timestamp")
    return read_table(spark, d, "events").select("event_id", F.datediff(F.col("ts").cast("date"), F.lit("2023-12-31").cast("date")).cast("long").alias("days"), F.floor(F.unix_seconds(t) / 3600).alias("hours"), F.date_trunc("month", t).cast("date").cast("string").alias("month"), F.dayofweek("ts").alias("dow"), (F.col("ts") + F.expr("INTERVAL 1 DAY")).cast("date").cast("string").alias("tomorrow"))


@op("math_functions", "SELECT event_id, round(exp(-0.01 * user_id), 9) AS e, round(ln(1 + user_id), 9) AS l, round(sqrt(user_id), 9) AS s, CAST(floor(value) AS BIGINT) AS f, greatest(user_id, 75) AS g, least(user_id, 75) AS m, user_id % 7 AS r FROM events")
def _(spark, d):
    u = F.col("user_id")
    return read_table(spark, d, "events").select("event_id", F.round(F.exp(-0.01 * u), 9).alias("e"), F.round(F.log1p(u.cast("double")), 9).alias("l"), F.round(F.sqrt(u), 9).alias("s"), F.floor("value").alias("f"), F.greatest(u, F.lit(75)).alias("g"), F.least(u, F.lit(75)).alias("m"), F.pmod(u, F.lit(7)).alias("r"))


@op("bit_functions", "SELECT event_id, user_id & 7 AS a, user_id | 8 AS o, xor(user_id, 5) AS x, user_id << 3 AS l, bit_count(user_id) AS c, ('0x' || substr(md5(event_type), 1, 8))::BIGINT AS k FROM events")
def _(spark, d):
    u = F.col("user_id")
    return read_table(spark, d, "events").select("event_id", u.bitwiseAND(7).alias("a"), u.bitwiseOR(8).alias("o"), u.bitwiseXOR(5).alias("x"), F.shiftleft(u, 3).alias("l"), F.bit_count(u).cast("int").alias("c"), fingerprint(F.col("event_type")).alias("k"))


@op("array_fold", methods.ORACLES["local_grid_preagg_users"])
def _(spark, d):
    return methods.QUERIES["local_grid_preagg_users"](spark, d)


@op("array_functions", "SELECT vec_id, round(list_sum([x::DOUBLE * x::DOUBLE for x in embedding]), 6) AS norm2, round(list_sum([(embedding[i])::DOUBLE * (embedding[len(embedding) + 1 - i])::DOUBLE for i in range(1, len(embedding) + 1)]), 6) AS palindrome, len([x for x in embedding if x > 0]) AS positive, len(list_filter(embedding, lambda x: x > 0.9)) > 0 AS large FROM embeddings")
def _(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    total = lambda a: F.round(F.aggregate(a, F.lit(0.0), lambda s, x: s + x), 6)
    return read_table(spark, d, "embeddings").select("vec_id", total(F.transform(e, lambda x: x * x)).alias("norm2"), total(F.zip_with(e, F.reverse(e), lambda x, y: x * y)).alias("palindrome"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.exists("embedding", lambda x: x > F.lit(0.9).cast("float")).alias("large"))


@op("map_functions", "SELECT event_type, count(*) / 2.0::DOUBLE AS half FROM events GROUP BY 1 HAVING count(*) > 10")
def _(spark, d):
    """Answers as a map and back to rows."""
    counts = read_table(spark, d, "events").groupBy("event_type").agg(F.count(F.lit(1)).alias("n")).agg(F.sort_array(F.collect_list(F.struct("event_type", "n"))).alias("x"))
    m = counts.select(F.map_from_arrays("x.event_type", "x.n").alias("m"))
    kept = m.select(F.transform_values(F.map_filter("m", lambda k, v: v > 10), lambda k, v: v / F.lit(2.0)).alias("m"))
    return kept.select(F.explode(F.map_entries("m")).alias("e")).select(F.col("e.key").alias("event_type"), F.col("e.value").alias("half"))


@op("json_functions", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    parsed = read_table(spark, d, "events").select(F.from_json("props", "k long").alias("p"), F.variant_get(F.parse_json("props"), "$.k", "long").alias("v"))
    return parsed.where(F.col("p.k") == F.col("v")).groupBy(F.col("p.k").alias("k")).agg(F.count(F.lit(1)).alias("n"))


@op("struct_functions", "SELECT n_nationkey AS i1, n_regionkey * 2.0::DOUBLE AS f1, upper(n_name) AS name FROM nation")
def _(spark, d):
    s = read_table(spark, d, "nation").select(F.struct(F.col("n_nationkey").alias("i1"), F.col("n_regionkey").cast("double").alias("f1"), F.col("n_name").alias("name")).alias("c"))
    return s.select(F.col("c").withField("f1", F.col("c.f1") * 2).withField("name", F.upper("c.name")).alias("c")).select("c.i1", "c.f1", "c.name")


@op("conditionals", "SELECT site, coalesce(1 / nullif(share, 0), -1) AS p_est, CASE WHEN share > 0 THEN 'yes' ELSE 'no' END AS reached FROM (SELECT CAST(i AS INTEGER) AS site, CASE WHEN i % 2 = 0 THEN 0.25 ELSE 0 END::DOUBLE AS share FROM range(6) t(i))")
def _(spark, d):
    s = spark.range(6).select(F.col("id").cast("int").alias("site"), F.when(F.col("id") % 2 == 0, 0.25).otherwise(0.0).alias("share"))
    return s.select("site", F.coalesce(F.try_divide(F.lit(1.0), F.nullif("share", F.lit(0.0))), F.lit(-1.0)).alias("p_est"), F.when(F.col("share") > 0, "yes").otherwise("no").alias("reached"))


@op("sql_functions", f"WITH {methods._stream('types')} SELECT item, item_key, sum(tick::DOUBLE) / 31.0::DOUBLE AS f, round(sum(exp(0.1 * (tick - 31))), 6) AS e, sum(pow(2.0::DOUBLE, floor(tick / 7.0) - 4)) AS h FROM s GROUP BY 1, 2")
def _(spark, d):
    register(spark)
    stream(spark, d, "types").createOrReplaceTempView("arrivals")
    return spark.sql("SELECT item, item_fingerprint(item) AS item_key, sum(CAST(tick AS DOUBLE)) / 31 AS f, round(sum(decay_exp(tick, 31, 0.1D)), 6) AS e, sum(decay_half_life(tick, 31, 7)) AS h FROM arrivals GROUP BY item")


@op("plan_table_function")
def _(spark, d):
    register(spark)
    return spark.sql("SELECT * FROM plan_parameters(0.02D, 0.002D, 5000D, 0.05D, 0.01D)")


@op("hash_table_function", f"WITH {methods._stream('types')} {methods._sql_cells(methods.FAMILY, '(SELECT DISTINCT item_key FROM s)', 'item_key')}")
def _(spark, d):
    register(spark)
    stream(spark, d, "types").select("item_key").distinct().createOrReplaceTempView("keys")
    return spark.sql("SELECT item_key, h.row, h.col FROM keys, LATERAL hash_rows(item_key, 4, 16) h")


@op("pandas_fold", methods.ORACLES["local_grid_preagg_types"])
def _(spark, d):
    from fadegossip import cells
    from fadegossip.decay import DecaySpec
    from fadegossip.hashing import with_cells
    from fadegossip.local import preaggregate

    rows = with_cells(preaggregate(stream(spark, d, "types"), DecaySpec("poly", b=1)), methods.FAMILY)
    lists = rows.groupBy("site", "row", "col").agg(F.array_sort(F.collect_list(F.struct((-F.col("x")).alias("n"), "item_key", "x"))).alias("e"))
    return cells.flat(lists.select("site", "row", "col", fold_udf(F.col("e.item_key"), F.col("e.x")).alias("cell")))


@op("zipf_rank_udf", methods.ORACLES["zipf_stream_counts"].replace("SELECT r AS item_key, count(*) AS n, sum(tick::DOUBLE) AS mass", "SELECT r AS item_key, count(*) AS n"))
def _(spark, d):
    u = fingerprint(F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"))
    return read_table(spark, d, "lineitem").select(zipf_rank(1.2, 1000)(u).alias("item_key")).groupBy("item_key").agg(F.count(F.lit(1)).alias("n"))
