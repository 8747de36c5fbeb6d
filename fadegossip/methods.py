"""Queries for the methods, with their DuckDB counterparts.

Counterparts are built from text pieces: a stream of a fixture, a fold of ordered arrivals into cells, and, for
gossip, the mixing matrix of the schedule written out as values (averaging is linear where no cell is contended).
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip import baselines, cells, churn, exact, gossip, local, metrics, planner, query, topology
from fadegossip.decay import DecaySpec, check_decay, decayed_count, decayed_freq, forward_backward_gap
from fadegossip.hashing import HashFamily, with_cells
from fadegossip.local import assign_sites, init_share
from fadegossip.plans import cut
from fadegossip.schedule import Schedule, check_levels, draw_exchanges, draw_matching, from_pairs
from fadegossip.sources import stream, zipf_stream
from fadegossip.sources.zipf import zipf_cdf

QUERIES: dict = {}
ORACLES: dict[str, str] = {}

LINEAR, PLAIN, QUADRATIC, HALF, EXP, STEP = DecaySpec("poly", b=1), DecaySpec(), DecaySpec("poly", b=2), DecaySpec("half_life", half=7), DecaySpec("exp", lam=0.1), DecaySpec("step", cut=15)
EVENTS_AT, DAYS_AT, IDS_AT = 31, 2557, 1_000_000
FAMILY, NARROW = HashFamily(4, 16), HashFamily(4, 8)


def build_local(df: DataFrame, spec: DecaySpec, family: HashFamily, mode: str = "preagg") -> DataFrame:
    """Grids that SQL can repeat: a site's items folded in one order, whatever the partitions."""
    return local.build_local(df, spec, family, mode)


def _key(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 8))::BIGINT"


def _days(ts: str, landmark: str) -> str:
    return f"date_diff('day', DATE '{landmark}', CAST({ts} AS DATE))"


# the streams of the fixtures as SQL: site, item, item_key, tick, and the columns that order equal ticks
STREAMS = {
    "types": f"SELECT CAST(user_id % 8 AS INTEGER) AS site, event_type AS item, {_key('event_type')} AS item_key, {_days('ts', '2023-12-31')} AS tick, event_id AS seq FROM events",
    "users": f"SELECT CAST(event_id % 16 AS INTEGER) AS site, CAST(user_id AS VARCHAR) AS item, user_id AS item_key, {_days('ts', '2023-12-31')} AS tick, event_id AS seq FROM events",
    "props": f"SELECT CAST(user_id % 8 AS INTEGER) AS site, json_extract_string(props, '$.k') AS item, CAST(json_extract_string(props, '$.k') AS BIGINT) AS item_key, {_days('ts', '2023-12-31')} AS tick, event_id AS seq FROM events",
    "suppliers": f"SELECT CAST(l_orderkey % 16 AS INTEGER) AS site, CAST(l_suppkey AS VARCHAR) AS item, l_suppkey AS item_key, {_days('l_shipdate', '1995-01-01')} AS tick, (l_orderkey, l_linenumber, l_partkey, l_suppkey) AS seq FROM lineitem",
    "parts": f"SELECT CAST(l_orderkey % 16 AS INTEGER) AS site, CAST(l_partkey AS VARCHAR) AS item, l_partkey AS item_key, {_days('l_shipdate', '1995-01-01')} AS tick, (l_orderkey, l_linenumber, l_partkey, l_suppkey) AS seq FROM lineitem",
    "priorities": f"SELECT CAST(o_custkey % 8 AS INTEGER) AS site, o_orderpriority AS item, {_key('o_orderpriority')} AS item_key, {_days('o_orderdate', '1994-12-31')} AS tick, o_orderkey AS seq FROM orders",
    "customers": f"SELECT CAST(o_custkey % 25 AS INTEGER) AS site, CAST(o_custkey AS VARCHAR) AS item, o_custkey AS item_key, {_days('o_orderdate', '1994-12-31')} AS tick, o_orderkey AS seq FROM orders",
    "words": f"SELECT CAST(regexp_extract(source, '[0-9]+') AS INTEGER) AS site, w AS item, {_key('w')} AS item_key, doc_id + 1 AS tick, doc_id AS seq FROM (SELECT source, doc_id, unnest(regexp_split_to_array(lower(text), '\\s+')) AS w FROM documents) WHERE w <> ''",
    "hosts": f"SELECT CAST(page_id % 4 AS INTEGER) AS site, h AS item, {_key('h')} AS item_key, page_id + 1 AS tick, page_id AS seq FROM (SELECT page_id, lower(regexp_extract(url, '^[a-z]+://([^/]+)', 1)) AS h FROM pages)",
    "roles": f"SELECT CAST(conv_id % 4 AS INTEGER) AS site, role AS item, {_key('role')} AS item_key, turn + 1 AS tick, (conv_id, turn) AS seq FROM conversations",
    "labels": "SELECT CAST(vec_id % 8 AS INTEGER) AS site, CAST(label AS VARCHAR) AS item, CAST(label AS BIGINT) AS item_key, vec_id + 1 AS tick, vec_id AS seq FROM embeddings",
}
RAW = {"none": "1.0::DOUBLE", "linear": "tick::DOUBLE", "quadratic": "pow(tick::DOUBLE, 2)", "half_life": "pow(2.0::DOUBLE, floor(tick / 7.0))", "exp": "exp(0.1 * tick)", "step": "CASE WHEN tick > 15 THEN 1.0 ELSE 0.0 END::DOUBLE"}
SPECS = {"none": PLAIN, "linear": LINEAR, "quadratic": QUADRATIC, "half_life": HALF, "exp": EXP, "step": STEP}


def _stream(name: str) -> str:
    return f"s AS ({STREAMS[name]})"


def _sql_cells(family: HashFamily, source: str, columns: str) -> str:
    """Rows of `source` for each row of the grid, with row and col."""
    params = ", ".join(f"({r}, {a}::BIGINT, {b}::BIGINT)" for r, (a, b) in enumerate(family.params))
    return f"SELECT {columns}, h.r AS \"row\", CAST({family.sql_col('item_key', 'h.a', 'h.b')} AS INTEGER) AS col FROM {source}, (VALUES {params}) AS h(r, a, b)"


def _sql_fold(source: str, by: str, order: str) -> str:
    """Cells (by, i1, f1, i2, f2) of ordered arrivals (item_key, x)."""
    cell = lambda i1, f1, i2, f2: f"{{'i1': {i1}, 'f1': {f1}, 'i2': {i2}, 'f2': {f2}}}"
    step = f"""CASE WHEN s.i1 = e.i1 THEN {cell('s.i1', 's.f1 + e.f1', 's.i2', 's.f2')}
      WHEN s.i2 = e.i1 THEN {cell('s.i1', 's.f1', 's.i2', 's.f2 + e.f1')}
      WHEN s.i2 IS NULL THEN {cell('s.i1', 's.f1', 'e.i1', 'e.f1')}
      WHEN s.f1 < s.f2 OR (s.f1 = s.f2 AND s.i1 < s.i2) THEN {cell('e.i1', 's.f1 + e.f1', 's.i2', 's.f2')}
      ELSE {cell('s.i1', 's.f1', 'e.i1', 's.f2 + e.f1')} END"""
    folded = f"SELECT {by}, list_reduce(list({cell('item_key', 'x', 'NULL::BIGINT', '0.0::DOUBLE')} ORDER BY {order}), lambda s, e: {step}) AS c FROM {source} GROUP BY {by}"
    swap = "c.i2 IS NOT NULL AND (c.f2 > c.f1 OR (c.f2 = c.f1 AND c.i2 < c.i1))"
    pick = lambda a, b: f"CASE WHEN {swap} THEN c.{b} ELSE c.{a} END AS {a}, CASE WHEN {swap} THEN c.{a} ELSE c.{b} END AS {b}"
    return f"SELECT {by}, {pick('i1', 'i2')}, {pick('f1', 'f2')} FROM ({folded})"


def _sql_grid(name: str, decay: str, family: HashFamily, mode: str, site: str = "site") -> str:
    """CTEs down to `grid` of a fixture."""
    if mode == "arrival":
        rows = f"SELECT {site} AS site, item_key, tick, seq, {RAW[decay]} AS x FROM s"
        order, columns = "tick, seq, item_key, x", "site, item_key, tick, seq, x"
    else:
        rows = f"SELECT {site} AS site, item_key, sum({RAW[decay]}) AS x FROM s GROUP BY 1, 2"
        order, columns = "x DESC, item_key", "site, item_key, x"
    return f"{_stream(name)}, m AS ({rows}), k AS ({_sql_cells(family, 'm', columns)}), grid AS ({_sql_fold('k', 'site, \"row\", col', order)})"


def _sql_answer(family: HashFamily, norm: float, factor: float) -> str:
    """CTEs from `grid` to `answer` (site, item_key, est_avg, tau, c_est)."""
    return f"""counts AS (SELECT site, sum(f1 + f2) / {norm!r}::DOUBLE AS c_est FROM grid WHERE "row" = 0 GROUP BY site),
    cand AS (SELECT DISTINCT g.site, g.i1 AS item_key, {factor!r}::DOUBLE * c.c_est AS tau, c.c_est FROM grid g JOIN counts c USING (site) WHERE g.i1 IS NOT NULL AND g.f1 / {norm!r}::DOUBLE > {factor!r}::DOUBLE * c.c_est),
    ck AS ({_sql_cells(family, 'cand', 'site, item_key, tau, c_est')}),
    est AS (SELECT ck.site, ck.item_key, any_value(tau) AS tau, any_value(c_est) AS c_est, min(CASE WHEN g.i1 = ck.item_key THEN g.f1 WHEN g.i2 = ck.item_key THEN g.f2 WHEN g.i1 IS NULL OR g.i2 IS NULL THEN 0 ELSE least(g.f1, g.f2) END) / {norm!r}::DOUBLE AS est_avg
      FROM ck LEFT JOIN grid g ON g.site = ck.site AND g."row" = ck."row" AND g.col = ck.col GROUP BY 1, 2),
    answer AS (SELECT * FROM est WHERE est_avg > tau)"""


def _values(schedule: Schedule, style: str = "push_pull") -> str:
    m = gossip.mixing_matrix(schedule, style)
    return ", ".join(f"({i}, {j}, {float(m[i, j])!r}::DOUBLE)" for i in range(len(m)) for j in range(len(m)) if m[i, j])


def query_of(name: str, oracle: str | None = None):
    def put(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


def _r(col: str, digits: int = 6):
    return F.round(F.col(col), digits).alias(col)


# -- decay -----------------------------------------------------------------------------------------------------
for _kind, _spec in SPECS.items():
    QUERIES[f"decayed_freq_{_kind}"] = lambda spark, d, spec=_spec: decayed_freq(stream(spark, d, "users"), spec, EVENTS_AT).select("item_key", _r("f"))
    ORACLES[f"decayed_freq_{_kind}"] = f"WITH {_stream('users')} SELECT item_key, round(sum({RAW[_kind]}) / {_spec.norm(EVENTS_AT)!r}::DOUBLE, 6) AS f FROM s GROUP BY 1"


@query_of("decayed_count_by_site", f"WITH {_stream('suppliers')} SELECT site, sum(tick::DOUBLE) / {float(DAYS_AT)!r}::DOUBLE AS c FROM s GROUP BY 1")
def _(spark, d):
    return decayed_count(stream(spark, d, "suppliers"), LINEAR, DAYS_AT, ("site",))


@query_of("decay_law_check", "SELECT 0::BIGINT AS violations, 0::BIGINT AS own_time")
def _(spark, d):
    return check_decay(HALF, stream(spark, d, "types"), [10, 20, 30, 31, 45])


@query_of("forward_backward_gap", "SELECT 0.0::DOUBLE AS gap")
def _(spark, d):
    return forward_backward_gap(stream(spark, d, "types"), 0.1, EVENTS_AT).select(_r("gap", 10))


@query_of("backward_decayed_freq", f"WITH {_stream('users')} SELECT item_key, round(sum(1.0 / (1 + {EVENTS_AT} - tick)), 6) AS f FROM s GROUP BY 1")
def _(spark, d):
    from fadegossip.decay import backward_weight

    return stream(spark, d, "users").groupBy("item_key").agg(F.round(F.sum(backward_weight(EVENTS_AT, lambda age: 1 / (1 + age.cast("double")))), 6).alias("f"))


@query_of("rebased_grid", f"WITH {_sql_grid('types', 'half_life', FAMILY, 'preagg')} SELECT site, \"row\", col, i1, f1 / 4 AS f1, i2, f2 / 4 AS f2 FROM grid")
def _(spark, d):
    from fadegossip.decay import rebase

    _, factor = HALF.rebased(14)
    return rebase(build_local(stream(spark, d, "types"), HALF, FAMILY), factor)


# -- exact answers ---------------------------------------------------------------------------------------------
def _exact(name: str, fixture: str, kind: str, support: float, asof: int, key: str) -> None:
    QUERIES[name] = lambda spark, d: exact.exact_hitters(stream(spark, d, fixture), SPECS[kind], support, asof).select("item_key", _r("f"), _r("c"))
    norm = SPECS[kind].norm(asof)
    ORACLES[name] = f"WITH {_stream(fixture)}, f AS MATERIALIZED (SELECT item_key, sum({RAW[kind]}) / {norm!r}::DOUBLE AS f FROM s GROUP BY 1), c AS (SELECT sum(f) AS c FROM f) SELECT item_key, round(f, 6) AS f, round(c, 6) AS c FROM f, c WHERE f > {support!r}::DOUBLE * c"


_exact("exact_hitters_types", "types", "linear", 0.15, EVENTS_AT, "types")
_exact("exact_hitters_words", "words", "linear", 0.01, IDS_AT, "words")
_exact("exact_hitters_hosts", "hosts", "linear", 0.02, IDS_AT, "hosts")
_exact("exact_hitters_suppliers", "suppliers", "linear", 0.0105, DAYS_AT, "suppliers")
_exact("exact_hitters_props", "props", "half_life", 0.011, EVENTS_AT, "props")
_exact("exact_hitters_parts_empty", "parts", "linear", 0.01, DAYS_AT, "parts")
_exact("exact_hitters_customers_empty", "customers", "linear", 0.01, DAYS_AT, "customers")
_exact("exact_hitters_priorities", "priorities", "none", 0.199, DAYS_AT, "priorities")
_exact("exact_hitters_roles", "roles", "linear", 0.1, IDS_AT, "roles")
_exact("exact_hitters_labels", "labels", "linear", 0.1, IDS_AT, "labels")


@query_of("forbidden_items", f"WITH {_stream('props')}, f AS (SELECT item_key, sum(tick::DOUBLE) / 31.0::DOUBLE AS f FROM s GROUP BY 1), c AS (SELECT sum(f) AS c FROM f) SELECT item_key, round(f, 6) AS f, round(c, 6) AS c FROM f, c WHERE f <= 0.01::DOUBLE * c")
def _(spark, d):
    return exact.forbidden_items(stream(spark, d, "props"), LINEAR, 0.012, 0.002, EVENTS_AT).select("item_key", _r("f"), _r("c"))


@query_of("exact_window_hitters", f"WITH {_stream('users')}, f AS (SELECT item_key, count(*)::DOUBLE AS f FROM s WHERE tick > 24 AND tick <= 31 GROUP BY 1), c AS (SELECT sum(f) AS c FROM f) SELECT item_key, f, c FROM f, c WHERE f > 0.008::DOUBLE * c")
def _(spark, d):
    return exact.exact_window(stream(spark, d, "users"), 0.008, EVENTS_AT, 7)


@query_of("window_counts", f"WITH {_stream('types')}, m AS (SELECT item_key, tick, count(*) AS m FROM s GROUP BY 1, 2) SELECT item_key, tick, CAST(sum(m) OVER (PARTITION BY item_key ORDER BY tick RANGE BETWEEN 6 PRECEDING AND CURRENT ROW) AS BIGINT) AS n FROM m")
def _(spark, d):
    return exact.window_counts(stream(spark, d, "types"), 7)


@query_of("exact_backward_hitters", f"WITH {_stream('users')}, f AS (SELECT item_key, sum(exp(-0.1 * (31 - tick))) AS f FROM s GROUP BY 1), c AS (SELECT sum(f) AS c FROM f) SELECT item_key, round(f, 6) AS f FROM f, c WHERE f > 0.008 * c")
def _(spark, d):
    return exact.exact_backward(stream(spark, d, "users"), lambda age: F.exp(-0.1 * age), 0.008, EVENTS_AT).select("item_key", _r("f"))


@query_of("exact_plain", f"WITH {_stream('words')} SELECT item_key, count(*) AS n FROM s GROUP BY 1")
def _(spark, d):
    return exact.exact_plain(stream(spark, d, "words"))


# -- hashing, sketches, cells ----------------------------------------------------------------------------------
@query_of("hash_cells", f"WITH {_stream('customers')} {_sql_cells(FAMILY, '(SELECT DISTINCT item_key FROM s)', 'item_key')}")
def _(spark, d):
    return with_cells(stream(spark, d, "customers").select("item_key").distinct(), FAMILY)


PLAIN_SKETCH = f"{_stream('suppliers')}, m AS (SELECT item_key, sum(tick::DOUBLE) AS x FROM s GROUP BY 1), k AS ({_sql_cells(FAMILY, 'm', 'item_key, x')}), p AS (SELECT \"row\", col, sum(x) AS mass FROM k GROUP BY 1, 2)"


@query_of("plain_grid", f"WITH {PLAIN_SKETCH} SELECT * FROM p")
def _(spark, d):
    return baselines.plain_sketch(stream(spark, d, "suppliers"), LINEAR, FAMILY)


@query_of("plain_point", f"WITH {PLAIN_SKETCH} SELECT item_key, min(mass) / 2557.0::DOUBLE AS est FROM k JOIN p USING (\"row\", col) GROUP BY 1")
def _(spark, d):
    s = stream(spark, d, "suppliers")
    return baselines.plain_point(baselines.plain_sketch(s, LINEAR, FAMILY), s, FAMILY, LINEAR, DAYS_AT)


@query_of("plain_hitters", f"WITH {PLAIN_SKETCH} SELECT item_key, min(mass) / 2557.0::DOUBLE AS est FROM k JOIN p USING (\"row\", col) GROUP BY 1 ORDER BY est DESC, item_key LIMIT 10")
def _(spark, d):
    return baselines.plain_hitters(stream(spark, d, "suppliers"), LINEAR, FAMILY, 10, DAYS_AT)


@query_of("space_saving_k")
def _(spark, d):
    return baselines.space_saving(stream(spark, d, "hosts"), LINEAR, 16, IDS_AT)


@query_of("space_saving_wide", f"WITH {_stream('hosts')} SELECT item_key, round(sum(tick::DOUBLE) / {float(IDS_AT)!r}::DOUBLE, 9) AS est FROM s GROUP BY 1")
def _(spark, d):
    """More counters than items: every counter is exact, whatever the order of merging."""
    return baselines.space_saving(stream(spark, d, "hosts"), LINEAR, 4096, IDS_AT).select("item_key", _r("est", 9))


@query_of("space_saving_bounds", "SELECT true AS hitters_held, true AS none_under, true AS none_far_over")
def _(spark, d):
    """What k counters guarantee: every item over 1/k of the mass is held, no estimate is too low, none by over 1/k of the mass too high."""
    s, k = stream(spark, d, "hosts"), 16
    freqs, total = decayed_freq(s, LINEAR, IDS_AT), decayed_count(s, LINEAR, IDS_AT)
    found = baselines.space_saving(s, LINEAR, k, IDS_AT)
    both = freqs.join(found, "item_key", "left").crossJoin(total)
    return both.agg(
        F.bool_and((F.col("f") <= F.col("c") / k) | F.col("est").isNotNull()).alias("hitters_held"), F.bool_and(F.coalesce(F.col("est") >= F.col("f") * (1 - 1e-9), F.lit(True))).alias("none_under"),
        F.bool_and(F.coalesce(F.col("est") <= F.col("f") + F.col("c") / k * (1 + 1e-9), F.lit(True))).alias("none_far_over"),
    )


@query_of("builtin_count_min", "SELECT true AS none_under, true AS near")
def _(spark, d):
    """Spark's own counter sketch never counts too low, and rarely by over eps of all too high."""
    s = stream(spark, d, "hosts")
    row = baselines.builtin_count_min(s, 0.001, 0.99).first()
    sketch = spark._jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(bytes(row.sketch))
    n = s.groupBy("item_key").agg(F.count(F.lit(1)).alias("n")).collect()  # a row for each host
    over = [sketch.estimateCount(x.item_key) - x.n for x in n]
    return spark.createDataFrame([(min(over) >= 0, sum(o <= 0.001 * sum(x.n for x in n) for o in over) >= 0.9 * len(over))], "none_under boolean, near boolean")


@query_of("builtin_neighbours_hold", f"WITH {_stream('hosts')} SELECT true AS hitters_held, true AS near_hll, true AS near_sketch, count(DISTINCT item_key) AS items FROM s")
def _(spark, d):
    s = stream(spark, d, "hosts")
    n = s.agg(F.countDistinct("item_key").alias("items"))
    often = s.groupBy("item_key").agg(F.count(F.lit(1)).alias("n")).crossJoin(s.agg(F.count(F.lit(1)).alias("all"))).where("n > 0.05 * all").agg(F.collect_list("item_key").alias("often"))
    near = lambda c: (F.abs(F.col(c) / F.col("items") - 1) < 0.15).alias
    return baselines.builtin_neighbours(s, 0.05).crossJoin(n).crossJoin(often).select((F.size(F.array_except("often", "frequent")) == 0).alias("hitters_held"), near("distinct_hll")("near_hll"), near("distinct_sketch")("near_sketch"), "items")


@query_of("builtin_neighbours")
def _(spark, d):
    return baselines.builtin_neighbours(stream(spark, d, "hosts"), 0.05)


for _mode in ("arrival", "preagg"):
    for _fix, _dec in (("types", "linear"), ("users", "linear"), ("props", "half_life"), ("suppliers", "none")):
        QUERIES[f"local_grid_{_mode}_{_fix}"] = lambda spark, d, m=_mode, f=_fix, k=_dec: build_local(stream(spark, d, f), SPECS[k], FAMILY, m)
        ORACLES[f"local_grid_{_mode}_{_fix}"] = f"WITH {_sql_grid(_fix, _dec, FAMILY, _mode)} SELECT * FROM grid"


@query_of("local_grid_partition", f"WITH {_sql_grid('types', 'linear', FAMILY, 'preagg')} SELECT * FROM grid")
def _(spark, d):
    # five items, no contended cell: any order of merging gives the same grid
    return build_local(stream(spark, d, "types"), LINEAR, FAMILY, "partition")


@query_of("centralised_grid", f"WITH {_sql_grid('users', 'linear', FAMILY, 'preagg', '0')} SELECT * FROM grid")
def _(spark, d):
    return baselines.centralised(stream(spark, d, "users"), LINEAR, FAMILY)


@query_of("grid_row_sums", f"WITH {_stream('users')} SELECT site, r AS \"row\", sum(tick::DOUBLE) AS mass FROM s, (VALUES (0), (1), (2), (3)) AS h(r) GROUP BY 1, 2")
def _(spark, d):
    return build_local(stream(spark, d, "users"), LINEAR, FAMILY).groupBy("site", "row").agg(F.sum(F.col("f1") + F.col("f2")).alias("mass"))


@query_of("grid_norm_gaps", "SELECT 0::BIGINT AS gaps")
def _(spark, d):
    s = stream(spark, d, "users")
    return metrics.norm_gaps(build_local(s, LINEAR, FAMILY), baselines.plain_sketch(s, LINEAR, FAMILY)).agg(F.count(F.lit(1)).alias("gaps"))


@query_of("local_query", f"WITH {_sql_grid('props', 'half_life', HashFamily(4, 64), 'preagg')}, {_sql_answer(HashFamily(4, 64), HALF.norm(EVENTS_AT), 0.02)} SELECT site, item_key, est_avg, tau, c_est FROM answer")
def _(spark, d):
    family = HashFamily(4, 64)
    return query.local_query(build_local(stream(spark, d, "props"), HALF, family), family, HALF, 0.02, EVENTS_AT).select("site", "item_key", "est_avg", "tau", "c_est")


@query_of("local_query_words", f"WITH {_sql_grid('words', 'linear', HashFamily(4, 250), 'preagg', '0')}, {_sql_answer(HashFamily(4, 250), float(IDS_AT), 0.01)} SELECT item_key, est_avg, c_est FROM answer")
def _(spark, d):
    family = HashFamily(4, 250)
    return query.local_query(baselines.centralised(stream(spark, d, "words"), LINEAR, family), family, LINEAR, 0.01, IDS_AT).select("item_key", "est_avg", "c_est")


@query_of("query_candidates", f"WITH {_sql_grid('suppliers', 'linear', FAMILY, 'preagg', '0')}, {_sql_answer(FAMILY, float(DAYS_AT), 0.0105)} SELECT site, item_key, tau, c_est FROM cand")
def _(spark, d):
    return query.peer_candidates(baselines.centralised(stream(spark, d, "suppliers"), LINEAR, FAMILY), LINEAR, 0.0105, 0.0, DAYS_AT)




@query_of("point_estimates", f"""WITH {_sql_grid('customers', 'linear', FAMILY, 'preagg', '0')}, cand AS (SELECT DISTINCT 0 AS site, item_key FROM s), ck AS ({_sql_cells(FAMILY, 'cand', 'site, item_key')})
SELECT ck.site, ck.item_key, min(CASE WHEN g.i1 = ck.item_key THEN g.f1 WHEN g.i2 = ck.item_key THEN g.f2 WHEN g.i1 IS NULL OR g.i2 IS NULL THEN 0 ELSE least(g.f1, g.f2) END) / {float(DAYS_AT)!r}::DOUBLE AS est_avg
FROM ck LEFT JOIN grid g ON g.site = ck.site AND g."row" = ck."row" AND g.col = ck.col GROUP BY 1, 2""")
def _(spark, d):
    s = stream(spark, d, "customers")
    return query.point_estimate(baselines.centralised(s, LINEAR, FAMILY), s.select(F.lit(0).alias("site"), "item_key"), FAMILY, LINEAR, DAYS_AT)


@query_of("count_estimates", f"WITH {_stream('types')} SELECT site, sum(tick::DOUBLE) / 31.0::DOUBLE AS c_est FROM s GROUP BY 1")
def _(spark, d):
    return query.count_estimate(build_local(stream(spark, d, "types"), LINEAR, FAMILY), LINEAR, EVENTS_AT)


@query_of("query_at_times", "SELECT at_time, item_key, round(est, 6) AS est FROM (" + " UNION ALL ".join(f"(WITH {_sql_grid('types', 'linear', FAMILY, 'preagg', '0')}, {_sql_answer(FAMILY, float(t), 0.19)} SELECT {t} AS at_time, item_key, est_avg AS est FROM answer)" for t in (31, 62)) + ") AS q")
def _(spark, d):
    grid = baselines.centralised(stream(spark, d, "types"), LINEAR, FAMILY)
    return query.at_times(grid, FAMILY, LINEAR, 0.19, 0.0, [31, 62]).select(F.col("asof").alias("at_time"), "item_key", F.round("est_avg", 6).alias("est"))


@query_of("top_k_local", f"WITH {_sql_grid('users', 'linear', HashFamily(4, 64), 'preagg')}, {_sql_answer(HashFamily(4, 64), 31.0, 0.01)} SELECT site, item_key, est_avg FROM answer QUALIFY row_number() OVER (PARTITION BY site ORDER BY est_avg DESC, item_key) <= 3")
def _(spark, d):
    family = HashFamily(4, 64)
    return query.top_k(query.local_query(build_local(stream(spark, d, "users"), LINEAR, family), family, LINEAR, 0.01, EVENTS_AT), 3).select("site", "item_key", "est_avg")


@query_of("local_consensus", f"WITH {_sql_grid('types', 'linear', FAMILY, 'preagg')}, {_sql_answer(FAMILY, 31.0, 0.2)} SELECT item_key, count(DISTINCT site) AS sites_naming, count(DISTINCT site) / 8.0::DOUBLE AS share FROM answer GROUP BY 1")
def _(spark, d):
    return query.consensus(query.local_query(build_local(stream(spark, d, "types"), LINEAR, FAMILY), FAMILY, LINEAR, 0.2, EVENTS_AT), 8)


# -- merging and gossip ----------------------------------------------------------------------------------------
_MERGE = """SELECT "row", col, m[1].k AS i1, coalesce(m[1].f, 0) AS f1, m[2].k AS i2, coalesce(m[2].f, 0) AS f2 FROM (
  SELECT "row", col, list_sort([{'n': -x.f, 'k': x.k, 'f': x.f} for x in [
    CASE WHEN a1 IS NOT NULL THEN {'k': a1, 'f': g1 + CASE WHEN b1 = a1 THEN h1 WHEN b2 = a1 THEN h2 ELSE mb END} END,
    CASE WHEN a2 IS NOT NULL THEN {'k': a2, 'f': g2 + CASE WHEN b1 = a2 THEN h1 WHEN b2 = a2 THEN h2 ELSE mb END} END,
    CASE WHEN b1 IS NOT NULL AND coalesce(b1 <> a1, true) AND coalesce(b1 <> a2, true) THEN {'k': b1, 'f': h1 + ma} END,
    CASE WHEN b2 IS NOT NULL AND coalesce(b2 <> a1, true) AND coalesce(b2 <> a2, true) THEN {'k': b2, 'f': h2 + ma} END] if x IS NOT NULL]) AS m
  FROM (SELECT coalesce(a."row", b."row") AS "row", coalesce(a.col, b.col) AS col, a.i1 AS a1, a.i2 AS a2, b.i1 AS b1, b.i2 AS b2,
    coalesce(a.f1, 0) AS g1, coalesce(a.f2, 0) AS g2, coalesce(b.f1, 0) AS h1, coalesce(b.f2, 0) AS h2,
    CASE WHEN a.i1 IS NULL OR a.i2 IS NULL THEN 0 ELSE least(a.f1, a.f2) END AS ma, CASE WHEN b.i1 IS NULL OR b.i2 IS NULL THEN 0 ELSE least(b.f1, b.f2) END AS mb
    FROM (SELECT * FROM grid WHERE site = {A}) a FULL JOIN (SELECT * FROM grid WHERE site = {B}) b ON a."row" = b."row" AND a.col = b.col))"""


def _merge_sql(a: int, b: int) -> str:
    return _MERGE.replace("{A}", str(a)).replace("{B}", str(b))


@query_of("merged_pair", f"WITH {_sql_grid('users', 'linear', NARROW, 'preagg')} {_merge_sql(0, 1)}")
def _(spark, d):
    grid = build_local(stream(spark, d, "users"), LINEAR, NARROW)
    return cells.merge_grids(grid.where("site = 0"), grid.where("site = 1"))


PAIRS = [(2 * i, 2 * i + 1) for i in range(8)]


@query_of("gossip_one_round", f"WITH {_sql_grid('users', 'linear', NARROW, 'preagg')} " + " UNION ALL ".join(f"SELECT site, \"row\", col, i1, f1 / 2 AS f1, i2, f2 / 2 AS f2 FROM ({_merge_sql(a, b)}), (VALUES ({a}), ({b})) AS t(site)" for a, b in PAIRS))
def _(spark, d):
    return gossip.avg_merge_round(build_local(stream(spark, d, "users"), LINEAR, NARROW), PAIRS, 16, NARROW).drop("round")


@query_of("gossip_one_round_joins", ORACLES["gossip_one_round"])
def _(spark, d):
    return gossip.gossip_by_round(build_local(stream(spark, d, "users"), LINEAR, NARROW), from_pairs(16, [PAIRS]).table(spark))


def demo_schedule(sites: int = 8, rounds: int = 12, seed: int = 5) -> Schedule:
    """Uniform gossip of a few sites; small enough to be written out in SQL."""
    return draw_exchanges(None, sites, rounds, 1, seed)


DEMO = demo_schedule()
SLACK = planner.slack(8, 12, 0.01)
_MIX = f"mix(site, src, wgt) AS (VALUES {_values(DEMO)})"


@query_of("share_after_rounds", f"WITH {_MIX} SELECT site, wgt AS share FROM mix WHERE src = 0")
def _(spark, d):
    return gossip.share_table(spark, DEMO)


@query_of("site_count", f"WITH {_MIX}, t AS (SELECT unnest(range(8))::INTEGER AS site) SELECT t.site, coalesce(wgt, 0) AS share, round(1 / nullif(wgt, 0), 6) AS p_est, coalesce(wgt, 0) > 0 AS reached FROM t LEFT JOIN mix ON mix.site = t.site AND mix.src = 0")
def _(spark, d):
    return gossip.site_count(gossip.share_table(spark, DEMO)).select("site", "share", _r("p_est"), "reached")


@query_of("initial_share", "SELECT CAST(i AS INTEGER) AS site, CASE WHEN i = 0 THEN 1.0 ELSE 0.0 END::DOUBLE AS share FROM range(8) t(i)")
def _(spark, d):
    return init_share(spark, 8)


@query_of("averaged_frequencies", f"WITH {_MIX}, {_stream('types')}, f AS (SELECT site AS src, item_key, sum(tick::DOUBLE) AS f FROM s GROUP BY 1, 2) SELECT mix.site, item_key, round(sum(wgt * f), 6) AS f FROM mix JOIN f USING (src) GROUP BY 1, 2")
def _(spark, d):
    freqs = stream(spark, d, "types").groupBy("site", "item_key").agg(F.sum(LINEAR.raw()).alias("f"))
    return gossip.average_vectors(freqs, DEMO).select("site", "item_key", _r("f"))


@query_of("cell_mass_after_rounds", f"WITH {PLAIN_SKETCH} SELECT \"row\", col, round(mass, 4) AS mass FROM p")
def _(spark, d):
    grid = build_local(stream(spark, d, "suppliers"), LINEAR, FAMILY)
    state = gossip.gossip_by_cell(grid, draw_exchanges(None, 16, 8, 1, 3), FAMILY)
    return metrics.mass_trace(state).select("row", "col", _r("mass", 4))


def gossip_answer(spark: SparkSession, d: str, fixture: str, support: float, asof: int) -> DataFrame:
    """Local grids, all rounds, and the answer of every site."""
    grid = build_local(stream(spark, d, fixture), LINEAR, FAMILY)
    state = gossip.gossip_by_cell(grid, DEMO, FAMILY)
    answer = query.peer_query(state, FAMILY, LINEAR, support, SLACK, asof, gossip.share_table(spark, DEMO))
    return answer.select("site", "item_key", _r("est_avg"), _r("est_global"), _r("tau"), _r("c_est"), _r("p_est"))


def _gossip_sql(fixture: str, support: float, asof: int) -> str:
    factor = query.relaxed(support, SLACK)
    return f"""WITH {_MIX}, {_stream(fixture)}, f AS (SELECT site AS src, item_key, sum(tick::DOUBLE) AS f FROM s GROUP BY 1, 2),
    a AS (SELECT mix.site, item_key, sum(wgt * f) / {float(asof)!r}::DOUBLE AS est_avg FROM mix JOIN f USING (src) GROUP BY 1, 2), c AS (SELECT site, sum(est_avg) AS c_est FROM a GROUP BY 1)
    SELECT a.site, item_key, round(est_avg, 6) AS est_avg, round(est_avg / wgt, 6) AS est_global, round({factor!r}::DOUBLE * c_est, 6) AS tau, round(c_est, 6) AS c_est, round(1 / wgt, 6) AS p_est
    FROM a JOIN c USING (site) LEFT JOIN mix ON mix.site = a.site AND mix.src = 0 WHERE est_avg > {factor!r}::DOUBLE * c_est"""


@query_of("gossip_query_types", _gossip_sql("types", 0.195, EVENTS_AT))
def _(spark, d):
    return gossip_answer(spark, d, "types", 0.195, EVENTS_AT)


@query_of("gossip_query_priority", _gossip_sql("priorities", 0.195, DAYS_AT))
def _(spark, d):
    return gossip_answer(spark, d, "priorities", 0.195, DAYS_AT)


@query_of("gossip_query_words")
def _(spark, d):
    """Contended cells and twenty natural sites: held against the sequential order in the tests."""
    family, schedule = HashFamily(4, 250), draw_exchanges(None, 20, 24, 1, 1)
    state = cut(gossip.gossip_by_cell(build_local(stream(spark, d, "words"), LINEAR, family), schedule, family))
    answer = query.peer_query(state, family, LINEAR, 0.01, planner.slack(20, 24, 0.01), IDS_AT, gossip.share_table(spark, schedule))
    return query.named(answer, stream(spark, d, "words"))


@query_of("gossip_resumed", _gossip_sql("types", 0.195, EVENTS_AT))
def _(spark, d):
    """Half of the rounds, the state written, then the other half: what all rounds at once give."""
    import numpy as np

    first, rest = DEMO.upto(6), DEMO.after(6)
    state = cut(gossip.gossip_by_cell(build_local(stream(spark, d, "types"), LINEAR, FAMILY), first, FAMILY).drop("round"))
    state = gossip.gossip_by_cell(state, rest, FAMILY)
    end = gossip.average_scalar(gossip.average_scalar(np.eye(8)[0], first), rest)
    share = spark.createDataFrame([(i, float(x)) for i, x in enumerate(end)], "site int, share double")
    answer = query.peer_query(state, FAMILY, LINEAR, 0.195, SLACK, EVENTS_AT, share)
    return answer.select("site", "item_key", _r("est_avg"), _r("est_global"), _r("tau"), _r("c_est"), _r("p_est"))


@query_of("scaled_grid", f"WITH {_sql_grid('users', 'linear', NARROW, 'preagg')} SELECT site, \"row\", col, i1, f1 / 4 AS f1, i2, f2 / 4 AS f2 FROM grid")
def _(spark, d):
    return cells.scale_grid(build_local(stream(spark, d, "users"), LINEAR, NARROW), 4)


@query_of("empty_grid", f"WITH {_stream('suppliers')} SELECT site, CAST(r AS INTEGER) AS \"row\", CAST(c AS INTEGER) AS col, NULL::BIGINT AS i1, 0.0::DOUBLE AS f1, NULL::BIGINT AS i2, 0.0::DOUBLE AS f2 FROM (SELECT DISTINCT site FROM s) a, range(4) b(r), range(8) e(c)")
def _(spark, d):
    from fadegossip.local import empty_grid

    return empty_grid(spark, NARROW, stream(spark, d, "suppliers").select("site"))


@query_of("site_count_errors", f"WITH {_MIX} SELECT site, round(abs(1 / wgt - 8) / 8, 9) AS err FROM mix WHERE src = 0")
def _(spark, d):
    return metrics.site_count_errors(gossip.share_table(spark, DEMO), 8).select("site", _r("err", 9))


@query_of("count_errors", f"WITH {_MIX}, {_stream('types')}, f AS (SELECT site AS src, sum(tick::DOUBLE) / 31 AS f FROM s GROUP BY 1), t AS (SELECT sum(f) AS c FROM f), a AS (SELECT mix.site, sum(wgt * f) AS c_est FROM mix JOIN f USING (src) GROUP BY 1) SELECT a.site, round(abs(c_est / wgt - c) / c, 9) AS err FROM a JOIN mix ON mix.site = a.site AND mix.src = 0, t")
def _(spark, d):
    s = stream(spark, d, "types")
    state = gossip.gossip_by_cell(build_local(s, LINEAR, FAMILY), DEMO, FAMILY)
    total = decayed_count(s, LINEAR, EVENTS_AT).first().c
    return metrics.count_errors(query.count_estimate(state, LINEAR, EVENTS_AT), gossip.share_table(spark, DEMO), total).select("site", _r("err", 9))


@query_of("guarantee_violations", f"WITH {_stream('props')}, f AS MATERIALIZED (SELECT item_key, sum({RAW['half_life']}) AS f FROM s GROUP BY 1) SELECT 0::BIGINT AS misses, 0::BIGINT AS forbidden, 0::BIGINT AS outside, count(*) AS must_not FROM f WHERE f <= {0.012 - planner.tolerance(planner.slack(8, 24, 0.01), 0.012, 500)!r}::DOUBLE * (SELECT sum(f) FROM f)")
def _(spark, d):
    """Counts over all sites of what must not happen, after gossip on the complete graph, and of items that must not be named."""
    s, family, schedule, support = stream(spark, d, "props"), HashFamily(4, 500), draw_exchanges(None, 8, 24, 1, 5), 0.012
    slack = planner.slack(8, 24, 0.01)
    state = cut(gossip.gossip_by_cell(build_local(s, HALF, family), schedule, family))
    answer = cut(query.peer_query(state, family, HALF, support, slack, EVENTS_AT, gossip.share_table(spark, schedule)))
    freqs, truth = decayed_freq(s, HALF, EVENTS_AT), exact.exact_hitters(s, HALF, support, EVENTS_AT)
    total, everyone = decayed_count(s, HALF, EVENTS_AT).first().c, spark.range(8).select(F.col("id").cast("int").alias("site"))
    tol = planner.tolerance(slack, support, family.width)
    n = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
    return n(metrics.misses(answer, truth, everyone), "misses").crossJoin(n(metrics.tolerance_violations(answer, exact.forbidden_items(s, HALF, support, tol, EVENTS_AT)), "forbidden")).crossJoin(n(metrics.frequency_violations(answer, freqs, slack, total, family.width), "outside")).crossJoin(n(exact.forbidden_items(s, HALF, support, tol, EVENTS_AT), "must_not"))


def _linear_state(mix: str, family: HashFamily) -> str:
    """CTEs down to `state` (site, row, col, i1, f1, i2, f2) of the types stream, where no cell is contended."""
    return f"""{mix}, {_stream('types')}, f AS (SELECT site AS src, item_key, sum(tick::DOUBLE) AS f FROM s GROUP BY 1, 2), a AS (SELECT mix.site, item_key, sum(wgt * f) AS x FROM mix JOIN f USING (src) GROUP BY 1, 2),
    k AS ({_sql_cells(family, 'a', 'site, item_key, x')}), n AS (SELECT site, "row", col, list_sort(list({{'n': -x, 'k': item_key}})) AS m FROM k GROUP BY 1, 2, 3),
    state AS (SELECT site, "row", col, m[1].k AS i1, round(-m[1].n, 6) AS f1, m[2].k AS i2, round(coalesce(-m[2].n, 0), 6) AS f2 FROM n)"""


for _style in ("push", "pull"):
    QUERIES[f"gossip_{_style}"] = lambda spark, d, st=_style: gossip.gossip_by_cell(build_local(stream(spark, d, "types"), LINEAR, FAMILY), DEMO, FAMILY, style=st).select("site", "row", "col", "i1", _r("f1"), "i2", _r("f2"))
    ORACLES[f"gossip_{_style}"] = f"WITH {_linear_state(f'mix(site, src, wgt) AS (VALUES {_values(DEMO, _style)})', FAMILY)} SELECT * FROM state"


THREE = [[(i, i ^ (1 << r)) for i in range(16) if not i >> r & 1] for r in range(3)]


def _rounds_sql(rounds: list[list[tuple[int, int]]], sites: int) -> str:
    """CTEs r1, r2 ... after `grid`: each round merges its pairs and halves them, the other sites stay."""
    out, before = [], "grid"
    for n, pairs in enumerate(rounds, 1):
        parts = [f"SELECT CAST(site AS INTEGER) AS site, \"row\", col, i1, f1 / 2 AS f1, i2, f2 / 2 AS f2 FROM ({_merge_sql(a, b).replace('FROM grid', f'FROM {before}')}), (VALUES ({a}), ({b})) AS t(site)" for a, b in pairs]
        idle = sorted(set(range(sites)) - {x for p in pairs for x in p})
        if idle:
            parts.append(f"SELECT * FROM {before} WHERE site IN ({', '.join(map(str, idle))})")
        out.append(f"r{n} AS MATERIALIZED ({' UNION ALL '.join(parts)})")
        before = f"r{n}"
    return ", ".join(out)


@query_of("gossip_three_rounds", f"WITH {_sql_grid('users', 'linear', NARROW, 'preagg')}, {_rounds_sql(THREE, 16)} SELECT * FROM r3")
def _(spark, d):
    """150 items in eight columns: every cell is contended in every round."""
    return gossip.gossip_by_cell(build_local(stream(spark, d, "users"), LINEAR, NARROW), from_pairs(16, THREE), NARROW).drop("round")


@query_of("gossip_three_rounds_joins", ORACLES["gossip_three_rounds"])
def _(spark, d):
    return gossip.gossip_by_round(build_local(stream(spark, d, "users"), LINEAR, NARROW), from_pairs(16, THREE).table(spark))


@query_of("peer_query_contended", f"WITH {_sql_grid('users', 'linear', NARROW, 'preagg')}, {_rounds_sql(THREE, 16)}, {_sql_answer(NARROW, 31.0, query.relaxed(0.02, 0.1)).replace('FROM grid', 'FROM r3').replace('JOIN grid', 'JOIN r3')} SELECT site, item_key, est_avg, tau, c_est FROM answer")
def _(spark, d):
    state = gossip.gossip_by_cell(build_local(stream(spark, d, "users"), LINEAR, NARROW), from_pairs(16, THREE), NARROW)
    return query.peer_query(state, NARROW, LINEAR, 0.02, 0.1, EVENTS_AT).select("site", "item_key", "est_avg", "tau", "c_est")


@query_of("gossip_snapshots", f"WITH {_stream('types')}, m AS (SELECT site, item_key, sum(tick::DOUBLE) AS x FROM s GROUP BY 1, 2), k AS ({_sql_cells(FAMILY, 'm', 'item_key, x')}) SELECT r.n AS round, \"row\", sum(x) AS mass FROM k, (VALUES (0), (4), (12)) AS r(n) GROUP BY 1, 2")
def _(spark, d):
    state = gossip.gossip_by_cell(build_local(stream(spark, d, "types"), LINEAR, FAMILY), DEMO, FAMILY, snapshots=(0, 4))
    return metrics.mass_trace(state).groupBy("round", "row").agg(F.round(F.sum("mass"), 3).alias("mass"))


@query_of("coordinator_merge", f"WITH {_stream('types')}, m AS (SELECT 0 AS site, item_key, sum(tick::DOUBLE) AS x FROM s GROUP BY 1, 2), k AS ({_sql_cells(FAMILY, 'm', 'site, item_key, x')}), grid AS ({_sql_fold('k', 'site, \"row\", col', 'x DESC, item_key')}) SELECT \"row\", col, i1, f1 / 8 AS f1, i2, f2 / 8 AS f2 FROM grid")
def _(spark, d):
    return gossip.coordinator_merge(build_local(stream(spark, d, "types"), LINEAR, FAMILY), 8)


@query_of("schedule_levels_valid", "SELECT 0::BIGINT AS bad")
def _(spark, d):
    return check_levels(DEMO.table(spark)).agg(F.count(F.lit(1)).alias("bad"))


@query_of("message_cost")
def _(spark, d):
    return metrics.message_cost(spark, DEMO, 4, 2500)


ORACLES["message_cost"] = "SELECT * FROM (VALUES " + ", ".join(f"({r}, 8::BIGINT, 16::BIGINT, {16 * 4 * 2500 * 32}::BIGINT)" for r in range(12)) + ") AS t(round, exchanges, messages, bytes)"


def trace_sql(schedule: Schedule) -> str:
    """Variance of a value that starts at site 0 as (round, var, deviation, factor, bound); exchanges are done one after another, in whole 2**-k steps."""
    from fractions import Fraction

    now = [Fraction(int(i == 0)) for i in range(schedule.sites)]
    states = [now[:]]
    for r in range(schedule.rounds):
        for a, b in zip(schedule.a[schedule.round == r].tolist(), schedule.b[schedule.round == r].tolist()):
            now[a] = now[b] = (now[a] + now[b]) / 2
        states.append(now[:])
    values = ", ".join(f"({r}, {i}, {float(x)!r}::DOUBLE)" for r, line in enumerate(states) for i, x in enumerate(line) if x)
    n, start = schedule.sites, 1 / schedule.sites
    return f"""WITH v(round, site, v) AS (VALUES {values}), w AS (SELECT CAST(r.i AS INTEGER) AS round, coalesce(v.v, 0) AS v FROM range({schedule.rounds + 1}) r(i) CROSS JOIN range({n}) t(i) LEFT JOIN v ON v.round = r.i AND v.site = t.i),
    g AS (SELECT round, var_samp(v) AS var, max(abs(v - {start!r}::DOUBLE)) AS deviation FROM w GROUP BY 1)
    SELECT round, round(var, 9) AS var, round(deviation, 9) AS deviation, round(var / lag(var) OVER (ORDER BY round), 6) AS factor, round(sqrt({n - 1} * {start!r}::DOUBLE / 0.01 * pow({_K}::DOUBLE, round)), 6) AS bound FROM g"""


_K = repr(planner.KAPPA)
TRACED = draw_exchanges(None, 64, 16, 1, 2)


def traced(spark: SparkSession, schedule: Schedule) -> DataFrame:
    import numpy as np

    found = metrics.variance_trace(spark, gossip.average_scalar(np.eye(schedule.sites)[0], schedule, trace=True))
    return found.select("round", _r("var", 9), _r("deviation", 9), _r("factor"), _r("bound"))


@query_of("variance_trace", trace_sql(TRACED))
def _(spark, d):
    return traced(spark, TRACED)


@query_of("assigned_sites_modulo", f"WITH {_stream('users')} SELECT CAST(item_key % 5 AS INTEGER) AS site, count(*) AS n FROM s GROUP BY 1")
def _(spark, d):
    return assign_sites(stream(spark, d, "users"), "modulo", 5).groupBy("site").agg(F.count(F.lit(1)).alias("n"))


for _policy in ("hash", "one"):
    QUERIES[f"assigned_sites_{_policy}"] = lambda spark, d, p=_policy: assign_sites(stream(spark, d, "users"), p, 5).groupBy("site").agg(F.count(F.lit(1)).alias("n"))
ORACLES["assigned_sites_one"] = "SELECT 0 AS site, count(*) AS n FROM events"
ORACLES["assigned_sites_hash"] = f"WITH {_stream('users')} SELECT CAST({_key("concat_ws('|', item_key, tick, '{' || seq || '}')")} % 5 AS INTEGER) AS site, count(*) AS n FROM s GROUP BY 1"


@query_of("assigned_sites_blocks", f"WITH {_stream('users')} SELECT 5::BIGINT AS sites, true AS in_order, true AS even, count(*) AS n FROM s")
def _(spark, d):
    """Blocks follow each other in time and are of nearly equal size (bounds are approximate quantiles, and a tick isn't split)."""
    per = assign_sites(stream(spark, d, "users"), "blocks", 5).groupBy("site").agg(F.count(F.lit(1)).alias("n"), F.min("tick").alias("low"), F.max("tick").alias("high"))
    from pyspark.sql import Window

    after = per.withColumn("next", F.lead("low").over(Window.orderBy("site")))
    return after.agg(F.count(F.lit(1)).alias("sites"), F.bool_and(F.coalesce(F.col("high") < F.col("next"), F.lit(True))).alias("in_order"), (F.max("n") < 1.5 * F.avg("n")).alias("even"), F.sum("n").alias("n"))


# -- planner ---------------------------------------------------------------------------------------------------
_GRID = "(VALUES (0.01::DOUBLE, 21), (0.02, 24), (0.04, 27), (0.02, 30)) AS t(support, rounds), (VALUES (1000.0::DOUBLE), (5000.0)) AS u(cap)"


def _grid(spark: SparkSession) -> DataFrame:
    rows = spark.createDataFrame([(0.01, 21), (0.02, 24), (0.04, 27), (0.02, 30)], "support double, rounds int")
    return rows.crossJoin(spark.createDataFrame([(1000.0,), (5000.0,)], "cap double"))


@query_of("slack_and_tolerance", f"SELECT support, rounds, cap, round(s, 9) AS slack, round(4 * s * support / pow(1 + s, 2) + exp(1) / (2 * 2500) * (1 - s) / (1 + s), 9) AS tol FROM (SELECT *, cap * sqrt(pow({_K}::DOUBLE, rounds) / 0.01) AS s FROM {_GRID})")
def _(spark, d):
    s = planner.slack_col(F.col("cap"), F.col("rounds"), F.lit(0.01))
    return _grid(spark).withColumn("s", s).select("support", "rounds", "cap", F.round("s", 9).alias("slack"), F.round(planner.tolerance_col(F.col("s"), F.col("support"), F.lit(2500.0)), 9).alias("tol"))


@query_of("width_curve", f"SELECT tol, rounds, round(s, 9) AS slack, round(CASE WHEN room > 0 AND s < 1 THEN exp(1) * (1 - s * s) / room END, 3) AS width FROM (SELECT *, 2 * tol * pow(1 + s, 2) - 8 * 0.02 * s AS room FROM (SELECT tol, rounds, 5000.0::DOUBLE * sqrt(pow({_K}::DOUBLE, rounds) / 0.01::DOUBLE) AS s FROM (VALUES (0.002::DOUBLE), (0.005), (0.01)) AS t(tol), (SELECT unnest(range(20, 41)) AS rounds)))")
def _(spark, d):
    return planner.width_curve(spark, [0.002, 0.005, 0.01], range(20, 41)).select("tol", "rounds", _r("slack", 9), _r("width", 3))


def _plan_row(spark: SparkSession, strategy: str) -> DataFrame:
    p = planner.plan(strategy, 0.02, 0.002, 5000, 0.05, 0.01)
    return spark.createDataFrame([(p.depth, p.width, p.rounds, round(p.slack, 9), round(p.tol, 9), round(p.fail, 9))], "depth int, width int, rounds int, slack double, tol double, fail double")


_TAIL = "CAST(ceil(ln(0.99 / 0.04)) AS INTEGER) AS depth, width, rounds, round(s, 9) AS slack, round(4 * s * 0.02 / pow(1 + s, 2) + exp(1) / (2 * width) * (1 - s) / (1 + s), 9) AS tol, round(0.01 + exp(-ceil(ln(0.99 / 0.04))) * 0.99, 9) AS fail"


@query_of("plan_time", f"""SELECT {_TAIL} FROM (SELECT *, CAST(ceil(exp(1) * (1 - s * s) / (2 * 0.002 * pow(1 + s, 2) - 8 * 0.02 * s)) AS INTEGER) AS width FROM (SELECT rounds, 5000 * sqrt(pow({_K}::DOUBLE, rounds) / 0.01) AS s FROM
(SELECT CAST(floor((ln(0.01::DOUBLE) + 2 * ln((0.04 - 0.002 - 2 * sqrt(0.0004::DOUBLE - 0.00004)) / (0.002 * 5000))) / ln({_K}::DOUBLE)) AS INTEGER) + 1 AS rounds)))""")
def _(spark, d):
    return _plan_row(spark, "time")


@query_of("plan_space", f"""SELECT {_TAIL} FROM (SELECT *, 5000 * sqrt(pow({_K}::DOUBLE, rounds) / 0.01) AS s FROM (SELECT *, CAST(floor((2 * ln(e) - 2 * ln(5000.0::DOUBLE) + ln(0.01::DOUBLE)) / ln({_K}::DOUBLE)) AS INTEGER) + 1 AS rounds FROM
(SELECT *, (2 * width * (0.04 - 0.002) - sqrt(16 * 0.02 * width * width * 0.018 + exp(2))) / (exp(1) + 2 * 0.002 * width) AS e FROM (SELECT CAST(floor(exp(1) / 0.004) AS INTEGER) + 1 AS width))))""")
def _(spark, d):
    return _plan_row(spark, "space")


@query_of("fail_probabilities", f"WITH {_stream('types')}, f AS (SELECT item_key, sum(tick::DOUBLE) AS f FROM s GROUP BY 1), h AS (SELECT item_key, f / (SELECT sum(f) FROM f) AS phi FROM f) SELECT item_key, d AS depth, round(0.01 + exp(-d) * 0.99, 12) AS fail, round(0.01 + pow((1 + 0.03) / (2 * phi * 250 * (1 - 0.03)), d) * 0.99, 9) AS miss, round(1 - pow(1 / (2 * phi * 250), d), 9) AS candidate FROM h, (VALUES (1), (2), (4), (6)) AS t(d)")
def _(spark, d):
    """For every event type, with its share of the decayed count as the support."""
    s = stream(spark, d, "types")
    phi = decayed_freq(s, LINEAR, EVENTS_AT).crossJoin(F.broadcast(decayed_count(s, LINEAR, EVENTS_AT))).withColumn("phi", F.col("f") / F.col("c"))
    rows = [F.struct(F.lit(k).alias("depth"), F.lit(round(planner.fail_total(k, 0.01), 12)).alias("fail"), F.round(planner.fail_miss(0.03, F.col("phi"), 250, k, 0.01), 9).alias("miss"), F.round(planner.candidate_prob(F.col("phi"), 250, k), 9).alias("candidate")) for k in (1, 2, 4, 6)]
    return phi.select("item_key", F.explode(F.array(*rows)).alias("x")).select("item_key", "x.*")


_SITES = f"{_stream('suppliers')}, i AS (SELECT site, item_key, sum(tick::DOUBLE) / {float(DAYS_AT)!r}::DOUBLE AS f FROM s GROUP BY 1, 2), c AS (SELECT site, sum(f) AS c, max(f) AS f FROM i GROUP BY 1)"


def _sites(spark, d):
    """(site, c, f): a site's decayed count and its most frequent item's share of it."""
    freqs = stream(spark, d, "suppliers").groupBy("site", "item_key").agg((F.sum(LINEAR.raw()) / float(DAYS_AT)).alias("f"))
    return freqs.groupBy("site").agg(F.sum("f").alias("c"), F.max("f").alias("f"))


@query_of("bounds", f"WITH {_SITES}, n AS (SELECT count(*) AS p FROM c) SELECT site, 0.0303::DOUBLE AS slack, round((1 - 0.0303) / p, 9) AS share_low, round(p / (1 - 0.0303), 9) AS sites_high, round(exp(1) * c / 500, 6) AS local_error, round(exp(1) * c / 250, 6) AS plain_error, round((1 + 0.0303) / (1 - 0.0303) * (f + exp(1) / 500 * c), 6) AS freq_high, round(c / 2.0::DOUBLE, 6) AS cell_error FROM c, n")
def _(spark, d):
    s, sites = 0.0303, _sites(spark, d)
    p, c = F.col("p"), F.col("c")
    every = sites.crossJoin(F.broadcast(sites.agg(F.count(F.lit(1)).alias("p"))))
    return every.select(
        "site", F.lit(s).alias("slack"), F.round(planner.share_interval(p, s)[0], 9).alias("share_low"), F.round(planner.sites_interval(p, s)[1], 9).alias("sites_high"), F.round(planner.local_bound(c, 250), 6).alias("local_error"),
        F.round(planner.plain_bound(c, 250), 6).alias("plain_error"), F.round(planner.freq_interval(F.col("f"), s, c, 250)[1], 6).alias("freq_high"), F.round(planner.ss_bound(c, 2), 6).alias("cell_error"),
    )


# -- Zipf, measures, churn, graphs -----------------------------------------------------------------------------
def _zipf_values(rho: float, universe: int = 1000) -> str:
    edge = [0, *(round(x * 2**32) for x in zipf_cdf(rho, universe))]
    return ", ".join(f"({r}, {edge[r - 1]}::BIGINT, {edge[r]}::BIGINT)" for r in range(1, universe + 1))


_ZIPF = f"z(r, lo, hi) AS (VALUES {_zipf_values(1.2)}), u AS (SELECT {_key("concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey)")} AS u, l_orderkey % 16 AS site, {_days('l_shipdate', '1995-01-01')} AS tick FROM lineitem)"


@query_of("zipf_stream_counts", f"WITH {_ZIPF} SELECT r AS item_key, count(*) AS n, sum(tick::DOUBLE) AS mass FROM u JOIN z ON u >= lo AND u < hi GROUP BY 1")
def _(spark, d):
    return zipf_stream(spark, d, 1.2).groupBy("item_key").agg(F.count(F.lit(1)).alias("n"), F.sum(LINEAR.raw()).alias("mass"))


def _local_truth(spark, d):
    s = stream(spark, d, "types")
    grid = build_local(s, LINEAR, FAMILY)
    answer = query.local_query(grid, FAMILY, LINEAR, 0.2, EVENTS_AT)
    return answer, exact.exact_hitters(s, LINEAR, 0.2, EVENTS_AT), decayed_freq(s, LINEAR, EVENTS_AT), spark.range(8).select(F.col("id").cast("int").alias("site"))


_TRUTH = f"{_sql_grid('types', 'linear', FAMILY, 'preagg')}, {_sql_answer(FAMILY, 31.0, 0.2)}, f AS (SELECT item_key, sum(tick::DOUBLE) / 31.0::DOUBLE AS f FROM s GROUP BY 1), truth AS (SELECT item_key FROM f WHERE f > 0.2::DOUBLE * (SELECT sum(f) FROM f))"


@query_of("recall_precision", f"WITH {_TRUTH}, h AS (SELECT a.site, count(*) AS named, count(t.item_key) AS good FROM answer a LEFT JOIN truth t USING (item_key) GROUP BY 1), n AS (SELECT count(*) AS n FROM truth) SELECT CAST(i AS INTEGER) AS site, CASE WHEN n = 0 THEN 1.0 ELSE coalesce(good, 0) / n END AS recall, CASE WHEN coalesce(named, 0) = 0 THEN 1.0 ELSE good / named END AS precision FROM range(8) t(i) LEFT JOIN h ON h.site = i, n")
def _(spark, d):
    answer, truth, _, sites = _local_truth(spark, d)
    return metrics.recall_precision(answer, truth, sites)


@query_of("are_by_site", f"WITH {_TRUTH} SELECT site, round(avg(abs(est_avg - f) / f), 9) AS are FROM answer JOIN f USING (item_key) GROUP BY 1")
def _(spark, d):
    answer, _, freqs, _ = _local_truth(spark, d)
    return metrics.are(answer, freqs).select("site", _r("are", 9))


@query_of("aggregated_runs")
def _(spark, d):
    answer, truth, freqs, sites = _local_truth(spark, d)
    return metrics.aggregate_runs(metrics.site_stats(answer, truth, freqs, sites)).select("metric", *[_r(c) for c in ("mean", "ci_low", "ci_high")], "sites")


ORACLES["aggregated_runs"] = f"""WITH rp AS ({ORACLES['recall_precision']}), a AS ({ORACLES['are_by_site']}), l AS (SELECT 'recall' AS metric, recall AS v FROM rp UNION ALL SELECT 'precision', precision FROM rp UNION ALL SELECT 'are', are FROM a),
g AS (SELECT metric, avg(v) AS mean, coalesce(stddev_samp(v), 0) AS sd, count(v) AS sites FROM l GROUP BY 1)
SELECT metric, round(mean, 6) AS mean, round(mean - {metrics.Z95!r}::DOUBLE * sd / sqrt(sites), 6) AS ci_low, round(mean + {metrics.Z95!r}::DOUBLE * sd / sqrt(sites), 6) AS ci_high, sites FROM g"""


@query_of("pareto_sampler", "SELECT 0.0::DOUBLE AS inverse_gap, true AS near")
def _(spark, d):
    """The quantile inverts the distribution, and the sampled means follow it (greatest distance of the two curves)."""
    from pyspark.sql import Window

    x = churn.session_means(spark, 512, 3).select(F.col("life").alias("x"))
    cdf = churn.pareto2_cdf(F.col("x"), churn.MU, 1.0, churn.MEAN_SHAPE)
    gap = spark.range(1, 100).select((F.col("id") / 100).alias("u")).select(F.abs(churn.pareto2_cdf(churn.pareto2_quantile(F.col("u"), churn.MU, 1.0, 3.0), churn.MU, 1.0, 3.0) - F.col("u")).alias("g"))
    far = x.select(F.abs(F.cume_dist().over(Window.orderBy("x")) - cdf).alias("k")).agg((F.max("k") < 1.63 / 512**0.5).alias("near"))
    return gap.agg(F.round(F.max("g"), 9).alias("inverse_gap")).crossJoin(far)


def _u(*parts: str) -> str:
    return f"(({_key("concat_ws('|', " + ', '.join(parts) + ')')}) + 0.5) / 4294967296.0::DOUBLE"


#: The sites of the churn: customers that order.
_ORDERING = "(SELECT DISTINCT CAST(o_custkey AS INTEGER) AS i FROM orders)"


def _ordering(spark, d):
    from fadegossip.sources import read_table

    return read_table(spark, d, "orders").select(F.col("o_custkey").alias("site"))


@query_of("fail_stop_timeline", f"WITH g AS (SELECT CAST(a.i AS INTEGER) AS site, CAST(b.i AS INTEGER) AS round FROM {_ORDERING} a, range(24) b(i)), l AS (SELECT site, min(CASE WHEN {_u("'0'", "'fail'", 'site', 'round')} < 0.05 THEN round END) AS failed FROM g GROUP BY 1) SELECT * FROM (SELECT site, 0 AS seq, 'on' AS state, 0 AS from_round, coalesce(failed, 24) AS to_round FROM l UNION ALL SELECT site, 1, 'off', coalesce(failed, 24), 24 FROM l) WHERE from_round < to_round")
def _(spark, d):
    return churn.fail_stop(spark, _ordering(spark, d), 24, 0.05)


_MEANS = f"SELECT CAST(i AS INTEGER) AS site, 1.01 + 1.0 * (pow(1 - {_u("'0'", "'life'", 'i')}, -1 / 3.0::DOUBLE) - 1) AS life, 1.01 + 2.0 * (pow(1 - {_u("'0'", "'off'", 'i')}, -1 / 3.0::DOUBLE) - 1) AS off FROM range(64) t(i)"


@query_of("session_means", f"SELECT site, round(life, 6) AS life, round(off, 6) AS off FROM ({_MEANS})")
def _(spark, d):
    return churn.session_means(spark, 64).select("site", _r("life"), _r("off"))


def _sessions_sql(on: str, rounds: int = 24) -> str:
    off = f"1.01 + 3.0 * (pow(1 - {_u("'0'", "'session'", 'site', 'seq')}, -1 / (2 * off)) - 1)"
    return f"""WITH m AS ({_MEANS}), g AS (SELECT m.*, CAST(i AS INTEGER) AS seq FROM m, range(128) t(i)),
    l AS (SELECT site, seq, CAST(greatest(1, round(CASE WHEN seq % 2 = 0 THEN {on} ELSE {off} END)) AS INTEGER) AS len FROM g),
    e AS (SELECT site, seq, len, CAST(sum(len) OVER (PARTITION BY site ORDER BY seq) AS INTEGER) AS upto FROM l)
    SELECT site, seq, CASE WHEN seq % 2 = 0 THEN 'on' ELSE 'off' END AS state, upto - len AS from_round, least(upto, {rounds}) AS to_round FROM e WHERE upto - len < {rounds}"""


@query_of("session_timeline", _sessions_sql(f"1.01 + 2.0 * (pow(1 - {_u("'0'", "'session'", 'site', 'seq')}, -1 / (2 * life)) - 1)"))
def _(spark, d):
    return churn.session_timeline(spark, 64, 24)


@query_of("session_timeline_exponential", _sessions_sql(f"-ln(1 - {_u("'0'", "'session'", 'site', 'seq')}) * life"))
def _(spark, d):
    return churn.session_timeline(spark, 64, 24, life="exponential")


@query_of("masked_schedule", f"WITH e(round, a, b) AS (VALUES {', '.join(f'({r}, {a}, {b})' for r, a, b in zip(DEMO.round.tolist(), DEMO.a.tolist(), DEMO.b.tolist()))}), o AS (SELECT CAST(a.i AS INTEGER) AS site, CAST(b.i AS INTEGER) AS round FROM range(8) a(i), range(12) b(i)), l AS (SELECT site, coalesce(min(CASE WHEN {_u("'0'", "'fail'", 'site', 'round')} < 0.1 THEN round END), 12) AS failed FROM o GROUP BY 1) SELECT round, a, b FROM e WHERE round < (SELECT failed FROM l WHERE site = a) AND round < (SELECT failed FROM l WHERE site = b)")
def _(spark, d):
    return churn.mask_schedule(DEMO.table(spark), churn.fail_stop(spark, 8, 12, 0.1)).select("round", "a", "b")


@query_of("churn_report", f"WITH l AS (SELECT i AS site, CASE WHEN {_u("'0'", "'fail'", 'i')} < 0.05 THEN floor({_u("'0'", "'when'", 'i')} * 24) END AS failed FROM {_ORDERING} t) SELECT CAST(r.i AS INTEGER) AS round, count(*) FILTER (WHERE coalesce(failed, 24) > r.i) AS online, count(*) FILTER (WHERE coalesce(failed, 24) > r.i) / count(*)::DOUBLE AS share FROM l, range(24) r(i) GROUP BY 1")
def _(spark, d):
    return churn.churn_report(churn.fail_stop(spark, _ordering(spark, d), 24, 0.05, "once"), 24)


@query_of("graph_report", "WITH l AS (SELECT DISTINCT l_orderkey AS o, l_suppkey AS s FROM lineitem), e AS (SELECT DISTINCT a.s AS src, b.s AS dst FROM l a JOIN l b USING (o) WHERE a.s <> b.s), g AS (SELECT src, count(*) AS n FROM e GROUP BY 1) SELECT count(*) AS sites, CAST(sum(n) / 2 AS BIGINT) AS edges, min(n) AS min_degree, max(n) AS max_degree, 0::BIGINT AS one_way FROM g")
def _(spark, d):
    from fadegossip.sources import read_table

    return topology.graph_report(topology.co_supplier_graph(read_table(spark, d, "lineitem").select("l_orderkey", "l_suppkey")))


def _reached(spark, d):
    """The sites, of 64, that lineitem's arrivals are dealt to."""
    from fadegossip.sources import read_table

    return read_table(spark, d, "lineitem").select(F.pmod("l_orderkey", F.lit(64)).cast("int").alias("site"))


for _name, _make in {"uniform": lambda s: topology.uniform_graph(s, 64), "preferential": lambda s: topology.preferential_graph(s, 64), "complete": lambda s: topology.complete_graph(s, 64), "ring": lambda s: topology.ring(s, 64), "star": lambda s: topology.star(s, 64), "tree": lambda s: topology.tree(s, 64), "hashed": lambda s: topology.hashed_uniform_graph(s, 64, 0.2)}.items():
    QUERIES[f"graph_{_name}"] = lambda spark, d, make=_make: topology.graph_report(topology.among(make(spark), _reached(spark, d)))
ORACLES |= {f"graph_{k}": f"SELECT 64::BIGINT AS sites, {e}::BIGINT AS edges, {lo}::BIGINT AS min_degree, {hi}::BIGINT AS max_degree, 0::BIGINT AS one_way" for k, e, lo, hi in (("star", 63, 1, 63), ("tree", 63, 1, 3))}


def _graph_sql(pairs) -> str:
    values = ", ".join(f"({a}, {b})" for a, b in {tuple(sorted(x)) for x in pairs.tolist()})
    return f"WITH p(a, b) AS (VALUES {values}), e AS (SELECT a AS src, b AS dst FROM p UNION SELECT b, a FROM p), g AS (SELECT src, count(*) AS n FROM e GROUP BY 1) SELECT count(*) AS sites, CAST(sum(n) / 2 AS BIGINT) AS edges, min(n) AS min_degree, max(n) AS max_degree, 0::BIGINT AS one_way FROM g"


ORACLES["graph_uniform"] = _graph_sql(topology.connected(topology.uniform_pairs(64, 8 / 63, 0), 64))
# the same of the sites that lineitem reaches, of 64
_REPORT = "e AS (SELECT a AS src, b AS dst FROM p UNION SELECT b, a FROM p), g AS (SELECT src, count(*) AS n FROM e GROUP BY 1) SELECT count(*) AS sites, CAST(sum(n) / 2 AS BIGINT) AS edges, min(n) AS min_degree, max(n) AS max_degree, 0::BIGINT AS one_way FROM g"
_LINKS = {
    "complete": "a.i < b.i", "ring": "b.i = (a.i + 1) % 64", "hashed": f"a.i < b.i AND {_key("concat_ws('|', '0', a.i, b.i)")} < {round(0.2 * 2**32)}",
    "preferential": "(a.i, b.i) IN (" + ", ".join(f"({x}, {y})" for x, y in topology.preferential_pairs(64, 3, 0).tolist()) + ")",
}
ORACLES |= {f"graph_{k}": f"WITH s AS (SELECT DISTINCT l_orderkey % 64 AS i FROM lineitem), p AS (SELECT a.i AS a, b.i AS b FROM s a, s b WHERE {x}), {_REPORT}" for k, x in _LINKS.items()}


@query_of("preferential_degrees", "SELECT 64::BIGINT AS sites, 186::BIGINT AS edges, true AS heavy_tail")
def _(spark, d):
    """Three links for each new site, and hubs well over the mean degree."""
    degree = topology.preferential_graph(spark, 64).groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    return degree.agg(F.count(F.lit(1)).alias("sites"), (F.sum("n") / 2).cast("long").alias("edges"), (F.max("n") > 2 * F.avg("n")).alias("heavy_tail"))


@query_of("ring_reach", "SELECT CAST(i AS INTEGER) AS site FROM range(8) t(i)")
def _(spark, d):
    return topology.reach(topology.ring(spark, 8))


@query_of("schedule_by_dataframes", "SELECT CAST(r.i AS INTEGER) AS round, 16::BIGINT AS choices, 16::BIGINT AS choosers, 0::BIGINT AS strangers FROM range(4) r(i)")
def _(spark, d):
    """In each round every site of a ring chooses one neighbour."""
    from fadegossip.schedule import draw_exchanges_df

    drawn = draw_exchanges_df(topology.ring(spark, 16), 4, 1)
    apart = F.pmod(F.col("a") - F.col("b"), F.lit(16))
    return drawn.groupBy("round").agg(F.count(F.lit(1)).alias("choices"), F.countDistinct("a").alias("choosers"), F.count(F.when(~apart.isin(1, 15), 1)).alias("strangers"))


@query_of("schedule_matching", "SELECT CAST(r.i AS INTEGER) AS round, 0::BIGINT AS twice, 0::BIGINT AS strangers, true AS maximal FROM range(6) r(i)")
def _(spark, d):
    """Pairs of a round share no site, are neighbours, and leave no two free neighbours."""
    edges = topology.uniform_graph(spark, 64)
    table = draw_matching(topology.neighbours(edges), 64, 6, 1).table(spark).select("round", "a", "b")
    ends = table.select("round", F.explode(F.array("a", "b")).alias("src"))
    twice = ends.groupBy("round", "src").agg((F.count(F.lit(1)) - 1).alias("more")).groupBy("round").agg(F.sum("more").alias("twice"))
    strangers = table.join(edges, (F.col("a") == F.col("src")) & (F.col("b") == F.col("dst")), "left").groupBy("round").agg(F.count(F.when(F.col("src").isNull(), 1)).alias("strangers"))
    turns = spark.range(6).select(F.col("id").cast("int").alias("round"))
    free = turns.crossJoin(edges).join(ends, ["round", "src"], "left_anti").join(ends.withColumnRenamed("src", "dst"), ["round", "dst"], "left_anti").groupBy("round").agg(F.count(F.lit(1)).alias("free"))
    return twice.join(strangers, "round").join(free, "round", "left").select("round", "twice", "strangers", F.col("free").isNull().alias("maximal"))


@query_of("static_timeline", "SELECT CAST(i AS INTEGER) AS site, 0 AS seq, 'on' AS state, 0 AS from_round, 24 AS to_round FROM range(64) t(i)")
def _(spark, d):
    return churn.static_timeline(spark, 64, 24)


@query_of("alive_at_end", f"SELECT site FROM ({ORACLES['fail_stop_timeline']}) WHERE state = 'on' AND to_round = 24")
def _(spark, d):
    return churn.alive(churn.fail_stop(spark, _ordering(spark, d), 24, 0.05), 23)


@query_of("static_against_churn", _gossip_sql("types", 0.195, EVENTS_AT))
def _(spark, d):
    """A timeline in which nobody leaves gives what no timeline gives."""
    kept = churn.mask(DEMO, churn.static_timeline(spark, 8, 12))
    state = gossip.gossip_by_cell(build_local(stream(spark, d, "types"), LINEAR, FAMILY), kept, FAMILY)
    answer = query.peer_query(state, FAMILY, LINEAR, 0.195, SLACK, EVENTS_AT, gossip.share_table(spark, kept))
    return answer.select("site", "item_key", _r("est_avg"), _r("est_global"), _r("tau"), _r("c_est"), _r("p_est"))


@query_of("facade_query", _gossip_sql("types", 0.195, EVENTS_AT))
def _(spark, d):
    from fadegossip.api import FadingHitters

    answer = FadingHitters(LINEAR, FAMILY).fit(stream(spark, d, "types")).gossip(DEMO).query(0.195, EVENTS_AT)
    return answer.select("site", "item_key", _r("est_avg"), _r("est_global"), _r("tau"), _r("c_est"), _r("p_est"))


@query_of("deviation_bound", f"WITH {_SITES}, v AS (SELECT count(*) AS p, var_samp(c) AS v FROM c) SELECT CAST(r.i AS INTEGER) AS rounds, round(sqrt((p - 1) * v * pow({_K}::DOUBLE, r.i) / 0.01), 3) AS bound FROM v, range(30) r(i)")
def _(spark, d):
    """For the decayed counts of the sites of lineitem."""
    start = _sites(spark, d).agg(F.count(F.lit(1)).alias("p"), F.var_samp("c").alias("v")).select("p", "v", F.explode(F.sequence(F.lit(0), F.lit(29))).alias("rounds"))
    return start.select("rounds", F.round(planner.deviation_bound(F.col("p"), F.col("v"), F.col("rounds"), 0.01), 3).alias("bound"))


@query_of("counters_per_site", f"WITH {_stream('suppliers')} SELECT site, depth, width, CAST(2 * depth * width AS BIGINT) AS counters FROM (SELECT DISTINCT site FROM s) a, (VALUES (4, 2500), (4, 250), (6, 100)) AS t(depth, width)")
def _(spark, d):
    sizes = F.array(*[F.struct(F.lit(k).alias("depth"), F.lit(w).alias("width"), F.lit(metrics.counters_per_site(k, w)).cast("long").alias("counters")) for k, w in ((4, 2500), (4, 250), (6, 100))])
    return stream(spark, d, "suppliers").select("site").distinct().select("site", F.explode(sizes).alias("x")).select("site", "x.*")


# -- experiments whose rows SQL can repeat ---------------------------------------------------------------------
_EMPTY = HashFamily(4, 450)
ORACLES["w0_width_curve"] = ORACLES["width_curve"]
ORACLES["w13_empty"] = f"WITH {_sql_grid('parts', 'linear', _EMPTY, 'preagg', '0')}, {_sql_answer(_EMPTY, float(DAYS_AT), 0.01)} SELECT site, item_key, est_avg, est_avg AS est_global, tau, c_est, 1.0::DOUBLE AS p_est FROM answer"
ORACLES["w15_skewed_start"] = trace_sql(draw_exchanges(None, 64, 24, 1, 0))


assert math.isclose(planner.KAPPA, 0.3032653298563167)
