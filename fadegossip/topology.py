"""Networks of sites: edge lists with both directions, and checks of them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.plans import checked
from fadegossip.sources.streams import fingerprint

#: Sites up to which a graph is made on the driver (a few edges per site).
DRIVER_SITES = 100_000


def _edges(spark: SparkSession, pairs: np.ndarray) -> DataFrame:
    both = np.unique(np.vstack([pairs, pairs[:, ::-1]]), axis=0) if len(pairs) else np.zeros((0, 2), int)
    return spark.createDataFrame([tuple(x) for x in both.tolist()], "src int, dst int")


def uniform_pairs(sites: int, q: float, seed: int) -> np.ndarray:
    """Every pair is linked with probability q; pairs are reached by geometric leaps, so the work is the number of edges."""
    rng, total, out, at = np.random.default_rng([seed, 1]), sites * (sites - 1) // 2, [], -1
    if q >= 1:
        return np.stack(np.triu_indices(sites, 1), 1)
    while q > 0:
        leaps = rng.geometric(q, max(16, int(1.1 * q * total) + 16))
        at_all = at + np.cumsum(leaps)
        out.append(at_all[at_all < total])
        at = int(at_all[-1])
        if at >= total:
            break
    n = np.concatenate(out).astype(np.int64) if out else np.zeros(0, np.int64)
    high = ((1 + np.sqrt(1 + 8 * n.astype(float))) / 2).astype(np.int64)
    high -= (high * (high - 1) // 2 > n).astype(np.int64)
    high += ((high + 1) * high // 2 <= n).astype(np.int64)
    return np.stack([n - high * (high - 1) // 2, high], 1)


def connected(pairs: np.ndarray, sites: int) -> np.ndarray:
    """The pairs, and a link from each component to the first one: averages are of a component's sites only."""
    root = list(range(sites))

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for a, b in pairs.tolist():
        root[find(a)] = find(b)
    heads = sorted({find(i) for i in range(sites)})
    extra = [(heads[0], h) for h in heads[1:]]
    return np.vstack([pairs, np.array(extra, np.int64).reshape(-1, 2)])


def uniform_graph(spark: SparkSession, sites: int, q: float | None = None, mean_degree: float = 8, seed: int = 0) -> DataFrame:
    """Uniform random graph; components that are apart are linked, so that all sites can reach each other."""
    q = q if q is not None else min(1.0, mean_degree / max(sites - 1, 1))
    return _edges(spark, connected(uniform_pairs(sites, q, seed), sites).astype(int))


def hashed_uniform_graph(spark: SparkSession, sites: int, q: float, seed: int = 0) -> DataFrame:
    """The same family without a driver: a theta join of site ids and a hash below a threshold (quadratic in sites)."""
    a, b = spark.range(sites).toDF("src"), spark.range(sites).toDF("dst")
    pair = a.join(b, F.col("src") < F.col("dst")).where(fingerprint(F.concat_ws("|", F.lit(str(seed)), F.col("src").cast("string"), F.col("dst").cast("string"))) < round(q * 2**32))
    pair = pair.select(F.col("src").cast("int"), F.col("dst").cast("int"))
    return pair.union(pair.select("dst", "src"))


def preferential_pairs(sites: int, links: int, seed: int) -> np.ndarray:
    """Each new site links to `links` different older ones, chosen in proportion to their degree."""
    rng, ends, pairs = np.random.default_rng([seed, 2]), [], []
    for new in range(1, sites):
        m = min(links, new)
        if new <= links:
            chosen = set(range(new))
        else:
            chosen: set[int] = set()
            while len(chosen) < m:
                chosen.add(ends[rng.integers(len(ends))])
        for old in sorted(chosen):
            pairs.append((old, new))
            ends += [old, new]
    return np.array(pairs, int).reshape(-1, 2)


def preferential_graph(spark: SparkSession, sites: int, links: int = 3, seed: int = 0) -> DataFrame:
    return _edges(spark, preferential_pairs(sites, links, seed))


def complete_graph(spark: SparkSession, sites: int) -> DataFrame:
    return _edges(spark, np.stack(np.triu_indices(sites, 1), 1))


def ring(spark: SparkSession, sites: int) -> DataFrame:
    return _edges(spark, np.array([(i, (i + 1) % sites) for i in range(sites) if sites > 1], int).reshape(-1, 2))


def star(spark: SparkSession, sites: int) -> DataFrame:
    return _edges(spark, np.array([(0, i) for i in range(1, sites)], int).reshape(-1, 2))


def tree(spark: SparkSession, sites: int, arity: int = 2) -> DataFrame:
    return _edges(spark, np.array([((i - 1) // arity, i) for i in range(1, sites)], int).reshape(-1, 2))


def co_supplier_graph(lineitem: DataFrame) -> DataFrame:
    """Suppliers that serve the same order."""
    a = lineitem.select("l_orderkey", F.col("l_suppkey").cast("int").alias("src")).distinct()
    b = a.withColumnRenamed("src", "dst")
    return a.join(b, "l_orderkey").where("src <> dst").select("src", "dst").distinct()


def among(edges: DataFrame, sites: DataFrame) -> DataFrame:
    """The links between the sites (site) that a stream reaches."""
    there = checked(sites.select("site").distinct())
    for end in ("src", "dst"):
        edges = edges.join(there, F.col(end) == F.col("site"), "left_semi")
    return edges


def graph_report(edges: DataFrame) -> DataFrame:
    """One row: sites, edges, least and greatest degree, edges without their reverse."""
    degree = edges.groupBy("src").agg(F.count(F.lit(1)).alias("n"))
    lonely = edges.select(F.col("src").alias("dst"), F.col("dst").alias("src")).join(edges, ["src", "dst"], "left_anti").agg(F.count(F.lit(1)).alias("one_way"))
    return degree.agg(F.count(F.lit(1)).alias("sites"), (F.sum("n") / 2).cast("long").alias("edges"), F.min("n").alias("min_degree"), F.max("n").alias("max_degree")).crossJoin(lonely)


def reach(edges: DataFrame, start: int = 0, limit: int = 100) -> DataFrame:
    """(site): sites reachable from one, by rounds of a join; rounds stop when nothing is new."""
    from fadegossip.plans import cut

    seen = cut(edges.sparkSession.createDataFrame([(start,)], "site int"))
    front = seen
    for _ in range(limit):
        front = cut(edges.join(front, F.col("src") == F.col("site")).select(F.col("dst").alias("site")).distinct().join(seen, "site", "left_anti"))
        if front.isEmpty():
            return seen
        seen = cut(seen.union(front))
    return seen


def neighbours(edges: DataFrame) -> dict[int, np.ndarray]:
    """Adjacency on the driver: a network of at most DRIVER_SITES sites."""
    rows = np.array([(x.src, x.dst) for x in edges.collect()], np.int64).reshape(-1, 2)
    if len(rows) and rows.max() >= DRIVER_SITES:
        raise ValueError("the network is too large for schedules made on the driver")
    rows = rows[np.lexsort((rows[:, 1], rows[:, 0]))]
    site, first = np.unique(rows[:, 0], return_index=True)
    return dict(zip(site.tolist(), np.split(rows[:, 1], first[1:]))) if len(rows) else {}
