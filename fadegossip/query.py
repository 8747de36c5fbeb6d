"""Asking a site for the heavy hitters, or for the frequency of an item.

Counters hold numerators, so every answer divides by the decay at the query time; one state answers any time. A
site knows its averaged counters only; the inverse of its share turns averages into global frequencies.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fadegossip.decay import DecaySpec
from fadegossip.hashing import HashFamily, with_cells
from fadegossip.plans import checked


def relaxed(support: float, slack: float) -> float:
    """Factor of the decayed count over which an item is reported."""
    return support * (1 - slack) / (1 + slack)


def threshold(support: float, count: Column, slack: float) -> Column:
    return F.lit(relaxed(support, slack)) * count


def count_estimate(state: DataFrame, spec: DecaySpec, asof: int, row: int = 0) -> DataFrame:
    """(site, c_est): every row of a grid sums to the averaged decayed count, so one row is read."""
    return state.where(F.col("row") == row).groupBy("site").agg((F.sum(F.col("f1") + F.col("f2")) / F.lit(spec.norm(asof))).alias("c_est"))


def peer_candidates(state: DataFrame, spec: DecaySpec, support: float, slack: float, asof: int) -> DataFrame:
    """(site, item_key, tau, c_est): majority candidates over the relaxed threshold, before they are confirmed."""
    counts = count_estimate(state, spec, asof).withColumn("tau", threshold(support, F.col("c_est"), slack))
    over = state.join(checked(counts), "site").where(F.col("i1").isNotNull() & (F.col("f1") / F.lit(spec.norm(asof)) > F.col("tau")))
    return over.select("site", F.col("i1").alias("item_key"), "tau", "c_est").distinct()


def point_estimate(state: DataFrame, items: DataFrame, family: HashFamily, spec: DecaySpec, asof: int) -> DataFrame:
    """items (site, item_key) -> with est_avg: the least, over the rows, of the item's counter or of its cell's minimum."""
    cells = with_cells(items.select("site", "item_key").distinct(), family)
    found = cells.join(state.select("site", "row", "col", "i1", "f1", "i2", "f2"), ["site", "row", "col"], "left")
    least = F.when(F.col("i1").isNull() | F.col("i2").isNull(), F.lit(0.0)).otherwise(F.least("f1", "f2"))
    value = F.when(F.col("i1") == F.col("item_key"), F.col("f1")).when(F.col("i2") == F.col("item_key"), F.col("f2")).otherwise(least)
    return found.groupBy("site", "item_key").agg((F.min(value) / F.lit(spec.norm(asof))).alias("est_avg"))


def peer_query(state: DataFrame, family: HashFamily, spec: DecaySpec, support: float, slack: float, asof: int, share: DataFrame | None = None, sites: list[int] | None = None, strict: bool = True) -> DataFrame:
    """(site, item_key, est_avg, est_global, tau, c_est, p_est): the answer of every site, or of the named ones.

    Without shares a grid stands for itself (one site, or no gossip). slack of 1 or more has no guarantee: it raises,
    or gives an empty answer where strict is off.
    """
    if not 0 < support < 1:
        raise ValueError("support is a fraction of the decayed count")
    if slack >= 1:
        if strict:
            raise ValueError("slack is 1 or more: more rounds, or a smaller bound on the number of sites")
        state = state.limit(0)
        slack = 0.0
    if sites is not None:
        state = state.where(F.col("site").isin(sites))
    found = peer_candidates(state, spec, support, slack, asof)
    confirmed = point_estimate(state, found, family, spec, asof).join(found, ["site", "item_key"]).where(F.col("est_avg") > F.col("tau"))
    if share is None:
        return confirmed.select("site", "item_key", "est_avg", F.col("est_avg").alias("est_global"), "tau", "c_est", F.lit(1.0).alias("p_est"))
    known = share.select("site", F.when(F.col("share") > 0, 1 / F.col("share")).alias("p_est"))
    return confirmed.join(known, "site", "left").select("site", "item_key", "est_avg", (F.col("est_avg") * F.col("p_est")).alias("est_global"), "tau", "c_est", "p_est")


def local_query(grid: DataFrame, family: HashFamily, spec: DecaySpec, support: float, asof: int) -> DataFrame:
    """Heavy hitters of every site's own part, before any gossip."""
    return peer_query(grid, family, spec, support, 0.0, asof)


def at_times(state: DataFrame, family: HashFamily, spec: DecaySpec, support: float, slack: float, asofs: list[int], share: DataFrame | None = None) -> DataFrame:
    """The answers at several query times from one state."""
    out = None
    for t in asofs:
        one = peer_query(state, family, spec, support, slack, t, share).withColumn("asof", F.lit(t))
        out = one if out is None else out.unionByName(one)
    return out


def named(answer: DataFrame, df: DataFrame) -> DataFrame:
    """The answer with its items spelled out: only reported keys are looked up in the stream."""
    keys = answer.select("item_key").distinct()
    names = df.select("item_key", "item").join(checked(keys), "item_key").groupBy("item_key").agg(F.min("item").alias("item"))
    return answer.join(checked(names), "item_key", "left")


def top_k(answer: DataFrame, k: int) -> DataFrame:
    place = F.row_number().over(Window.partitionBy("site").orderBy(F.desc("est_avg"), "item_key"))
    return answer.withColumn("place", place).where(F.col("place") <= k)


def consensus(answers: DataFrame, sites: int) -> DataFrame:
    """(item_key, sites_naming, share): how many sites name each item."""
    return answers.groupBy("item_key").agg(F.countDistinct("site").alias("sites_naming")).withColumn("share", F.col("sites_naming") / F.lit(sites))
