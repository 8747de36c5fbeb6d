"""Accuracy and cost of answers and of gossip."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fadegossip import planner
from fadegossip.plans import checked
from fadegossip.schedule import Schedule

Z95 = 1.959963984540054


def recall_precision(answer: DataFrame, truth: DataFrame, sites: DataFrame) -> DataFrame:
    """(site, recall, precision) of every site; an empty truth is recalled, an empty answer is precise."""
    true = checked(truth.select("item_key", F.lit(1).alias("t")))
    hits = answer.select("site", "item_key").join(true, "item_key", "left").groupBy("site").agg(F.count(F.lit(1)).alias("named"), F.count("t").alias("right"))
    n = true.agg(F.count(F.lit(1)).alias("true"))
    rows = sites.select("site").join(hits, "site", "left").crossJoin(F.broadcast(n)).na.fill(0, ["named", "right"])
    ratio = lambda a, b: F.when(F.col(b) == 0, 1.0).otherwise(F.col(a) / F.col(b))
    return rows.select("site", ratio("right", "true").alias("recall"), ratio("right", "named").alias("precision"))


def relative_errors(answer: DataFrame, freqs: DataFrame) -> DataFrame:
    """(site, item_key, err) of reported items; freqs (item_key, f) are the exact ones."""
    return answer.join(freqs.select("item_key", "f"), "item_key").select("site", "item_key", (F.abs(F.col("est_global") - F.col("f")) / F.col("f")).alias("err"))


def are(answer: DataFrame, freqs: DataFrame) -> DataFrame:
    """(site, are): mean relative error over what a site reports."""
    return relative_errors(answer, freqs).groupBy("site").agg(F.avg("err").alias("are"))


def site_stats(answer: DataFrame, truth: DataFrame, freqs: DataFrame, sites: DataFrame, run: int = 0) -> DataFrame:
    """(run, site, recall, precision, are)."""
    return recall_precision(answer, truth, sites).join(are(answer, freqs), "site", "left").select(F.lit(run).alias("run"), "site", "recall", "precision", "are")


def aggregate_runs(stats: DataFrame) -> DataFrame:
    """(metric, mean, ci_low, ci_high, sites): per site the mean over runs, then mean and 95 % interval over sites."""
    per_site = stats.groupBy("site").agg(*[F.avg(m).alias(m) for m in ("recall", "precision", "are")])
    long = per_site.select(F.explode(F.array(*[F.struct(F.lit(m).alias("metric"), F.col(m).alias("v")) for m in ("recall", "precision", "are")])).alias("x")).select("x.*")
    out = long.groupBy("metric").agg(F.avg("v").alias("mean"), F.coalesce(F.stddev_samp("v"), F.lit(0.0)).alias("sd"), F.count("v").alias("sites"))
    half = F.lit(Z95) * F.col("sd") / F.sqrt(F.col("sites"))
    return out.select("metric", "mean", (F.col("mean") - half).alias("ci_low"), (F.col("mean") + half).alias("ci_high"), "sites")


def misses(answer: DataFrame, truth: DataFrame, sites: DataFrame) -> DataFrame:
    """(site, item_key) of true hitters that a site doesn't name."""
    return sites.select("site").crossJoin(checked(truth.select("item_key"))).join(answer.select("site", "item_key"), ["site", "item_key"], "left_anti")


def tolerance_violations(answer: DataFrame, forbidden: DataFrame) -> DataFrame:
    """(site, item_key) of named items that no answer may name."""
    return answer.select("site", "item_key").join(forbidden.select("item_key"), "item_key", "left_semi")


def frequency_violations(answer: DataFrame, freqs: DataFrame, slack: float, count: float, width: int) -> DataFrame:
    """(site, item_key, f, est_global) of reports outside their two-sided bound."""
    low, high = planner.freq_interval(F.col("f"), slack, F.lit(count), width)
    return answer.join(freqs.select("item_key", "f"), "item_key").where((F.col("est_global") < low * (1 - 1e-12)) | (F.col("est_global") > high * (1 + 1e-12))).select("site", "item_key", "f", "est_global")


def variance_trace(spark: SparkSession, values: np.ndarray, var0: float | None = None, fail_gossip: float = 0.01) -> DataFrame:
    """values (rounds + 1, sites) -> (round, var, factor, deviation, bound): spread of an averaged number after each round."""
    rows = [(r, i, float(x)) for r, line in enumerate(values) for i, x in enumerate(line)]
    df = spark.createDataFrame(rows, "round int, site int, v double")
    mean = float(values[0].mean())
    out = df.groupBy("round").agg(F.var_samp("v").alias("var"), F.max(F.abs(F.col("v") - mean)).alias("deviation"))
    p = values.shape[1]
    start = float(np.var(values[0], ddof=1)) if var0 is None else var0
    bound = F.sqrt(F.lit((p - 1) * start / fail_gossip) * F.pow(F.lit(planner.KAPPA), F.col("round").cast("double")))
    return out.withColumn("factor", F.try_divide("var", F.lag("var").over(Window.orderBy("round")))).withColumn("bound", bound)


def mass_trace(states: DataFrame) -> DataFrame:
    """(round, row, col, mass) summed over all sites, offline ones included; constant over rounds."""
    return states.groupBy("round", "row", "col").agg(F.sum(F.col("f1") + F.col("f2")).alias("mass"))


def norm_gaps(grid: DataFrame, sketch: DataFrame) -> DataFrame:
    """(row, col, gap) of cells whose counters don't add up to the plain sketch's counter."""
    own = grid.groupBy("row", "col").agg(F.sum(F.col("f1") + F.col("f2")).alias("own"))
    return own.join(sketch, ["row", "col"], "full_outer").select("row", "col", F.abs(F.coalesce("own", F.lit(0.0)) - F.coalesce("mass", F.lit(0.0))).alias("gap")).where("gap > 1e-6")


def site_count_errors(share: DataFrame, sites: int) -> DataFrame:
    return share.where("share > 0").select("site", (F.abs(1 / F.col("share") - sites) / sites).alias("err"))


def count_errors(counts: DataFrame, share: DataFrame, exact: float) -> DataFrame:
    """(site, err) of the estimated global decayed count."""
    return counts.join(share.where("share > 0"), "site").select("site", (F.abs(F.col("c_est") / F.col("share") - exact) / exact).alias("err"))


def message_cost(spark: SparkSession, schedule: Schedule, depth: int, width: int) -> DataFrame:
    """(round, exchanges, messages, bytes): two messages of a whole grid for each exchange."""
    n = np.bincount(schedule.round, minlength=schedule.rounds)
    return spark.createDataFrame([(r, int(x), 2 * int(x), 2 * int(x) * depth * width * 2 * 16) for r, x in enumerate(n)], "round int, exchanges long, messages long, bytes long")


def counters_per_site(depth: int, width: int) -> int:
    return 2 * depth * width
