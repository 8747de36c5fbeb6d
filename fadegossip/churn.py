"""Sites that leave, and sites that come and go.

A timeline is a table (site, seq, state, from_round, to_round) of half-open intervals of rounds. All draws are hashes of
(seed, site, number), so any engine and any partitioning repeats them.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fadegossip.plans import checked
from fadegossip.schedule import Schedule
from fadegossip.sources import fingerprint

# fixed values: laws of the mean durations and of the durations (location, scale; shape of the means)
MU, MEAN_SHAPE, MEAN_SCALE = 1.01, 3.0, {"life": 1.0, "off": 2.0}
LIFE_SCALE, OFF_SCALE = 2.0, 3.0
SESSIONS = 64


def uniform(seed: int, *parts: Column) -> Column:
    """A number in (0, 1) from a hash."""
    return (fingerprint(F.concat_ws("|", F.lit(str(seed)), *[p.cast("string") for p in parts])) + 0.5) / F.lit(float(2**32))


def pareto2_cdf(x: Column, mu: float, beta: float, alpha: float) -> Column:
    return F.when(x < mu, 0.0).otherwise(1 - F.pow(1 + (x - mu) / beta, F.lit(-alpha)))


def pareto2_quantile(u: Column, mu: float, beta: float | Column, alpha: float | Column) -> Column:
    lit = lambda v: v if isinstance(v, Column) else F.lit(float(v))
    return F.lit(mu) + lit(beta) * (F.pow(1 - u, -1 / lit(alpha)) - 1)


def _sites(spark: SparkSession, sites: int | DataFrame) -> DataFrame:
    """(site) of a number of sites, or the distinct ones of a table."""
    return spark.range(sites).select(F.col("id").cast("int").alias("site")) if isinstance(sites, int) else sites.select(F.col("site").cast("int").alias("site")).where("site IS NOT NULL").distinct()


def static_timeline(spark: SparkSession, sites: int, rounds: int) -> DataFrame:
    return spark.range(sites).select(F.col("id").cast("int").alias("site"), F.lit(0).alias("seq"), F.lit("on").alias("state"), F.lit(0).alias("from_round"), F.lit(rounds).alias("to_round"))


def fail_stop(spark: SparkSession, sites: int | DataFrame, rounds: int, prob: float, scope: str = "per_round", seed: int = 0) -> DataFrame:
    """Sites that fail never come back. per_round: every round may be a site's last; once: one draw per site and a uniform round."""
    site = _sites(spark, sites)
    if scope == "per_round":
        turns = site.crossJoin(F.broadcast(spark.range(rounds).select(F.col("id").cast("int").alias("round"))))
        failed = F.min(F.when(uniform(seed, F.lit("fail"), F.col("site"), F.col("round")) < prob, F.col("round")))
        last = turns.groupBy("site").agg(failed.alias("failed"))
    elif scope == "once":
        when = F.floor(uniform(seed, F.lit("when"), F.col("site")) * rounds).cast("int")
        last = site.select("site", F.when(uniform(seed, F.lit("fail"), F.col("site")) < prob, when).alias("failed"))
    else:
        raise ValueError(f"unknown scope {scope}")
    end = F.coalesce("failed", F.lit(rounds))
    both = F.array(
        F.struct(F.lit(0).alias("seq"), F.lit("on").alias("state"), F.lit(0).alias("from_round"), end.alias("to_round")),
        F.struct(F.lit(1).alias("seq"), F.lit("off").alias("state"), end.alias("from_round"), F.lit(rounds).alias("to_round")),
    )
    return last.select("site", F.explode(both).alias("x")).select("site", "x.*").where("from_round < to_round")


def session_means(spark: SparkSession, sites: int, seed: int = 0) -> DataFrame:
    """(site, life, off): mean durations of every site."""
    draw = lambda what: pareto2_quantile(uniform(seed, F.lit(what), F.col("site")), MU, MEAN_SCALE[what], MEAN_SHAPE).alias(what)
    return spark.range(sites).select(F.col("id").cast("int").alias("site")).select("site", draw("life"), draw("off"))


def session_timeline(spark: SparkSession, sites: int, rounds: int, life: str = "pareto", law: str = "printed", seed: int = 0, sessions: int = SESSIONS) -> DataFrame:
    """Everyone starts online; online and offline durations alternate, at least one round long.

    life: pareto or exponential. law: printed puts twice the mean into the shape, swapped puts it into the scale
    (with shape 3, which gives that mean when the location is 0).
    """
    means = session_means(spark, sites, seed)
    rows = means.crossJoin(F.broadcast(spark.range(2 * sessions).select(F.col("id").cast("int").alias("seq"))))
    u = uniform(seed, F.lit("session"), F.col("site"), F.col("seq"))
    pareto = lambda mean, scale: pareto2_quantile(u, MU, scale, 2 * mean) if law == "printed" else pareto2_quantile(u, MU, 2 * mean, 3.0)
    on = pareto(F.col("life"), LIFE_SCALE) if life == "pareto" else -F.log(1 - u) * F.col("life")
    length = F.greatest(F.lit(1), F.round(F.when(F.col("seq") % 2 == 0, on).otherwise(pareto(F.col("off"), OFF_SCALE))).cast("int"))
    ends = F.sum("length").over(Window.partitionBy("site").orderBy("seq")).cast("int")
    spans = rows.withColumn("length", length).withColumn("to_round", ends).withColumn("from_round", F.col("to_round") - F.col("length"))
    state = F.when(F.col("seq") % 2 == 0, "on").otherwise("off").alias("state")
    return spans.where(F.col("from_round") < rounds).select("site", "seq", state, "from_round", F.least("to_round", F.lit(rounds)).alias("to_round"))


def online(timeline: DataFrame, sites: int, rounds: int) -> np.ndarray:
    """alive[round, site] on the driver, for a network whose schedule is there too."""
    out = np.zeros((rounds, sites), bool)
    for x in timeline.where("state = 'on'").collect():
        out[x.from_round : x.to_round, x.site] = True
    return out


def mask_schedule(schedule: DataFrame, timeline: DataFrame) -> DataFrame:
    """Exchanges whose both ends are online, by two range joins with the timeline."""
    up = checked(timeline.where("state = 'on'").select("site", "from_round", "to_round"))
    during = (F.col("round") >= F.col("from_round")) & (F.col("round") < F.col("to_round"))
    out = schedule
    for end in ("a", "b"):
        out = out.join(up, (F.col(end) == F.col("site")) & during, "left_semi")
    return out


def mask(schedule: Schedule, timeline: DataFrame) -> Schedule:
    return schedule.keep(online(timeline, schedule.sites, schedule.rounds))


def alive(timeline: DataFrame, at_round: int) -> DataFrame:
    """(site): sites online in a round (the last one for a query at the end)."""
    return timeline.where((F.col("state") == "on") & (F.col("from_round") <= at_round) & (F.col("to_round") > at_round)).select("site").distinct()


def churn_report(timeline: DataFrame, rounds: int) -> DataFrame:
    """(round, online, share) of sites."""
    spark = timeline.sparkSession
    turns = spark.range(rounds).select(F.col("id").cast("int").alias("round"))
    n = timeline.select("site").distinct().agg(F.count(F.lit(1)).alias("all"))
    up = timeline.where("state = 'on'").join(F.broadcast(turns), (F.col("round") >= F.col("from_round")) & (F.col("round") < F.col("to_round"))).groupBy("round").agg(F.countDistinct("site").alias("online"))
    return turns.join(up, "round", "left").crossJoin(n).select("round", F.coalesce("online", F.lit(0)).alias("online"), (F.coalesce("online", F.lit(0)) / F.col("all")).alias("share"))
