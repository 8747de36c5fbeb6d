"""Guarantees as functions of the sizes, and sizes for wanted guarantees."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Expected factor of the variance in a round of uniform gossip on a complete graph.
KAPPA = 1 / (2 * math.sqrt(math.e))


def slack(site_cap: float, rounds: int, fail_gossip: float, kappa: float = KAPPA) -> float:
    return site_cap * math.sqrt(kappa**rounds / fail_gossip)


def tolerance(s: float, support: float, width: float) -> float:
    """Items at or below (support - tolerance) of the count are not reported (with the planned probability)."""
    return 4 * s * support / (1 + s) ** 2 + math.e / (2 * width) * (1 - s) / (1 + s)


def fail_total(depth: int, fail_gossip: float) -> float:
    return fail_gossip + math.exp(-depth) * (1 - fail_gossip)


def candidate_prob(support: float, width: float, depth: int) -> float:
    """A frequent item leads at least one of its cells with at least this probability."""
    return 1 - (1 / (2 * support * width)) ** depth


def fail_miss(s: float, support: float, width: float, depth: int, fail_gossip: float) -> float:
    return fail_gossip + ((1 + s) / (2 * support * width * (1 - s))) ** depth * (1 - fail_gossip)


def feasible(s: float, support: float, width: float) -> bool:
    """Whether the tolerance is below the support; misses are then rarer than false reports."""
    return s < 1 and width > math.e * (1 + s) / (2 * support * (1 - s))


def width_for(tol: float, support: float, s: float) -> float:
    """Width that gives a tolerance at a slack; infinite where none does."""
    room = 2 * tol * (1 + s) ** 2 - 8 * support * s
    return math.e * (1 - s * s) / room if room > 0 and s < 1 else math.inf


def rounds_min(tol: float, support: float, site_cap: float, fail_gossip: float, kappa: float = KAPPA) -> int:
    most = (2 * support - tol - 2 * math.sqrt(support * support - tol * support)) / tol  # the slack at which no width is enough
    return math.floor((math.log(fail_gossip) + 2 * math.log(most / site_cap)) / math.log(kappa)) + 1


def width_min(tol: float) -> int:
    return math.floor(math.e / (2 * tol)) + 1


def slack_for(tol: float, support: float, width: float) -> float:
    """The greatest slack that keeps a tolerance with a width."""
    return (2 * width * (2 * support - tol) - math.sqrt(16 * support * width**2 * (support - tol) + math.e**2)) / (math.e + 2 * tol * width)


def rounds_for(s: float, site_cap: float, fail_gossip: float, kappa: float = KAPPA) -> int:
    return math.floor((2 * math.log(s) - 2 * math.log(site_cap) + math.log(fail_gossip)) / math.log(kappa)) + 1


def depth_for(fail: float, fail_gossip: float) -> int:
    return max(1, math.ceil(math.log((1 - fail_gossip) / (fail - fail_gossip))))


@dataclass(frozen=True)
class Plan:
    depth: int
    width: int
    rounds: int
    slack: float
    tol: float
    fail: float
    fail_miss: float


def plan(strategy: str, support: float, tol: float, site_cap: float, fail: float, fail_gossip: float, kappa: float = KAPPA) -> Plan:
    """strategy time: as few rounds as possible, then the width; space: as small a width as possible, then the rounds."""
    if not 0 < tol < support or not 0 < fail_gossip < fail < 1:
        raise ValueError("0 < tol < support and 0 < fail_gossip < fail < 1")
    if strategy == "time":
        rounds = rounds_min(tol, support, site_cap, fail_gossip, kappa)
        width = math.ceil(width_for(tol, support, slack(site_cap, rounds, fail_gossip, kappa)))
    elif strategy == "space":
        width = width_min(tol)
        rounds = rounds_for(slack_for(tol, support, width), site_cap, fail_gossip, kappa)
    else:
        raise ValueError(f"unknown strategy {strategy}")
    s, depth = slack(site_cap, rounds, fail_gossip, kappa), depth_for(fail, fail_gossip)
    return Plan(depth, width, rounds, s, tolerance(s, support, width), fail_total(depth, fail_gossip), fail_miss(s, support, width, depth, fail_gossip))


# -- bounds ----------------------------------------------------------------------------------------------------


def ss_bound(mass: float, counters: int) -> float:
    """Overestimate of a counter summary at most."""
    return mass / counters


def local_bound(count: float, width: float) -> float:
    return math.e * count / (2 * width)


def plain_bound(count: float, width: float) -> float:
    return math.e * count / width


def share_interval(p: int, s: float) -> tuple[float, float]:
    return (1 - s) / p, (1 + s) / p


def sites_interval(p: int, s: float) -> tuple[float, float]:
    return p / (1 + s), p / (1 - s)


def avg_freq_interval(f: float, p: int, s: float) -> tuple[float, float]:
    return f / p * (1 - s), f / p * (1 + s)


def count_interval(c: float, p: int, s: float) -> tuple[float, float]:
    return avg_freq_interval(c, p, s)


def freq_interval(f, s: float, count, width: float):
    """Bounds of a reported global frequency; numbers or columns."""
    return (1 - s) / (1 + s) * f, (1 + s) / (1 - s) * (f + math.e / (2 * width) * count)


def deviation_bound(p: int, var0: float, rounds: int, fail_gossip: float, kappa: float = KAPPA) -> float:
    """Numbers or columns."""
    return ((p - 1) * var0 * kappa**rounds / fail_gossip) ** 0.5


# -- columns ---------------------------------------------------------------------------------------------------


def slack_col(site_cap: Column, rounds: Column, fail_gossip: Column, kappa: float = KAPPA) -> Column:
    return site_cap * F.sqrt(F.pow(F.lit(kappa), rounds.cast("double")) / fail_gossip)


def tolerance_col(s: Column, support: Column, width: Column) -> Column:
    return 4 * s * support / F.pow(1 + s, F.lit(2.0)) + F.lit(math.e) / (2 * width) * (1 - s) / (1 + s)


def width_col(tol: Column, support: Column, s: Column) -> Column:
    room = 2 * tol * F.pow(1 + s, F.lit(2.0)) - 8 * support * s
    return F.when((room > 0) & (s < 1), F.lit(math.e) * (1 - s * s) / room)


def width_curve(spark: SparkSession, tols: list[float], rounds: range, support: float = 0.02, site_cap: float = 5000, fail_gossip: float = 0.01) -> DataFrame:
    """(tol, rounds, slack, width): the width a tolerance needs after each number of rounds; null where none is enough."""
    grid = spark.createDataFrame([(t,) for t in tols], "tol double").crossJoin(spark.range(rounds.start, rounds.stop).toDF("rounds"))
    s = slack_col(F.lit(float(site_cap)), F.col("rounds"), F.lit(fail_gossip))
    return grid.withColumn("slack", s).withColumn("width", width_col(F.col("tol"), F.lit(support), F.col("slack")))
