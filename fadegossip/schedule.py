"""Who exchanges with whom, in which order.

A schedule is a table (round, level, seq, a, b): exchanges of a round in order, split into levels of disjoint pairs.
Levels keep every site's own order, so replaying level after level gives what the sequential order gives.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Schedule:
    """Arrays of equal length, in order of execution."""

    sites: int
    rounds: int
    round: np.ndarray
    level: np.ndarray
    a: np.ndarray
    b: np.ndarray

    def table(self, spark: SparkSession) -> DataFrame:
        rows = zip(self.round.tolist(), self.level.tolist(), range(len(self.a)), self.a.tolist(), self.b.tolist())
        return spark.createDataFrame(list(rows), "round int, level int, seq int, a int, b int")

    def levels(self):
        """(round, a, b) of each level in order."""
        if not len(self.a):
            return
        cut = np.flatnonzero((self.round[1:] != self.round[:-1]) | (self.level[1:] != self.level[:-1])) + 1
        for part in np.split(np.arange(len(self.a)), cut):
            yield int(self.round[part[0]]), self.a[part], self.b[part]

    def keep(self, alive: np.ndarray) -> Schedule:
        """Exchanges whose both ends are online; alive[round, site]."""
        ok = alive[self.round, self.a] & alive[self.round, self.b]
        return _levelled(self.sites, self.rounds, self.round[ok], self.a[ok], self.b[ok])

    def upto(self, rounds: int) -> Schedule:
        ok = self.round < rounds
        return Schedule(self.sites, rounds, self.round[ok], self.level[ok], self.a[ok], self.b[ok])

    def after(self, rounds: int) -> Schedule:
        """The rest, counted from 0."""
        ok = self.round >= rounds
        return Schedule(self.sites, self.rounds - rounds, self.round[ok] - rounds, self.level[ok], self.a[ok], self.b[ok])


def _levelled(sites: int, rounds: int, round_: np.ndarray, a: np.ndarray, b: np.ndarray) -> Schedule:
    level = np.zeros(len(a), np.int64)
    busy, now = [0] * sites, -1
    for i, (r, x, y) in enumerate(zip(round_.tolist(), a.tolist(), b.tolist())):
        if r != now:
            busy, now = [0] * sites, r
        level[i] = max(busy[x], busy[y])
        busy[x] = busy[y] = level[i] + 1
    order = np.lexsort((np.arange(len(a)), level, round_))
    return Schedule(sites, rounds, round_[order], level[order], a[order], b[order])


def from_pairs(sites: int, rounds: list[list[tuple[int, int]]]) -> Schedule:
    """A schedule written by hand: the pairs of each round in order."""
    flat = [(r, a, b) for r, pairs in enumerate(rounds) for a, b in pairs]
    arr = np.array(flat, np.int64).reshape(-1, 3)
    return _levelled(sites, len(rounds), arr[:, 0], arr[:, 1], arr[:, 2])


def draw_exchanges(adjacency: dict[int, np.ndarray] | None, sites: int, rounds: int, fanout: int = 1, seed: int = 0) -> Schedule:
    """In every round the sites, in random order, each choose `fanout` different neighbours. adjacency None: every other site."""
    rng, out = np.random.default_rng([seed, 3]), []
    for r in range(rounds):
        for x in rng.permutation(sites).tolist():
            if adjacency is None:
                n = min(fanout, sites - 1)
                chosen = rng.choice(sites - 1, n, replace=False) if n else np.zeros(0, int)
                chosen = chosen + (chosen >= x)
            else:
                near = adjacency.get(x, np.zeros(0, int))
                chosen = rng.choice(near, min(fanout, len(near)), replace=False) if len(near) else near
            out += [(r, x, int(y)) for y in chosen]
    arr = np.array(out, np.int64).reshape(-1, 3)
    return _levelled(sites, rounds, arr[:, 0], arr[:, 1], arr[:, 2])


def draw_matching(adjacency: dict[int, np.ndarray], sites: int, rounds: int, seed: int = 0) -> Schedule:
    """Greedy random matchings: every site is in one pair of a round at most."""
    rng, out = np.random.default_rng([seed, 4]), []
    for r in range(rounds):
        free = np.ones(sites, bool)
        for x in rng.permutation(sites).tolist():
            near = adjacency.get(x, np.zeros(0, int))
            near = near[free[near]] if len(near) else near
            if free[x] and len(near):
                y = int(rng.choice(near))
                free[x] = free[y] = False
                out.append((r, x, y))
    arr = np.array(out, np.int64).reshape(-1, 3)
    return _levelled(sites, rounds, arr[:, 0], arr[:, 1], arr[:, 2])


def draw_exchanges_df(edges: DataFrame, rounds: int, fanout: int = 1, seed: int = 0) -> DataFrame:
    """(round, a, b) by DataFrames alone, for networks beyond the driver: of each site's neighbours the first by a hash."""
    from pyspark.sql import Window

    turns = edges.sparkSession.range(rounds).select(F.col("id").cast("int").alias("round"))
    tossed = edges.crossJoin(F.broadcast(turns)).withColumn("toss", F.xxhash64("round", "src", "dst", F.lit(seed)))
    place = F.row_number().over(Window.partitionBy("round", "src").orderBy("toss", "dst"))
    return tossed.withColumn("n", place).where(F.col("n") <= fanout).select("round", F.col("src").alias("a"), F.col("dst").alias("b"))


def check_levels(schedule: DataFrame) -> DataFrame:
    """(round, level, site, n) of sites that a level holds twice; empty for a valid schedule."""
    ends = schedule.select("round", "level", F.explode(F.array("a", "b")).alias("site"))
    return ends.groupBy("round", "level", "site").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
