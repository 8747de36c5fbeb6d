"""Averaging gossip of grids and numbers.

Cells never meet other cells in a merge. So the state of a cell over all sites depends on that cell and on the
schedule alone: the grids are dealt by blocks of cells (the only shuffle), the schedule is sent to every task, and a
task replays all rounds for its cells in NumPy. Beyond `BROADCAST_EXCHANGES` exchanges, rounds are joins instead.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip import cells
from fadegossip.hashing import HashFamily
from fadegossip.plans import cut
from fadegossip.schedule import Schedule

#: Exchanges that are sent to every task at most (16 bytes each), and bytes of state that a task replays at once.
BROADCAST_EXCHANGES, TASK_BYTES = 20_000_000, 64 << 20
STYLES = ("push_pull", "push", "pull")


def replay_cells(key: np.ndarray, freq: np.ndarray, schedule: Schedule, style: str = "push_pull", snapshots: tuple[int, ...] = ()):
    """State arrays (sites, cells, 2) after the given numbers of rounds and after the last: yields (rounds, key, freq)."""
    done, wanted = 0, set(snapshots)

    def upto(r: int):
        nonlocal done
        while done < r:
            done += 1
            if done in wanted and done < schedule.rounds:
                yield done, key.copy(), freq.copy()

    if 0 in wanted and schedule.rounds:
        yield 0, key.copy(), freq.copy()
    for r, a, b in schedule.levels():
        yield from upto(r)
        k, f = cells.ss2_merge_np(key[a], freq[a], key[b], freq[b])
        f = f / 2
        if style != "push":
            key[a], freq[a] = k, f
        if style != "pull":
            key[b], freq[b] = k, f
    yield from upto(schedule.rounds)
    yield schedule.rounds, key, freq


def gossip_by_cell(grid: DataFrame, schedule: Schedule, family: HashFamily, style: str = "push_pull", snapshots: tuple[int, ...] = ()) -> DataFrame:
    """grid_table with `round`: the state of every site after the last round (and after the snapshots)."""
    if style not in STYLES:
        raise ValueError(f"unknown style {style}")
    if len(schedule.a) > BROADCAST_EXCHANGES:
        if snapshots:
            raise ValueError("snapshots need a schedule that fits every task")
        return gossip_by_round(grid.where(F.col("site") < schedule.sites), schedule.table(grid.sparkSession), style).select(F.lit(schedule.rounds).alias("round"), "site", "row", "col", *cells.COLUMNS)
    sites, width = schedule.sites, family.width
    per_task = max(1, min(TASK_BYTES // (sites * 32 * 6), -(-family.depth * width // 8)))
    place = F.col("row") * width + F.col("col")

    def run(part):
        at = np.asarray(part.column("row")).astype(np.int64) * width + np.asarray(part.column("col"))
        which, cell = np.unique(at, return_inverse=True)
        site = np.asarray(part.column("site"))
        key = np.full((sites, len(which), 2), cells.NONE)
        freq = np.zeros((sites, len(which), 2))
        for i in (0, 1):
            key[site, cell, i] = part.column(f"i{i + 1}").fill_null(-1).to_numpy()
            freq[site, cell, i] = part.column(f"f{i + 1}").to_numpy()
        out = []
        for r, k, f in replay_cells(key, freq, schedule, style, snapshots):
            s, c = np.nonzero((k != cells.NONE).any(-1))
            one = lambda x, kind, null=None: pa.array(x, kind, mask=null)
            cols = [one(np.full(len(s), r), pa.int32()), one(s, pa.int32()), one(which[c] // width, pa.int32()), one(which[c] % width, pa.int32())]
            for i in (0, 1):
                cols += [one(k[s, c, i], pa.int64(), k[s, c, i] == cells.NONE), one(f[s, c, i], pa.float64())]
            out.append(pa.table(cols, names=["round", "site", "row", "col", *cells.COLUMNS]))
        return pa.concat_tables(out)

    blocks = grid.where(F.col("site") < sites).withColumn("block", F.floor(place / per_task))
    return blocks.groupBy("block").applyInArrow(run, "round int, site int, row int, col int, i1 long, f1 double, i2 long, f2 double")


def gossip_by_round(grid: DataFrame, schedule: DataFrame, style: str = "push_pull", every: int = 4) -> DataFrame:
    """The same by two joins per level: for networks whose schedule fits no task, and as a check of the replay.

    The driver learns one number a round, that of its levels.
    """
    now = grid.select("site", "row", "col", *cells.COLUMNS)
    last = {x["round"]: x["last"] for x in schedule.groupBy("round").agg(F.max("level").alias("last")).collect()}
    steps = [(r, level) for r in sorted(last) for level in range(last[r] + 1)]
    for n, (r, level) in enumerate(steps, 1):
        pairs = schedule.where((F.col("round") == r) & (F.col("level") == level)).select("a", "b", F.monotonically_increasing_id().alias("pair"))
        ends = pairs.select("pair", F.explode(F.array(F.struct(F.lit(0).alias("side"), F.col("a").alias("site")), F.struct(F.lit(1).alias("side"), F.col("b").alias("site")))).alias("e")).select("pair", "e.side", "e.site")
        state = now.join(ends, "site")
        a = state.where("side = 0").select("pair", F.col("site").alias("sa"), "row", "col", cells.as_struct().alias("ca"))
        b = state.where("side = 1").select("pair", F.col("site").alias("sb"), "row", "col", cells.as_struct().alias("cb"))
        both = a.join(b, ["pair", "row", "col"], "full_outer")
        merged = both.select("pair", "row", "col", "sa", "sb", cells.ss2_merge(F.coalesce("ca", cells.empty()), F.coalesce("cb", cells.empty())).alias("cell"))
        halved = merged.select("pair", "row", "col", F.struct(F.col("cell.i1").alias("i1"), (F.col("cell.f1") / 2).alias("f1"), F.col("cell.i2").alias("i2"), (F.col("cell.f2") / 2).alias("f2")).alias("cell"))
        takers = ends if style == "push_pull" else ends.where(F.col("side") == (1 if style == "push" else 0))
        fresh = cells.flat(halved.join(takers, "pair").select("site", "row", "col", "cell"))
        now = now.join(takers.select("site"), "site", "left_anti").unionByName(fresh)
        if n % every == 0 or n == len(steps):
            now = cut(now)
    return now


def average_scalar(values: np.ndarray, schedule: Schedule, style: str = "push_pull", trace: bool = False) -> np.ndarray:
    """Values of all sites after the last round; trace: (rounds + 1, sites) with the state after each round."""
    now = np.array(values, float)
    states, done = [now.copy()], 0
    for r, a, b in schedule.levels():
        while trace and done < r:
            states.append(now.copy())
            done += 1
        mean = (now[a] + now[b]) / 2
        if style != "push":
            now[a] = mean
        if style != "pull":
            now[b] = mean
    if not trace:
        return now
    while done < schedule.rounds:
        states.append(now.copy())
        done += 1
    return np.array(states)


def shares(schedule: Schedule, leader: int = 0, style: str = "push_pull") -> np.ndarray:
    start = np.zeros(schedule.sites)
    start[leader] = 1
    return average_scalar(start, schedule, style)


def share_table(spark: SparkSession, schedule: Schedule, leader: int = 0) -> DataFrame:
    """(site, share) after the last round."""
    return spark.createDataFrame([(i, float(x)) for i, x in enumerate(shares(schedule, leader))], "site int, share double")


def site_count(share: DataFrame) -> DataFrame:
    """(site, share, p_est, reached): the inverse share estimates the number of sites; null where no share has come yet."""
    return share.select("site", "share", F.when(F.col("share") > 0, 1 / F.col("share")).alias("p_est"), (F.col("share") > 0).alias("reached"))


def mixing_matrix(schedule: Schedule, style: str = "push_pull") -> np.ndarray:
    """(sites, sites): the part of every site's start in every site's end, for whatever is averaged linearly."""
    now = np.eye(schedule.sites)
    for _, a, b in schedule.levels():
        mean = (now[a] + now[b]) / 2
        if style != "push":
            now[a] = mean
        if style != "pull":
            now[b] = mean
    return now


def mixing_table(spark: SparkSession, schedule: Schedule) -> DataFrame:
    m = mixing_matrix(schedule)
    s, t = np.nonzero(m)
    return spark.createDataFrame(list(zip(s.tolist(), t.tolist(), m[s, t].tolist())), "site int, src int, wgt double")


def average_vectors(freqs: DataFrame, schedule: Schedule) -> DataFrame:
    """freqs (site, item_key, f) -> the exact averaged frequencies that every site's grid summarises after the rounds."""
    mixing = mixing_table(freqs.sparkSession, schedule)
    return freqs.withColumnRenamed("site", "src").join(mixing, "src").groupBy("site", "item_key").agg(F.sum(F.col("wgt") * F.col("f")).alias("f"))


def avg_merge_round(grid: DataFrame, pairs: list[tuple[int, int]], sites: int, family: HashFamily) -> DataFrame:
    """One simulated round over all sites' grids."""
    from fadegossip.schedule import from_pairs

    return gossip_by_cell(grid, from_pairs(sites, [pairs]), family)


def coordinator_merge(grid: DataFrame, sites: int, fan_in: int = 256) -> DataFrame:
    """(row, col, cell): the grid that gossip tends to, by one aggregation: all grids merged, divided by their number."""
    return cells.scale_grid(cells.fold_grids(grid, ("row", "col"), fan_in, sites), sites)
