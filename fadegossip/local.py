"""Grids of single sites: three ways to build them, initial shares, and dealing a stream to sites.

`arrival` folds every arrival in order (exact to the sequential algorithm, one task holds a cell's stream: tests and
small data). `preagg` folds one weighted update per site and item, largest first; a cell's distinct items meet in one row.
`partition`, the default, lets every input partition fold its own items in NumPy and merges the partial grids in a tree of bounded
fan-in: the shuffle has partitions x cells rows, whatever the number of arrivals and items.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fadegossip import cells
from fadegossip.decay import DecaySpec
from fadegossip.hashing import P, HashFamily, with_cells
from fadegossip.sources.streams import fingerprint

GRID = "site int, row int, col int, i1 long, f1 double, i2 long, f2 double"
#: Partial grids that are merged at once; three levels of the tree serve FAN_IN ** 3 partitions.
FAN_IN = 256


def preaggregate(df: DataFrame, spec: DecaySpec) -> DataFrame:
    """(site, item_key, x): decayed mass of an item at a site. Combined before the shuffle, so a hot item costs a row per partition."""
    return df.groupBy("site", "item_key").agg(F.sum(spec.raw()).alias("x"))


def build_local(df: DataFrame, spec: DecaySpec, family: HashFamily, mode: str = "partition") -> DataFrame:
    """(site, row, col, i1, f1, i2, f2): the touched cells of every site's grid, numerators of the decay in the counters."""
    if mode == "arrival":
        rows = with_cells(df.select("site", "item_key", "tick", "seq", spec.raw().alias("x")), family)
        entry = F.struct("tick", "seq", F.col("item_key").alias("key"), "x")
    elif mode == "preagg":
        rows = with_cells(preaggregate(df, spec), family)
        entry = F.struct((-F.col("x")).alias("order"), F.col("item_key").alias("key"), "x")
    elif mode == "partition":
        return partition_fold(df, spec, family)
    else:
        raise ValueError(f"unknown mode {mode}")
    return cells.flat(rows.groupBy("site", "row", "col").agg(cells.fold(F.array_sort(F.collect_list(entry))).alias("cell")))


def fold_ranked(site: np.ndarray, key: np.ndarray, x: np.ndarray, family: HashFamily) -> dict[str, np.ndarray]:
    """Cells of distinct (site, key) with masses x, each folded with its heaviest item first; vectorised over cells."""
    d = family.depth
    a, b = (np.array(v, np.int64)[:, None] for v in zip(*family.params))
    col = ((a * (key % P)[None, :] + b) % P) % family.width
    row = np.repeat(np.arange(d), len(key))
    cell = (np.tile(site.astype(np.int64), d) * d + row) * family.width + col.ravel()
    keys, xs = np.tile(key, d), np.tile(x, d)
    order = np.lexsort((keys, -xs, cell))
    cell, keys, xs = cell[order], keys[order], xs[order]
    first = np.flatnonzero(np.concatenate(([True], cell[1:] != cell[:-1]))) if len(cell) else np.zeros(0, np.int64)
    size = np.diff(np.append(first, len(cell)))
    k = np.full((len(first), 2), cells.NONE)
    f = np.zeros((len(first), 2))
    for step in range(int(size.max()) if len(size) else 0):
        on = np.flatnonzero(size > step)
        at = first[on] + step
        # items are distinct: the newcomer takes a free counter or inherits the least one
        slot = step if step < 2 else np.where((f[on, 0] < f[on, 1]) | ((f[on, 0] == f[on, 1]) & (k[on, 0] < k[on, 1])), 0, 1)
        f[on, slot] += xs[at]
        k[on, slot] = keys[at]
    swap = (k[:, 1] != cells.NONE) & ((f[:, 1] > f[:, 0]) | ((f[:, 1] == f[:, 0]) & (k[:, 1] < k[:, 0])))
    k[swap], f[swap] = k[swap][:, ::-1], f[swap][:, ::-1]
    where = cell[first] if len(first) else first
    return {"site": where // (family.width * d), "row": where // family.width % d, "col": where % family.width, "i1": k[:, 0], "f1": f[:, 0], "i2": k[:, 1], "f2": f[:, 1]}


def _as_batch(got: dict[str, np.ndarray]) -> pa.RecordBatch:
    kinds = {"site": pa.int32(), "row": pa.int32(), "col": pa.int32(), "i1": pa.int64(), "f1": pa.float64(), "i2": pa.int64(), "f2": pa.float64()}
    return pa.RecordBatch.from_arrays([pa.array(got[c], kind, mask=got[c] == cells.NONE if c in ("i1", "i2") else None) for c, kind in kinds.items()], list(kinds))


def partition_fold(df: DataFrame, spec: DecaySpec, family: HashFamily, held_items: int = 1 << 20, fan_in: int = FAN_IN) -> DataFrame:
    """Every input partition sums its items and folds them; partial grids are merged by site and cell in a tree.

    A partition with over `held_items` distinct items at once emits what it has and goes on, so memory is bounded. A
    merge gathers the grids of `fan_in` neighbouring partitions (or of as many merged ones) and no more.
    """

    def run(batches):
        have: dict[str, np.ndarray] = {}

        def add(site, key, x):
            if have:
                site, key, x = (np.concatenate((have[n], v)) for n, v in zip(("site", "key", "x"), (site, key, x)))
            order = np.lexsort((key, site))
            site, key, x = site[order], key[order], x[order]
            new = np.concatenate(([True], (site[1:] != site[:-1]) | (key[1:] != key[:-1]))) if len(site) else np.zeros(0, bool)
            have.update(site=site[new], key=key[new], x=np.add.reduceat(x, np.flatnonzero(new)) if len(site) else x)

        for batch in batches:
            if batch.num_rows:
                add(*(np.asarray(batch.column(c)) for c in ("site", "item_key", "x")))
            if have and len(have["key"]) > held_items:
                yield _as_batch(fold_ranked(have["site"], have["key"], have["x"], family))
                have.clear()
        if have:
            yield _as_batch(fold_ranked(have["site"], have["key"], have["x"], family))

    partial = df.select("site", "item_key", spec.raw().alias("x")).mapInArrow(run, GRID).withColumn("part", F.spark_partition_id())
    for _ in range(2):
        partial = cells.fold_grids(partial.withColumn("part", F.floor(F.col("part") / fan_in)), ("site", "row", "col", "part"))
    return cells.fold_grids(partial)


def _joined(one: dict[str, np.ndarray], other: dict[str, np.ndarray], family: HashFamily) -> dict[str, np.ndarray]:
    """Two grids of the same sites merged cell by cell."""
    place = lambda g: (g["site"] * family.depth + g["row"]) * family.width + g["col"]
    cell = np.union1d(place(one), place(other))
    sides = []
    for g in (one, other):
        k, f = np.full((len(cell), 2), cells.NONE), np.zeros((len(cell), 2))
        at = np.searchsorted(cell, place(g))
        k[at], f[at] = np.column_stack([g["i1"], g["i2"]]), np.column_stack([g["f1"], g["f2"]])
        sides += [k, f]
    k, f = cells.ss2_merge_np(*sides)
    return {"site": cell // (family.width * family.depth), "row": cell // family.width % family.depth, "col": cell % family.width, "i1": k[:, 0], "f1": f[:, 0], "i2": k[:, 1], "f2": f[:, 1]}


def site_fold(masses: DataFrame, family: HashFamily, held_items: int = 1 << 20) -> DataFrame:
    """Grids of masses (site, item_key, x), one row for an item of a site: the cells of `preagg`, folded in NumPy.

    A site is in one task. Of more than `held_items` items at once the task folds what it has and merges the grids, so
    memory is bounded; up to that number a cell gets its items in one order, whatever the partitions.
    """

    def run(batches):
        done, parts, held = None, [], 0

        def folded():
            site, key, x = (np.concatenate(v) for v in zip(*parts))
            got = fold_ranked(site, key, x, family)
            return got if done is None else _joined(done, got, family)

        for batch in batches:
            parts.append([np.asarray(batch.column(c)) for c in ("site", "item_key", "x")])
            held += batch.num_rows
            if held > held_items:
                done, parts, held = folded(), [], 0
        if held:
            done = folded()
        if done is not None:
            yield _as_batch(done)

    return masses.select("site", "item_key", "x").repartition("site").sortWithinPartitions("site", "item_key").mapInArrow(run, GRID)


def init_share(spark: SparkSession, sites: int, leader: int = 0) -> DataFrame:
    """(site, share): 1 at one site, 0 at the others; averaging makes it 1 / sites."""
    return spark.range(sites).select(F.col("id").cast("int").alias("site"), F.when(F.col("id") == leader, 1.0).otherwise(0.0).alias("share"))


def empty_grid(spark: SparkSession, family: HashFamily, sites: int | DataFrame) -> DataFrame:
    """Dense grids without counters (stored grids leave empty cells out), of a number of sites or of those of a table (site)."""
    site = spark.range(sites).select(F.col("id").cast("int").alias("site")) if isinstance(sites, int) else sites.select("site").distinct()
    places = F.explode(F.sequence(F.lit(0), F.lit(family.depth * family.width - 1))).alias("at")
    grid = site.select("site", places).select("site", F.floor(F.col("at") / family.width).cast("int").alias("row"), (F.col("at") % family.width).cast("int").alias("col"))
    return cells.flat(grid.withColumn("cell", cells.empty()))


def assign_sites(df: DataFrame, policy: str, sites: int, key: str = "item_key") -> DataFrame:
    """hash: by a hash of the row; modulo: by a key; blocks: contiguous in time; one: all on site 0 (the worst start)."""
    by: dict[str, Column] = {
        "hash": F.pmod(fingerprint(F.concat_ws("|", F.col("item_key").cast("string"), F.col("tick").cast("string"), F.col("seq").cast("string"))), F.lit(sites)).cast("int"),
        "modulo": F.pmod(F.col(key), F.lit(sites)).cast("int"),
        "one": F.lit(0),
    }
    if policy == "blocks":
        # bounds of equal mass from approximate quantiles of time, so that nothing is sorted
        edge = [x for x in df.approxQuantile("tick", [i / sites for i in range(1, sites)], 0.001)] if sites > 1 else []
        place = sum((F.col("tick") > F.lit(e)).cast("int") for e in edge) if edge else F.lit(0)
        return df.withColumn("site", place + F.lit(0))
    return df.withColumn("site", by[policy])


def ranked_blocks(df: DataFrame, sites: int) -> DataFrame:
    """Blocks of exactly equal size, by a global order (small data)."""
    return df.withColumn("site", F.ntile(sites).over(Window.orderBy("tick", "seq")) - 1)
