"""Cells with two counters: update, majority candidate, minimum, merge, scaling.

A cell is (i1, f1, i2, f2), a null item being a free counter. Order is total everywhere: larger frequency first,
then smaller key; the counter to be evicted is the one with smaller frequency, then smaller key. `i1` is the
majority candidate of a stored cell.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CELL = "struct<i1:bigint,f1:double,i2:bigint,f2:double>"
COLUMNS = ("i1", "f1", "i2", "f2")


def empty() -> Column:
    return F.struct(F.lit(None).cast("long").alias("i1"), F.lit(0.0).alias("f1"), F.lit(None).cast("long").alias("i2"), F.lit(0.0).alias("f2"))


def _cell(i1: Column, f1: Column, i2: Column, f2: Column) -> Column:
    return F.struct(i1.alias("i1"), f1.alias("f1"), i2.alias("i2"), f2.alias("f2"))


def ordered(s: Column) -> Column:
    """The larger counter first."""
    swap = s.i2.isNotNull() & ((s.f2 > s.f1) | ((s.f2 == s.f1) & (s.i2 < s.i1)))
    return F.when(swap, _cell(s.i2, s.f2, s.i1, s.f1)).otherwise(_cell(s.i1, s.f1, s.i2, s.f2))


def ss2_update(s: Column, key: Column, x: Column) -> Column:
    """The cell after an arrival of weight x: hit, free counter, or the least counter is inherited."""
    first_goes = (s.f1 < s.f2) | ((s.f1 == s.f2) & (s.i1 < s.i2))
    return (
        F.when(s.i1 == key, _cell(s.i1, s.f1 + x, s.i2, s.f2))
        .when(s.i2 == key, _cell(s.i1, s.f1, s.i2, s.f2 + x))
        .when(s.i1.isNull(), _cell(key, x, s.i2, s.f2))
        .when(s.i2.isNull(), _cell(s.i1, s.f1, key, x))
        .when(first_goes, _cell(key, s.f1 + x, s.i2, s.f2))
        .otherwise(_cell(s.i1, s.f1, key, s.f2 + x))
    )


def fold(arrivals: Column) -> Column:
    """Cell of an ordered array of (key, x) structs."""
    return F.aggregate(arrivals, empty(), lambda s, e: ss2_update(s, e.key, e.x), ordered)


def majority(s: Column) -> Column:
    return ordered(s).i1


def cell_min(s: Column) -> Column:
    """The least counter, 0 while one is free."""
    return F.when(s.i1.isNull() | s.i2.isNull(), F.lit(0.0)).otherwise(F.least(s.f1, s.f2))


def ss2_merge(a: Column, b: Column) -> Column:
    """Cell of the union of two streams: counters of an item add up, an item the other cell lacks gets its minimum; the best two stay."""
    in_other = lambda key, s: F.when(s.i1 == key, s.f1).when(s.i2 == key, s.f2)
    own = lambda key, f, s: F.when(key.isNotNull(), F.struct((-(f + F.coalesce(in_other(key, s), cell_min(s)))).alias("minus"), key.alias("key")))
    new = lambda key, f, s: F.when(key.isNotNull() & in_other(key, s).isNull(), F.struct((-(f + cell_min(s))).alias("minus"), key.alias("key")))
    best = F.array_sort(F.filter(F.array(own(a.i1, a.f1, b), own(a.i2, a.f2, b), new(b.i1, b.f1, a), new(b.i2, b.f2, a)), lambda c: c.isNotNull()))
    at = lambda n: F.get(best, F.lit(n))
    return _cell(at(0).key, F.coalesce(-at(0).minus, F.lit(0.0)), at(1).key, F.coalesce(-at(1).minus, F.lit(0.0)))


def as_struct(prefix: str = "") -> Column:
    return _cell(*[F.col(prefix + c) for c in COLUMNS])


def flat(df: DataFrame, cell: str = "cell") -> DataFrame:
    """The cell struct as four columns."""
    return df.select(*[c for c in df.columns if c != cell], *[F.col(f"{cell}.{c}").alias(c) for c in COLUMNS])


def scale_grid(grid: DataFrame, v: float) -> DataFrame:
    """Every counter divided by v."""
    return grid.withColumns({f: F.col(f) / F.lit(float(v)) for f in ("f1", "f2")})


def merge_grids(left: DataFrame, right: DataFrame, by: tuple[str, ...] = ("row", "col")) -> DataFrame:
    """Grid of the union of two streams; a cell that one side lacks is empty there."""
    a = left.select(*by, as_struct().alias("a"))
    b = right.select(*by, as_struct().alias("b"))
    joined = a.join(b, list(by), "full_outer")
    return flat(joined.select(*by, ss2_merge(F.coalesce("a", empty()), F.coalesce("b", empty())).alias("cell")))


def fold_grids(grids: DataFrame, by: tuple[str, ...] = ("site", "row", "col"), fan_in: int = 256, parts: int | None = None) -> DataFrame:
    """Merges all cells with equal `by`, in the order of their counters (merging is not associative).

    parts: how many cells a group may hold at most; above `fan_in` the merge is a tree, so that no task gathers more.
    """
    if parts and parts > fan_in:
        grids = fold_grids(grids.withColumn("_part", F.pmod(F.xxhash64(*COLUMNS), F.lit(-(-parts // fan_in)))), (*by, "_part"), fan_in)
    cells = F.array_sort(F.collect_list(F.struct((-F.col("f1")).alias("n1"), "i1", (-F.col("f2")).alias("n2"), "i2")))
    each = lambda e: _cell(e.i1, -e.n1, e.i2, -e.n2)
    return flat(grids.groupBy(*by).agg(cells.alias("all")).select(*by, F.aggregate("all", empty(), lambda s, e: ss2_merge(s, each(e))).alias("cell")))


# -- NumPy twin, for replaying many exchanges ------------------------------------------------------------------

NONE = np.int64(-1)


def ss2_merge_np(ka: np.ndarray, fa: np.ndarray, kb: np.ndarray, fb: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Cell-wise merge of arrays (..., 2) of keys (-1: free) and counters."""
    low = lambda k, f: np.where((k == NONE).any(-1), 0.0, f.min(-1))[..., None]
    hit = (ka[..., :, None] == kb[..., None, :]) & (ka != NONE)[..., :, None]
    own = fa + np.where(hit.any(-1), (hit * fb[..., None, :]).sum(-1), low(kb, fb))
    new = fb + low(ka, fa)
    key = np.concatenate((ka, kb), -1)
    freq = np.concatenate((np.where(ka == NONE, -np.inf, own), np.where((kb == NONE) | hit.any(-2), -np.inf, new)), -1)
    best = np.lexsort((key, -freq), axis=-1)[..., :2]
    key, freq = np.take_along_axis(key, best, -1), np.take_along_axis(freq, best, -1)
    gone = np.isneginf(freq)
    return np.where(gone, NONE, key), np.where(gone, 0.0, freq)
