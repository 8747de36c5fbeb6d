"""Sketches and summaries that the grids are compared with."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadegossip.decay import DecaySpec
from fadegossip.hashing import HashFamily, with_cells
from fadegossip.local import build_local


def plain_sketch(df: DataFrame, spec: DecaySpec, family: HashFamily) -> DataFrame:
    """(row, col, mass): one counter per cell. Items are summed before they are dealt to the rows."""
    masses = df.groupBy("item_key").agg(F.sum(spec.raw()).alias("x"))
    return with_cells(masses, family).groupBy("row", "col").agg(F.sum("x").alias("mass"))


def plain_point(sketch: DataFrame, items: DataFrame, family: HashFamily, spec: DecaySpec, asof: int) -> DataFrame:
    """(item_key, est): the least counter over the rows."""
    cells = with_cells(items.select("item_key").distinct(), family)
    return cells.join(sketch, ["row", "col"], "left").groupBy("item_key").agg((F.min(F.coalesce("mass", F.lit(0.0))) / F.lit(spec.norm(asof))).alias("est"))


def plain_hitters(df: DataFrame, spec: DecaySpec, family: HashFamily, k: int, asof: int) -> DataFrame:
    """(item_key, est): the k items with the largest sketch estimates (a report of k rows)."""
    return plain_point(plain_sketch(df, spec, family), df, family, spec, asof).orderBy(F.desc("est"), "item_key").limit(k)


def ss_update_k(state: dict[int, float], key: int, x: float, k: int) -> None:
    """One weighted arrival at a summary of k counters; the evicted one is the least, then the smallest key."""
    if key in state:
        state[key] += x
    elif len(state) < k:
        state[key] = x
    else:
        out = min(state, key=lambda i: (state[i], i))
        state[key] = state.pop(out) + x


def ss_merge_k(a: dict[int, float], b: dict[int, float], k: int) -> dict[int, float]:
    """Summary of the union: counters add up, an item that a full summary lacks gets its minimum there; the best k stay."""
    low_a, low_b = (min(s.values()) if len(s) >= k else 0.0 for s in (a, b))
    both = {i: f + b.get(i, low_b) for i, f in a.items()} | {i: f + low_a for i, f in b.items() if i not in a}
    return dict(sorted(both.items(), key=lambda e: (-e[1], e[0]))[:k])


def space_saving(df: DataFrame, spec: DecaySpec, k: int, asof: int, fan_in: int = 64) -> DataFrame:
    """(item_key, est): partitions fold their arrivals, then summaries are merged in a tree of four levels."""

    def fold(batches):
        state: dict[int, float] = {}
        part = 0
        for batch in batches:
            if batch.num_rows:
                part = batch.column("part")[0].as_py()
            for key, x in zip(batch.column("item_key").to_pylist(), batch.column("x").to_pylist()):
                ss_update_k(state, key, x, k)
        if state:
            yield pa.RecordBatch.from_arrays([pa.array([part], pa.int64()), pa.array([list(state)], pa.list_(pa.int64())), pa.array([list(state.values())], pa.list_(pa.float64()))], ["part", "keys", "freqs"])

    def merge(group):
        rows = sorted(zip(group.column("keys").to_pylist(), group.column("freqs").to_pylist()))
        state: dict[int, float] = {}
        for keys, freqs in rows:
            state = ss_merge_k(state, dict(zip(keys, freqs)), k) if state else dict(zip(keys, freqs))
        return pa.table({"part": pa.array([group.column("part")[0].as_py()], pa.int64()), "keys": pa.array([list(state)], pa.list_(pa.int64())), "freqs": pa.array([list(state.values())], pa.list_(pa.float64()))})

    schema = "part long, keys array<long>, freqs array<double>"
    parts = df.select("item_key", spec.raw().alias("x"), F.spark_partition_id().alias("part")).mapInArrow(fold, schema)
    for _ in range(4):  # `fan_in` neighbours at once, so that fan_in ** 4 partitions end in one summary
        parts = parts.withColumn("part", F.floor(F.col("part") / fan_in)).groupBy("part").applyInArrow(merge, schema)
    return parts.select(F.explode(F.arrays_zip("keys", "freqs")).alias("x")).select(F.col("x.keys").alias("item_key"), (F.col("x.freqs") / F.lit(spec.norm(asof))).alias("est"))


def centralised(df: DataFrame, spec: DecaySpec, family: HashFamily, mode: str = "preagg") -> DataFrame:
    """The grid of one site that sees the whole stream."""
    return build_local(df.withColumn("site", F.lit(0)), spec, family, mode)


def builtin_neighbours(df: DataFrame, support: float) -> DataFrame:
    """One row of Spark's own sketches: frequent items, distinct items two ways."""
    frequent = df.freqItems(["item_key"], support).select(F.array_sort("item_key_freqItems").alias("frequent"))
    distinct = df.agg(F.approx_count_distinct("item_key").alias("distinct_hll"), F.hll_sketch_estimate(F.hll_sketch_agg("item_key")).alias("distinct_sketch"))
    return frequent.crossJoin(distinct)


def builtin_count_min(df: DataFrame, eps: float, confidence: float, seed: int = 1) -> DataFrame:
    """Spark's own counter sketch of undecayed counts, serialised."""
    return df.agg(F.count_min_sketch("item_key", F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))


def sequential_space_saving(items: list[tuple[int, float]], k: int) -> dict[int, float]:
    state: dict[int, float] = {}
    for key, x in items:
        ss_update_k(state, key, x, k)
    return state


def variance(values: np.ndarray) -> float:
    return float(np.var(values, ddof=1))
