"""Exact answers: what the approximate ones are held against."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fadegossip.decay import DecaySpec, backward_weight, decayed_count, decayed_freq


def _over(freqs: DataFrame, support: float, above: bool = True) -> DataFrame:
    """Items over (or not over) a fraction of all mass. The total is one row, broadcast."""
    total = freqs.agg(F.sum("f").alias("c"))
    limit = F.lit(support) * F.col("c")
    return freqs.crossJoin(F.broadcast(total)).where(F.col("f") > limit if above else F.col("f") <= limit)


def exact_hitters(df: DataFrame, spec: DecaySpec, support: float, asof: int) -> DataFrame:
    """(item_key, f, c): items with more than `support` of the decayed count."""
    return _over(decayed_freq(df, spec, asof), support)


def forbidden_items(df: DataFrame, spec: DecaySpec, support: float, tol: float, asof: int) -> DataFrame:
    """(item_key, f, c): items that no answer may name."""
    return _over(decayed_freq(df, spec, asof), support - tol, above=False)


def exact_backward(df: DataFrame, h: Callable[[Column], Column], support: float, asof: int) -> DataFrame:
    return _over(df.groupBy("item_key").agg(F.sum(backward_weight(asof, h)).alias("f")), support)


def exact_window(df: DataFrame, support: float, asof: int, span: int) -> DataFrame:
    """Hitters among the arrivals of the last `span` ticks; the slice is a filter on the scan."""
    return _over(df.where((F.col("tick") > asof - span) & (F.col("tick") <= asof)).groupBy("item_key").agg(F.count(F.lit(1)).cast("double").alias("f")), support)


def window_counts(df: DataFrame, span: int) -> DataFrame:
    """(item_key, tick, n): arrivals of an item in the last `span` ticks, at every tick at which it arrives."""
    daily = df.groupBy("item_key", "tick").agg(F.count(F.lit(1)).alias("m"))
    return daily.select("item_key", "tick", F.sum("m").over(Window.partitionBy("item_key").orderBy("tick").rangeBetween(1 - span, 0)).alias("n"))


def exact_plain(df: DataFrame) -> DataFrame:
    return df.groupBy("item_key").agg(F.count(F.lit(1)).alias("n"))


__all__ = ["decayed_count", "decayed_freq", "exact_backward", "exact_hitters", "exact_plain", "exact_window", "forbidden_items", "window_counts"]
