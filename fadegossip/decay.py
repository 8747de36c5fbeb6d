"""Time decay of arrivals.

Forward decay weighs an arrival by g(age of the arrival from the landmark) / g(age of the query). The numerator
never changes, so counters keep numerators and a query divides once. All weights are native column expressions.
"""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class DecaySpec:
    """kind: none, poly (power b), exp (rate lam), half_life (whole ticks H, dyadic weights), step (0 up to `cut`, then 1)."""

    kind: str = "none"
    b: float = 1.0
    lam: float = 0.0
    half: int = 1
    cut: int = 0
    shift: int = 0  # ticks by which the landmark was moved on (rebase)

    def __post_init__(self):
        if self.kind not in ("none", "poly", "exp", "half_life", "step"):
            raise ValueError(f"unknown decay {self.kind}")
        if self.kind == "exp" and self.lam <= 0 or self.kind == "half_life" and self.half < 1 or self.kind == "poly" and self.b < 0:
            raise ValueError("a decay needs a positive parameter")

    def raw(self, tick: str | Column = "tick") -> Column:
        """The numerator g(tick)."""
        t = F.col(tick) if isinstance(tick, str) else tick
        if self.shift:
            t = t - F.lit(self.shift)
        if self.kind == "none":
            return F.lit(1.0)
        if self.kind == "poly":
            return t.cast("double") if self.b == 1 else F.pow(t.cast("double"), F.lit(float(self.b)))
        if self.kind == "exp":
            return F.exp(F.lit(self.lam) * t)
        if self.kind == "half_life":
            return F.pow(F.lit(2.0), F.floor(t / F.lit(self.half)).cast("double"))
        return F.when(t > self.cut, F.lit(1.0)).otherwise(F.lit(0.0))

    def norm(self, asof: int) -> float:
        """The denominator g(asof)."""
        t = asof - self.shift
        if self.kind == "none":
            return 1.0
        if self.kind == "poly":
            return float(t) ** self.b
        if self.kind == "exp":
            return math.exp(self.lam * t)
        if self.kind == "half_life":
            return 2.0 ** (t // self.half)
        return 1.0 if t > self.cut else 0.0

    def rebased(self, ticks: int) -> tuple[DecaySpec, float]:
        """The same decay from a landmark `ticks` later, and the factor for counters that exist. Exponential kinds only."""
        if self.kind == "half_life" and ticks % self.half:
            raise ValueError("a half-life landmark moves by whole half-lives")
        if self.kind not in ("exp", "half_life"):
            raise ValueError("only exponential weights survive a move of the landmark")
        factor = math.exp(-self.lam * ticks) if self.kind == "exp" else 2.0 ** -(ticks // self.half)
        return DecaySpec(self.kind, self.b, self.lam, self.half, self.cut, self.shift + ticks), factor

    def last_safe_tick(self) -> float:
        """Ticks from the landmark at which numerators overflow a double."""
        if self.kind == "exp":
            return self.shift + math.log(1.7e308) / self.lam
        return self.shift + 1023 * self.half if self.kind == "half_life" else math.inf


def weight(spec: DecaySpec, asof: int, tick: str | Column = "tick") -> Column:
    """Forward decayed weight at `asof`."""
    return spec.raw(tick) / F.lit(spec.norm(asof))


def backward_weight(asof: int, h: Callable[[Column], Column], tick: str | Column = "tick") -> Column:
    """h(age at query) / h(0): every weight changes with the query time."""
    t = F.col(tick) if isinstance(tick, str) else tick
    return h(F.lit(asof) - t) / h(F.lit(0))


def check_decay(spec: DecaySpec, df: DataFrame, asofs: list[int]) -> DataFrame:
    """One row: how many weights break the law (1 at the own time, within [0, 1], not growing with the query time)."""
    times = df.sparkSession.createDataFrame([(t, spec.norm(t)) for t in sorted(asofs)], "asof long, norm double")
    w = df.select("tick").distinct().crossJoin(F.broadcast(times)).where("asof >= tick").withColumn("w", spec.raw() / F.col("norm"))
    own = spec.raw() / F.coalesce(F.nullif(spec.raw(), F.lit(0.0)), F.lit(1.0))
    grown = w.withColumn("before", F.lag("w").over(Window.partitionBy("tick").orderBy("asof")))
    bad = (F.col("w") < 0) | (F.col("w") > 1) | (F.col("before") < F.col("w"))
    return grown.agg(F.count_if(bad).alias("violations"), F.count_if((own != 1) & (spec.raw() != 0)).alias("own_time"))


def forward_backward_gap(df: DataFrame, lam: float, asof: int) -> DataFrame:
    """One row: the largest difference of forward and backward exponential weights, which are equal."""
    forward = weight(DecaySpec("exp", lam=lam), asof)
    backward = backward_weight(asof, lambda age: F.exp(-F.lit(lam) * age))
    return df.agg(F.max(F.abs(forward - backward)).alias("gap"))


def decayed_freq(df: DataFrame, spec: DecaySpec, asof: int) -> DataFrame:
    """(item_key, f): decayed frequency of every item. One shuffle of distinct items."""
    return df.groupBy("item_key").agg((F.sum(spec.raw()) / F.lit(spec.norm(asof))).alias("f"))


def decayed_count(df: DataFrame, spec: DecaySpec, asof: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Total decayed mass, of all or by columns."""
    return df.groupBy(*by).agg((F.sum(spec.raw()) / F.lit(spec.norm(asof))).alias("c"))


def rebase(grid: DataFrame, factor: float) -> DataFrame:
    """Counters of a grid for a moved landmark."""
    return grid.withColumns({f: F.col(f) * F.lit(factor) for f in ("f1", "f2")})
