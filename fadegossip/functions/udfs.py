"""Functions that Python has to compute: table functions, a grouped fold, ranks of a large Zipf law."""

from __future__ import annotations

import pandas as pd
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType, LongType, StructField, StructType

from fadegossip import planner
from fadegossip.hashing import HashFamily
from fadegossip.sources.zipf import _rank_udf as zipf_rank  # noqa: F401  (re-exported)


@udtf(returnType="strategy string, depth int, width int, rounds int, slack double, tol double, fail double")
class PlanParameters:
    """Both strategies for wanted guarantees."""

    def eval(self, support: float, tol: float, site_cap: float, fail: float, fail_gossip: float):
        for strategy in ("time", "space"):
            p = planner.plan(strategy, float(support), float(tol), float(site_cap), float(fail), float(fail_gossip))
            yield strategy, p.depth, p.width, p.rounds, p.slack, p.tol, p.fail


@udtf(returnType="row int, col int")
class HashRows:
    """Cells of a key."""

    def eval(self, key: int, depth: int, width: int):
        for r, (a, b) in enumerate(HashFamily(depth, width).params):
            yield r, (a * (key % 2147483647) + b) % 2147483647 % width


CELL = StructType([StructField("i1", LongType()), StructField("f1", DoubleType()), StructField("i2", LongType()), StructField("f2", DoubleType())])


def _fold(keys, xs) -> dict:
    k, f = [None, None], [0.0, 0.0]
    for key, x in zip(keys, xs):
        if key in k:
            f[k.index(key)] += x
        elif None in k:
            at = k.index(None)
            k[at], f[at] = key, x
        else:
            at = 0 if (f[0], k[0]) < (f[1], k[1]) else 1
            k[at], f[at] = key, f[at] + x
    if k[1] is not None and (-f[1], k[1]) < (-f[0], k[0]):
        k, f = k[::-1], f[::-1]
    return {"i1": k[0], "f1": f[0], "i2": k[1], "f2": f[1]}


@pandas_udf(CELL)
def fold_udf(keys: pd.Series, xs: pd.Series) -> pd.DataFrame:
    """Cells of ordered arrays of keys and weights; the native fold is cells.fold."""
    return pd.DataFrame([_fold(k, x) for k, x in zip(keys, xs)]).astype({"i1": "Int64", "i2": "Int64"})
