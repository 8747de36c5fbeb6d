"""Every query with a DuckDB counterpart gives the same rows; the others run. (The sweeps are run by the experiment tests.)"""

import math

import duckdb
import pytest

from fadegossip import catalog, experiments

QUERIES, ORACLES = catalog.queries(), catalog.oracles()
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(small):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    return con


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else float(f"{v:.10g}")
    if hasattr(v, "item"):
        return plain(v.item())
    if isinstance(v, (list, tuple)):
        return tuple(map(plain, v))
    return v


@pytest.mark.parametrize("name", [n for n in QUERIES if n not in experiments.QUERIES or n in ORACLES])
def test_query(spark, small, duck, name):
    df = QUERIES[name](spark, small)
    names = sorted(df.columns)
    got = sorted(repr(tuple(plain(r[c]) for c in names)) for r in df.collect())
    if name in ORACLES:
        result = duck.sql(ORACLES[name])
        columns = result.columns
        assert sorted(columns) == names
        assert got == sorted(repr(tuple(plain(r[columns.index(c)]) for c in names)) for r in result.fetchall())
