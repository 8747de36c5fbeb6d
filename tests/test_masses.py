"""The sweeps' sums over one scan, and the grids made of them."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from fadegossip import experiments as e
from fadegossip.hashing import HashFamily
from fadegossip.local import build_local, site_fold


@pytest.mark.parametrize("kept", [e.KEPT_SUMS, 0])
def test_masses_are_those_of_the_drawn_streams(spark, small, monkeypatch, kept):
    monkeypatch.setattr(e, "KEPT_SUMS", kept)
    laws = tuple(spec for _, spec in e.DECAYS)
    got = {(r.block, r.site, r.item_key): (r.x0, r.x1, r.x2, r.x3) for r in e.masses(spark, small, (0.9, 1.2), 16, 2, laws).collect()}
    want = {}
    for n, rho in enumerate((0.9, 1.2)):
        for r in e.drawn(spark, small, rho, 16, 2).groupBy("site", "item_key").agg(*[F.sum(spec.raw()).alias(f"x{i}") for i, spec in enumerate(laws)]).collect():
            want[n * 2 + r.site // 16, r.site % 16, r.item_key] = (r.x0, r.x1, r.x2, r.x3)
    assert got == want
    wide = e.masses(spark, small, (1.2,), 32, 1)
    assert {tuple(r) for r in e.dealt_to(wide, 16).collect()} == {tuple(r) for r in e.masses(spark, small, (1.2,), 16, 1).collect()}


def test_site_fold(spark, small):
    family, df = HashFamily(4, 16), e.drawn(spark, small, 1.2, 8, 1)
    found = df.groupBy("site", "item_key").agg(F.sum(e.LINEAR.raw()).alias("x"))
    rows = lambda g: sorted(tuple(r) for r in g.select("site", "row", "col", "i1", "f1", "i2", "f2").collect())
    assert rows(site_fold(found, family)) == rows(build_local(df, e.LINEAR, family, "preagg"))
    # grids that are merged lose no mass
    mass = {r.site: r.x for r in found.groupBy("site").agg(F.sum("x").alias("x")).collect()}
    parts = site_fold(found, family, held_items=50).where("row = 0").groupBy("site").agg(F.sum(F.col("f1") + F.col("f2")).alias("x")).collect()
    assert all(np.isclose(r.x, mass[r.site]) for r in parts) and len(parts) == len(mass)
