"""Laws of decay, hand-made cells, and the NumPy twin of the column expressions."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from fadegossip import cells
from fadegossip.baselines import sequential_space_saving, ss_merge_k
from fadegossip.decay import DecaySpec, backward_weight, weight
from fadegossip.functions.udfs import _fold
from fadegossip.hashing import HashFamily
from fadegossip.local import fold_ranked

SPECS = [DecaySpec(), DecaySpec("poly", b=1), DecaySpec("poly", b=2), DecaySpec("exp", lam=0.2), DecaySpec("half_life", half=3), DecaySpec("step", cut=4)]


@pytest.mark.parametrize("spec", SPECS)
def test_decay_law(spark, spec):
    rows = spark.range(1, 40).withColumnRenamed("id", "tick")
    got = {r.tick: [r[f"w{t}"] for t in (40, 60, 90)] for r in rows.select("tick", *[weight(spec, t).alias(f"w{t}") for t in (40, 60, 90)]).collect()}
    for ws in got.values():
        assert all(0 <= w <= 1 for w in ws) and ws == sorted(ws, reverse=True)
    own = rows.select((spec.raw() / F.lit(spec.norm(39))).alias("w")).where("tick = 39").first().w
    assert own == 1


def test_forward_is_backward_for_the_exponential(spark):
    rows = spark.range(1, 30).withColumnRenamed("id", "tick")
    gap = rows.select(F.max(F.abs(weight(DecaySpec("exp", lam=0.3), 31) - backward_weight(31, lambda a: F.exp(-0.3 * a)))).alias("g")).first().g
    assert gap < 1e-12


def test_rebase():
    spec, factor = DecaySpec("half_life", half=7).rebased(14)
    assert factor == 0.25 and spec.norm(28) == 4.0
    spec, factor = DecaySpec("exp", lam=0.5).rebased(10)
    assert math.isclose(spec.norm(20) / factor, DecaySpec("exp", lam=0.5).norm(20))
    with pytest.raises(ValueError):
        DecaySpec("poly").rebased(3)
    with pytest.raises(ValueError):
        DecaySpec("half_life", half=7).rebased(3)


# keys: a=1 b=2 c=3 d=4
FOLDS = [([(1, 3), (2, 1), (3, 2)], (1, 3, 3, 3)), ([(1, 2), (2, 2), (3, 1)], (3, 3, 2, 2)), ([(1, 5)], (1, 5, None, 0)), ([], (None, 0, None, 0))]
MERGES = [
    ((1, 5, 2, 3), (3, 4, 4, 2), (1, 7, 3, 7)), ((1, 5, 2, 3), (1, 1, 3, 4), (3, 7, 1, 6)), ((1, 5, None, 0), (3, 4, 4, 2), (1, 7, 3, 4)),
    ((1, 5, 2, 3), (None, 0, None, 0), (1, 5, 2, 3)), ((None, 0, None, 0), (None, 0, None, 0), (None, 0, None, 0)),
]


@pytest.mark.parametrize("arrivals, want", FOLDS)
def test_fold(spark, arrivals, want):
    got = _fold([k for k, _ in arrivals], [float(x) for _, x in arrivals])
    assert tuple(got.values()) == want
    array = F.array(*[F.struct(F.lit(k).cast("long").alias("key"), F.lit(float(x)).alias("x")) for k, x in arrivals]) if arrivals else F.expr("CAST(array() AS array<struct<key:bigint,x:double>>)")
    assert tuple(spark.range(1).select(cells.fold(array).alias("c")).select("c.*").first()) == want


def column(cell):
    i1, f1, i2, f2 = cell
    return F.struct(F.lit(i1).cast("long").alias("i1"), F.lit(float(f1)).alias("f1"), F.lit(i2).cast("long").alias("i2"), F.lit(float(f2)).alias("f2"))


def arrays(cell):
    return np.array([-1 if i is None else i for i in cell[::2]], np.int64), np.array(cell[1::2], float)


@pytest.mark.parametrize("a, b, want", MERGES)
def test_merge(spark, a, b, want):
    assert tuple(spark.range(1).select(cells.ss2_merge(column(a), column(b)).alias("c")).select("c.*").first()) == want
    k, f = cells.ss2_merge_np(*arrays(a), *arrays(b))
    assert tuple(x for pair in zip([None if i < 0 else i for i in k.tolist()], f.tolist()) for x in pair) == want


def random_cell(rng):
    n = rng.randrange(3)
    keys = rng.sample(range(1, 6), n)
    fs = sorted((float(rng.randrange(1, 9)) for _ in range(n)), reverse=True)
    cell = [x for pair in zip(keys, fs) for x in pair] + [None, 0.0] * (2 - n)
    if n == 2 and fs[0] == fs[1] and keys[0] > keys[1]:
        cell = cell[2:] + cell[:2]
    return tuple(cell)


def test_merge_laws_and_twin(spark):
    rng = random.Random(1)
    pairs = [(random_cell(rng), random_cell(rng)) for _ in range(400)]
    schema = ", ".join(f"{s}{c} {'long' if c[0] == 'i' else 'double'}" for s in "ab" for c in cells.COLUMNS)
    df = spark.createDataFrame([(*a, *b) for a, b in pairs], schema).coalesce(1)
    native = [tuple(r) for r in df.select(cells.ss2_merge(cells.as_struct("a"), cells.as_struct("b")).alias("c")).select("c.*").collect()]
    for (a, b), got in zip(pairs, native):
        k, f = cells.ss2_merge_np(*arrays(a), *arrays(b))
        assert [None if i < 0 else i for i in k.tolist()] == [got[0], got[2]] and f.tolist() == [got[1], got[3]]
        back = cells.ss2_merge_np(*arrays(b), *arrays(a))
        assert (back[0] == k).all() and (back[1] == f).all()
        assert sum(f) == sum(a[1::2]) + sum(b[1::2])


def test_ranked_fold_is_the_sequential_fold():
    rng = np.random.default_rng(3)
    family = HashFamily(2, 4)
    site, key, x = rng.integers(0, 3, 80), np.arange(80), rng.integers(1, 50, 80).astype(float)
    got = fold_ranked(site, key, x, family)
    have = {(s, r, c): (i1, f1, i2, f2) for s, r, c, i1, f1, i2, f2 in zip(*[got[n].tolist() for n in ("site", "row", "col", "i1", "f1", "i2", "f2")])}
    want = {}
    for n in sorted(range(80), key=lambda n: (-x[n], key[n])):
        for r, (a, b) in enumerate(family.params):
            want.setdefault((int(site[n]), r, (a * int(key[n]) + b) % 2147483647 % 4), []).append((int(key[n]), float(x[n])))
    for cell, arrivals in want.items():
        fold = _fold(*zip(*arrivals))
        assert have[cell] == tuple(-1 if v is None else v for v in fold.values())


def test_general_summaries():
    rng = random.Random(2)
    stream = [(rng.choice([1, 1, 1, 2, 2, *range(3, 30)]), 1.0) for _ in range(600)]
    exact = {}
    for k, x in stream:
        exact[k] = exact.get(k, 0) + x
    for counters in (4, 8, 16):
        parts = [sequential_space_saving(stream[a::3], counters) for a in range(3)]
        whole = sequential_space_saving(stream, counters)
        merged = ss_merge_k(ss_merge_k(parts[0], parts[1], counters), parts[2], counters)
        for summary in (whole, merged):
            assert len(summary) == counters and all(0 <= f - exact.get(k, 0) <= 600 / counters + 1e-9 for k, f in summary.items())
        assert sum(whole.values()) == 600


def test_hash_family():
    family = HashFamily(6, 16)
    assert family.params[:2] == [(1103515245, 12345), (48271, 11)] and len(set(family.params)) == 6
    assert HashFamily(3, 8, seed=1).params != HashFamily(3, 8, seed=2).params
