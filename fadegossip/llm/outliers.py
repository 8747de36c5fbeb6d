"""Quality rules: fixed limits, then robust multivariate outliers.

Every whole text gets counts (words, symbols, repeated lines, repeated windows of words) and from them a vector
of transformed statistics. Location and scatter are estimated by the minimum covariance determinant: of all subsets that
hold `SHARE` of a group's rows, the one whose scatter has the least determinant. Starts come from a sample of some
`START_ROWS` rows of a group (small subsets and coordinate medians, concentrated there, the best `KEPT` by determinant);
concentration steps over all rows then bring each down until its determinant no longer falls, the lower one is taken,
and one step with all rows that are no outliers to it (`INNER`) gives the final estimate.

A step is two passes over the table of statistics: a histogram of the distances, whose cut is exact (rows of the bin
in which the share ends, a 360th of a distance wide, share the weight that is left), and the moments of the rows up to it.
Nothing is sorted and no group is gathered. A scatter has a least scale per coordinate (a statistic that is nearly
always zero would otherwise reject any row where it is not) and is made consistent at the median.

Estimates are made per (language, source), per language and over all rows, in one go, and each is drawn towards the
next wider one as if that were `PRIOR_ROWS` rows more. So a group of any size is judged by the same rule: a large one
by itself, a tiny one mostly by its language.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fadegossip.llm.frames import cut, table
from fadegossip.llm.words import BYTE_BASE, BYTE_CODE, WORD_BASE, Words, chunked, mix, span_hashes, strings

COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "n_distinct", "n_upper", "n_digits", "n_chars")
#: Statistics and the least standard deviation each is given.
FLOORS = {"length": 0.6, "width": 0.12, "symbols": 0.4, "upper": 0.3, "digits": 1.2, "variety": 0.06, "repeats": 1.5}
#: Share of a group that is concentrated on, steps at most, and tail of the chi-square law that is rejected.
SHARE, STEPS, TAIL = 0.75, 25, 1e-4
#: Rows of a group that starts are drawn from (about), number of small subsets, and starts that are carried on over all rows.
START_ROWS, STARTS, KEPT = 600, 200, 2
#: Share of the chi-square law inside which rows take part in the last step; rows that a wider group's estimate counts for.
INNER, PRIOR_ROWS = 0.975, 28
#: Groups up to which their estimates are broadcast (about 500 bytes each); beyond, Spark joins by shuffle.
BROADCAST_GROUPS = 20_000
RUN = 8
_SYMBOL = np.isin(np.arange(256), list(b"#*$%&|<>"))
_UPPER = np.isin(np.arange(256), np.arange(65, 91))
_DIGIT = np.isin(np.arange(256), np.arange(48, 58))


def counts_of(texts: pa.Array) -> dict[str, np.ndarray]:
    """The counts of each text of a large_string array."""
    words = Words(texts)
    body, offsets, n_docs = words.body, words.offsets, len(words.count)
    between = lambda marks, at: np.diff(np.concatenate(([0], np.cumsum(marks, dtype=np.int64)))[at])
    character = (body & 0xC0) != 0x80
    in_word = np.zeros(len(body) + 1, np.int8)
    in_word[words.start] = 1
    np.add.at(in_word, words.end, -1)
    in_word = np.cumsum(in_word[:-1], dtype=np.int8).astype(bool)
    # lines: from behind a line feed (or the start of the text) to the next (or the end)
    feeds = np.flatnonzero(body == 10)
    begin = np.sort(np.concatenate((offsets[:-1], feeds + 1)), kind="stable")
    end = np.sort(np.concatenate((feeds, offsets[1:])), kind="stable")
    owner = np.repeat(np.arange(n_docs), between(body == 10, offsets) + 1)
    worded = np.searchsorted(words.start, end) > np.searchsorted(words.start, begin)
    names = span_hashes(BYTE_CODE[body], BYTE_BASE, begin[worded], end[worded])
    owner_w = owner[worded]
    distinct = np.unique(names + mix(owner_w.astype(np.uint64) + np.uint64(1)), return_index=True)[1]
    n_lines = np.bincount(owner_w, minlength=n_docs)
    dup = n_lines - np.bincount(owner_w[distinct], minlength=n_docs)
    hashed = words.hashes()
    doc_salt = mix(words.doc.astype(np.uint64) + np.uint64(1))
    kinds = np.unique(hashed + doc_salt, return_index=True)[1]
    at = words.starts_of(RUN)
    keys = span_hashes(hashed, WORD_BASE, at, at + RUN) + doc_salt[at]
    _, which, often = np.unique(keys, return_inverse=True, return_counts=True)
    again = at[often[which] > 1]
    depth = np.zeros(len(words.doc) + 1, np.int32)
    np.add.at(depth, again, 1)
    np.add.at(depth, again + RUN, -1)
    repeated = np.cumsum(depth[:-1]) > 0
    return {
        "n_words": words.count,
        "word_chars": between(character & in_word, offsets),
        "n_symbols": between(_SYMBOL[body], offsets),
        "n_dup_lines": dup,
        "n_repeat_words": np.bincount(words.doc[repeated], minlength=n_docs),
        "n_lines": n_lines,
        "n_distinct": np.bincount(words.doc[kinds], minlength=n_docs),
        "n_upper": between(_UPPER[body], offsets),
        "n_digits": between(_DIGIT[body], offsets),
        "n_chars": between(character, offsets),
    }


def counted(docs: DataFrame) -> DataFrame:
    """(doc_id, lang, source, counts), a row for each row of docs; null texts count as empty."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "text"):
                got = counts_of(strings(part.column("text")))
                yield pa.RecordBatch.from_arrays([part.column(c) for c in ("doc_id", "lang", "source")] + [pa.array(got[c].astype(np.int64)) for c in COUNTS], ["doc_id", "lang", "source", *COUNTS])

    rows = docs.select("doc_id", F.col("lang").cast("string").alias("lang"), F.col("source").cast("string").alias("source"), "text")
    return rows.mapInArrow(run, f"doc_id {kind}, lang string, source string, " + ", ".join(f"{c} long" for c in COUNTS))


def statistics() -> dict[str, Column]:
    c = F.col
    words = F.greatest(c("n_words"), F.lit(1)).cast("double")
    per_cent = lambda x, y: F.log(1 + 100 * x / y)
    return {
        "length": F.log(words + 1),
        "width": F.log(1 + c("word_chars") / words),
        "symbols": per_cent(c("n_symbols"), words),
        "upper": per_cent(c("n_upper"), F.greatest(c("word_chars"), F.lit(1))),
        "digits": per_cent(c("n_digits"), F.greatest(c("word_chars"), F.lit(1))),
        "variety": F.log(1.0 + c("n_distinct")) / F.log(1 + words),
        "repeats": per_cent(c("n_repeat_words"), words),
    }


def base_failed() -> Column:
    return (F.col("n_words") < 20) | (100 * F.col("n_repeat_words") > 30 * F.col("n_words"))


def chi_square(p: int, tail: float) -> float:
    """Quantile by the cube-root approximation."""
    from statistics import NormalDist

    z = NormalDist().inv_cdf(1 - tail)
    return p * (1 - 2 / (9 * p) + z * math.sqrt(2 / (9 * p))) ** 3


BINS_PER_OCTAVE = 256


def _distance(names: list[str]) -> Column:
    """Squared Mahalanobis distance of the row's statistics from the estimate joined to it (mean, inverse)."""
    p = len(names)
    gap = [F.col(n) - F.col("mean")[i] for i, n in enumerate(names)]
    total = F.lit(0.0)
    for i in range(p):
        total = total + F.col("inverse")[i * p + i] * gap[i] * gap[i]
        for j in range(i + 1, p):
            total = total + 2 * F.col("inverse")[i * p + j] * gap[i] * gap[j]
    return F.greatest(total, F.lit(0.0))


def moments(x: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Weighted mean and scatter."""
    mean = weight @ x / weight.sum()
    gap = x - mean
    return mean, (gap * weight[:, None]).T @ gap / weight.sum()


def nearest(d2: np.ndarray, n: np.ndarray, h: float) -> np.ndarray:
    """Weights, up to n each and h together, on the least distances."""
    order = np.argsort(d2, kind="stable")
    upto = np.cumsum(n[order])
    out = np.empty(len(n))
    out[order] = np.clip(h - (upto - n[order]), 0, n[order])
    return out


def _distances(x: np.ndarray, mean: np.ndarray, scatter: np.ndarray) -> np.ndarray:
    gap = x - mean
    return np.einsum("ij,ij->i", gap @ np.linalg.inv(scatter), gap)


def best_starts(x: np.ndarray, n: np.ndarray, floor2: np.ndarray, share: float = SHARE, starts: int = STARTS, kept: int = KEPT) -> list[tuple[float, np.ndarray, np.ndarray]]:
    """(log determinant, mean, scatter), lowest first, of rows x with weights n; the scatter includes floor2."""
    h, p = share * n.sum(), x.shape[1]
    rng = np.random.default_rng(len(x))
    order = np.lexsort(x.T)  # the same draws whatever the order of the rows
    x, n = x[order], n[order]
    middle = np.median(x, axis=0)
    first = [(middle, np.diag((1.4826 * np.median(np.abs(x - middle), axis=0)) ** 2) + floor2)]
    for _ in range(starts if len(x) > p + 1 else 0):
        pick = rng.choice(len(x), p + 1, replace=False)
        mean, scatter = moments(x[pick], np.ones(p + 1))
        first.append((mean, scatter + floor2))

    def steps(mean, scatter, most):
        low = np.inf
        for _ in range(most):
            mean, scatter = moments(x, nearest(_distances(x, mean, scatter), n, h))
            scatter = scatter + floor2
            now = np.linalg.slogdet(scatter)[1]
            if now >= low - 1e-10:
                break
            low = now
        return now, mean, scatter

    some = sorted((steps(m, s, 2) for m, s in first), key=lambda t: t[0])[: 10 * kept]
    found: list[tuple[float, np.ndarray, np.ndarray]] = []
    for t in sorted((steps(m, s, 100) for _, m, s in some), key=lambda t: t[0]):
        if all(abs(t[0] - u[0]) > 1e-7 for u in found) and len(found) < kept:
            found.append(t)
    return found


class _State:
    """Estimates of some groups, several (`cand`) for each, on the driver; tasks get it broadcast."""

    def __init__(self, rows: list, floor2: np.ndarray):
        """rows: (gid, mean, scatter without the floor)."""
        self.floor2, self.gid = floor2, np.array([r[0] for r in rows], np.int64)
        p = len(floor2)
        self.mean = np.array([r[1] for r in rows], float).reshape(-1, p)
        self.scatter = np.array([self._whole(np.array(r[2])) for r in rows]).reshape(-1, p, p)
        self.inverse = np.linalg.inv(self.scatter) if len(rows) else self.scatter
        self.logdet = np.full(len(rows), np.inf)
        self.done = np.zeros(len(rows), bool)

    def _whole(self, scatter: np.ndarray) -> np.ndarray:
        value, vector = np.linalg.eigh(scatter)  # eigenvalues below zero are rounding
        return (vector * np.maximum(value, 0)) @ vector.T + self.floor2

    def renew(self, at: int, sums: np.ndarray) -> None:
        """sums: weight, first and second moments about the present mean."""
        p = len(self.floor2)
        move, scatter = sums[1 : 1 + p] / sums[0], np.zeros((p, p))
        scatter[np.triu_indices(p)] = sums[1 + p :] / sums[0]
        scatter = self._whole(scatter + np.triu(scatter, 1).T - np.outer(move, move))
        self.mean[at] += move
        self.scatter[at], self.inverse[at] = scatter, np.linalg.inv(scatter)
        now = np.linalg.slogdet(scatter)[1]
        self.done[at] = now >= self.logdet[at] - 1e-6
        self.logdet[at] = now

    def take(self, at: np.ndarray) -> _State:
        out = _State([], self.floor2)
        for c in ("gid", "mean", "scatter", "inverse", "logdet", "done"):
            setattr(out, c, getattr(self, c)[at])
        return out


def _met(batches, keys: tuple[str, ...], names: list[str], state: _State):
    """(place in the state, rows' gaps from the mean, rows' bins) for every group of a batch."""
    order = np.argsort(state.gid, kind="stable")
    ordered = state.gid[order]
    for batch in batches:
        if not batch.num_rows:
            continue
        x = np.column_stack([np.asarray(batch.column(n), float) for n in names])
        for key in keys:
            gid = np.asarray(batch.column(key))
            turn = np.argsort(gid, kind="stable")
            cuts = np.concatenate(([0], np.flatnonzero(np.diff(gid[turn])) + 1, [len(gid)]))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
                rows = x[turn[a:b]]
                for k in range(*np.searchsorted(ordered, [gid[turn[a]], gid[turn[a]] + 1]).tolist()):
                    gap = rows - state.mean[order[k]]
                    d2 = np.einsum("ij,ij->i", gap @ state.inverse[order[k]], gap)
                    yield int(order[k]), gap, np.floor(np.log2(np.maximum(d2, 2.0**-20)) * BINS_PER_OCTAVE).astype(np.int64)


def _cuts(rows: DataFrame, keys: tuple[str, ...], names: list[str], state: _State, share: float) -> dict[str, np.ndarray]:
    """For each estimate the bin in which the share of its rows ends, how much of that bin counts, the median's bin, and the number of rows."""
    shared = rows.sparkSession.sparkContext.broadcast(state)

    def run(batches):
        held: list[np.ndarray] = []
        low, wide = -20 * BINS_PER_OCTAVE, 1 << 20

        def counted():
            code, n = np.unique(np.concatenate(held), return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(code // wide, pa.int32()), pa.array(code % wide + low, pa.int32()), pa.array(n, pa.int64())], ["at", "bin", "n"])

        for at, _, bins in _met(batches, keys, names, shared.value):
            held.append(at * wide + bins - low)
            if len(held) > 20_000:
                yield counted()
                held = []
        if held:
            yield counted()

    counts = rows.select(*keys, *names).mapInArrow(run, "at int, bin int, n long").groupBy("at", "bin").agg(F.sum("n").alias("n"))
    whole = Window.partitionBy("at")
    upto = counts.withColumn("upto", F.sum("n").over(whole.orderBy("bin"))).withColumn("total", F.sum("n").over(whole))
    left = (share * F.col("total") - (F.col("upto") - F.col("n"))) / F.col("n")
    ends = F.min(F.when(F.col("upto") >= share * F.col("total"), F.struct(F.col("bin"), left.alias("part")))).alias("x")
    found = upto.groupBy("at").agg(ends, F.min(F.when(F.col("upto") >= 0.5 * F.col("total"), F.col("bin"))).alias("median"), F.max("total").alias("total"))
    got = found.select("at", "x.bin", "x.part", "median", "total").collect()  # a row for each estimate
    out = {"bin": np.zeros(len(state.gid), np.int64), "part": np.zeros(len(state.gid)), "median": np.zeros(len(state.gid)), "total": np.zeros(len(state.gid), np.int64)}
    for r in got:
        out["bin"][r.at], out["part"][r.at], out["median"][r.at], out["total"][r.at] = r.bin, r.part, r.median, r.total
    return out


def _step(rows: DataFrame, keys: tuple[str, ...], names: list[str], state: _State, bins: np.ndarray, part: np.ndarray) -> None:
    """Renews every estimate by the rows up to its bin, those of the bin itself weighing `part`."""
    shared = rows.sparkSession.sparkContext.broadcast((state, bins, part))
    p = len(names)
    pairs = np.triu_indices(p)
    size = 1 + p + len(pairs[0])

    def run(batches):
        sums: dict[int, np.ndarray] = {}
        now, bins, part = shared.value
        for at, gap, own in _met(batches, keys, names, now):
            w = np.where(own < bins[at], 1.0, np.where(own == bins[at], part[at], 0.0))
            weighed = gap * w[:, None]
            sums[at] = sums.get(at, 0) + np.concatenate(([w.sum()], weighed.sum(0), (weighed.T @ gap)[pairs]))
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), *[pa.array([x[i] for x in sums.values()]) for i in range(size)]], ["at", *[f"m{i}" for i in range(size)]])

    found = rows.select(*keys, *names).mapInArrow(run, "at int, " + ", ".join(f"m{i} double" for i in range(size)))
    for r in found.groupBy("at").agg(*[F.sum(f"m{i}").alias(f"m{i}") for i in range(size)]).collect():  # a row for each estimate
        state.renew(r[0], np.array(r[1:], float))


def _scale(cuts: dict[str, np.ndarray], p: int) -> np.ndarray:
    """How far the median distance is beyond that of the chi-square law."""
    return np.maximum(2.0 ** ((cuts["median"] + 0.5) / BINS_PER_OCTAVE) / chi_square(p, 0.5), 1.0)


def estimate(rows: DataFrame, names: list[str], keys: tuple[str, ...] = ("gid",), share: float = SHARE, steps: int = STEPS, groups_at_once: int = BROADCAST_GROUPS) -> DataFrame:
    """rows (keys: long numbers of the groups a row is in, statistics) -> (gid, n, mean, scatter, scale, logdet) of every group.

    The scatter includes the floors; scale brings the median distance down to that of the chi-square law, never up;
    logdet is that of the subset, before the last step. Up to `groups_at_once` groups are estimated side by side (their few
    numbers are on the driver and broadcast), more of them in several turns.
    """
    spark, p = rows.sparkSession, len(names)
    floor2 = np.diag([FLOORS[n] ** 2 for n in names])
    long = rows.select(F.explode(F.array(*keys)).alias("gid"), F.xxhash64(*names).alias("h"), *names)
    sizes = cut(long.groupBy("gid").agg(F.count(F.lit(1)).alias("size"), F.min(F.struct("h", *names)).alias("least")))
    groups = sizes.count()
    some = F.broadcast(sizes.select("gid", "size")) if groups <= groups_at_once else sizes.select("gid", "size")
    # equal rows are drawn or left together, but are one weighted row
    drawn = long.join(some, "gid").where(F.pmod("h", F.lit(1 << 30)) < F.lit(float(START_ROWS << 30)) / F.col("size"))
    drawn = drawn.groupBy("gid", *names).agg(F.count(F.lit(1)).cast("double").alias("n"))
    # a group of which no hash is drawn starts from the row of the least hash
    drawn = drawn.unionByName(sizes.select("gid", *[f"least.{n}" for n in names], F.lit(0.0).alias("n")))

    def begin(members):
        x = np.column_stack([np.asarray(members.column(n), float) for n in names])
        n = np.asarray(members.column("n"))
        real = n > 0
        found = best_starts(x[real], n[real], floor2, share) if real.any() else [(np.inf, x[0], floor2)]
        gid = members.column("gid")[0].as_py()
        return pa.table({"gid": pa.array([gid] * len(found), pa.int64()), "mean": pa.array([m.tolist() for _, m, _ in found], pa.list_(pa.float64())), "scatter": pa.array([(s - floor2).ravel().tolist() for _, _, s in found], pa.list_(pa.float64()))})

    starts = cut(drawn.groupBy("gid").applyInArrow(begin, "gid long, mean array<double>, scatter array<double>"))
    turns = max(1, -(-groups // groups_at_once))
    out = None
    for turn in range(turns):
        got = starts.where(F.pmod("gid", F.lit(turns)) == turn).orderBy("gid", "mean").collect()  # at most KEPT rows for each group of a turn
        state = _State([(r.gid, r.mean, np.array(r.scatter).reshape(p, p)) for r in got], floor2)
        for _ in range(steps):
            at = np.flatnonzero(~state.done)
            if not len(at):
                break
            live = state.take(at)
            cuts = _cuts(rows, keys, names, live, share)
            _step(rows, keys, names, live, cuts["bin"], cuts["part"])
            for c in ("mean", "scatter", "inverse", "logdet", "done"):
                getattr(state, c)[at] = getattr(live, c)
        best = state.take(np.array([min(np.flatnonzero(state.gid == g), key=lambda k: state.logdet[k]) for g in np.unique(state.gid)], np.int64))
        logdet = best.logdet.copy()
        inner = chi_square(p, 1 - INNER) * _scale(_cuts(rows, keys, names, best, 0.5), p)
        _step(rows, keys, names, best, np.floor(np.log2(inner) * BINS_PER_OCTAVE).astype(np.int64), np.ones(len(inner)))
        last = _cuts(rows, keys, names, best, 0.5)
        found = zip(best.gid.tolist(), last["total"].tolist(), best.mean.tolist(), best.scatter.reshape(-1, p * p).tolist(), _scale(last, p).tolist(), logdet.tolist())
        one = spark.createDataFrame(list(found), "gid long, n long, mean array<double>, scatter array<double>, scale double, logdet double")
        out = one if out is None else out.union(cut(one))
    return out


def drawn_to(n: float, own: tuple, wider: tuple) -> tuple[np.ndarray, np.ndarray, float]:
    """(mean, scatter, scale) of n rows, drawn towards a wider group's as if that were PRIOR_ROWS rows."""
    k = PRIOR_ROWS
    (m, s, c), (m0, s0, c0) = own, wider
    gap = m - m0
    return (n * m + k * m0) / (n + k), (n * s + k * s0 + n * k / (n + k) * np.outer(gap, gap)) / (n + k), float(np.exp((n * np.log(c) + k * np.log(c0)) / (n + k)))


def judge(docs: DataFrame, tail: float = TAIL) -> DataFrame:
    """(doc_id, counts, base_failed, distance, kept) of every row of docs (doc_id, text, lang, source).

    Null languages and sources are groups like any other; null texts count as empty, texts of any length are counted
    whole, repeated rows are rows of their own, and other columns of any name change nothing. distance is null where the
    fixed limits fail. An empty table gives an empty result.
    """
    names = list(statistics())
    p = len(names)
    base = cut(counted(docs).withColumn("base_failed", base_failed()))
    tested = base.where(~F.col("base_failed"))
    keys = {"own": F.xxhash64(F.lit(1), F.col("lang").isNull(), F.coalesce("lang", F.lit("")), F.col("source").isNull(), F.coalesce("source", F.lit(""))), "wide": F.xxhash64(F.lit(2), F.col("lang").isNull(), F.coalesce("lang", F.lit(""))), "whole": F.xxhash64(F.lit(3))}
    placed = cut(tested.select("doc_id", *COUNTS, "base_failed", *[x.alias(n) for n, x in keys.items()], *[x.alias(n) for n, x in statistics().items()]))
    named = placed.select(*keys).distinct()
    found = estimate(placed.select(*keys, *names), names, tuple(keys))
    joined = named
    for key in keys:
        joined = joined.join(found.select(F.col("gid").alias(key), F.struct("n", "mean", "scatter", "scale").alias(f"{key}_")), key)

    def draw(batches):
        for batch in batches:
            gids, means, inverses, scales = [], [], [], []
            for row in batch.to_pylist():
                a, b, c = ((row[x]["n"], (np.array(row[x]["mean"]), np.array(row[x]["scatter"]).reshape(p, p), row[x]["scale"])) for x in ("own_", "wide_", "whole_"))
                mean, scatter, scale = drawn_to(*a, drawn_to(*b, c[1]))
                gids.append(row["own"])
                means.append(mean.tolist())
                inverses.append(np.linalg.inv(scatter).ravel().tolist())
                scales.append(scale)
            yield pa.RecordBatch.from_arrays([pa.array(gids, pa.int64()), pa.array(means, pa.list_(pa.float64())), pa.array(inverses, pa.list_(pa.float64())), pa.array(scales, pa.float64())], ["gid", "mean", "inverse", "scale"])

    final = cut(joined.mapInArrow(draw, "gid long, mean array<double>, inverse array<double>, scale double"))
    limit = chi_square(p, tail)
    near = placed.join(F.broadcast(final) if final.count() <= BROADCAST_GROUPS else final, F.col("own") == F.col("gid"))
    verdict = near.withColumn("distance", _distance(names) / F.col("scale")).select("doc_id", *COUNTS, "base_failed", "distance", (F.col("distance") <= limit).alias("kept"))
    return verdict.union(base.where("base_failed").select("doc_id", *COUNTS, "base_failed", F.lit(None).cast("double"), F.lit(False)))


def op9_outliers(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = judge(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "distance")
