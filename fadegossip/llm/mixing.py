"""Mixing sources to target weights by entropy balancing.

Each source gets a token target. Among all rates between 0 and `MOST` per document whose expected tokens meet the
target, the one nearest to one copy each (in relative entropy of a bounded rate) is an exponential tilt by the
document's size: odds(r / MOST) = exp(multiplier * size / mean size). The multipliers maximise the concave dual;
sources don't share constraints, so its Hessian is diagonal and Newton's step is a division. Gradient and Hessian
are sums over the table of (source, size) counts, made anew in each iteration by the executors.

Rates become copies by a dithered threshold: copy c of a document has the position c - rate - dither in [0, 1), and
a source takes its copies in order of position as far as its target reaches. The cut is found by histograms of
the positions, narrowed three times; then smaller documents fill what is left. Nothing is sorted or gathered.

The dither is a hash of id, text and source. Rows that are equal in these are numbered and their dithers are spread
evenly from that hash by the golden ratio, so a source of equal rows meets its target as well as any other, and the
result, a multiset of rows, is the same however the rows are dealt.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fadegossip.llm.frames import cut, table

WEIGHTS, SHARE, MOST = (3.0, 1.0, 2.0), 1.5, 2
BINS, NARROWINGS, FILLS, STEPS = 1024, 3, 3, 60
#: Sources whose parameters are broadcast (under 200 bytes each).
BROADCAST_SOURCES = 50_000
#: Equal rows whose hashes are broadcast up to this number.
BROADCAST_REPEATS = 200_000
WORD = r"[^\x20\x09-\x0D]+"
GOLDEN = 0.6180339887498949


def size_of(text: Column) -> Column:
    """Words of a whole text (null: 0)."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def numbered(rows: DataFrame) -> DataFrame:
    """rows (h, v, ...), checkpointed, with `turn`: 0, 1, ... for the rows that are equal in h, in order of v.

    Rows of an (h, v) are counted within each partition first, so that one in a third of all rows makes no task
    larger than a partition; only numbers for each (h, v, partition) are then summed over the partitions.
    """
    rows = rows.withColumn("part", F.spark_partition_id()).withColumn("seq", F.monotonically_increasing_id())
    key = ["h", "v", "part"]
    own = F.row_number().over(Window.partitionBy(*key).orderBy("seq")) - 1
    counts = rows.groupBy(*key).agg(F.count(F.lit(1)).alias("n"))
    before = F.sum("n").over(Window.partitionBy("h").orderBy("v", "part").rowsBetween(Window.unboundedPreceding, -1))
    ahead = counts.withColumn("ahead", before).where("ahead > 0").select(*key, "ahead")  # hashes in several places
    return rows.withColumn("own", own).join(ahead, key, "left").withColumn("turn", F.col("own") + F.coalesce("ahead", F.lit(0))).drop("v", "part", "seq", "own", "ahead")


def dither(h: Column, turn: Column) -> Column:
    """In [0, 1), evenly spread over the turns of an h."""
    x = h.bitwiseAND(F.lit((1 << 52) - 1)) / float(1 << 52) + turn * GOLDEN
    return x - F.floor(x)


def targets(sizes: list[int], weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST) -> list[float]:
    """Token targets of sources in order: `share` of all tokens by weight, none above `most` times its own, the excess reshared."""
    out = [0.0] * len(sizes)
    left, total = list(range(len(sizes))), share * sum(sizes)
    weight = lambda i: weights[i % len(weights)]
    while left:
        each = total / sum(map(weight, left))
        over = [i for i in left if each * weight(i) > most * sizes[i]]
        if not over:
            for i in left:
                out[i] = each * weight(i)
            break
        for i in over:
            out[i] = float(most * sizes[i])
            total -= out[i]
        left = [i for i in left if i not in set(over)]
    return out


def _params(spark: SparkSession, rows: list[tuple], schema: str | T.StructType) -> DataFrame:
    """A row for each source, broadcast up to BROADCAST_SOURCES of them and joined by shuffle beyond."""
    df = spark.createDataFrame(rows, schema)
    return F.broadcast(df) if len(rows) <= BROADCAST_SOURCES else df


def multipliers(counts: DataFrame, goal: dict[int, float], total: dict[int, int], docs: dict[int, int], most: int = MOST) -> dict[int, float]:
    """Newton's method, kept inside a bracket, for all sources at once. counts: (k, size, n)."""
    spark = counts.sparkSession
    at = {k: 0.0 for k in goal if total[k] and 0 < goal[k] < most * total[k]}
    low, high = dict.fromkeys(at, -math.inf), dict.fromkeys(at, math.inf)
    live = set(at)
    for _ in range(STEPS):
        if not live:
            break
        params = _params(spark, [(k, at[k], total[k] / docs[k]) for k in live], "k int, lam double, mean double")
        x = F.col("size") / F.col("mean")
        z = F.col("lam") * x
        p = F.when(z > 700, F.lit(1.0)).when(z < -700, F.lit(0.0)).otherwise(1 / (1 + F.exp(-z)))
        tokens = F.col("size") * F.col("n") * most * p
        sums = counts.join(params, "k").groupBy("k").agg(F.sum(tokens).alias("t"), F.sum(tokens * (1 - p) * x).alias("slope")).collect()
        for row in sums:
            k, gap = row.k, row.t - goal[row.k]
            if abs(gap) <= 1e-9 * goal[k] + 1e-6:
                live.discard(k)
                continue
            if gap > 0:
                high[k] = at[k]
            else:
                low[k] = at[k]
            step = at[k] - gap / row.slope if row.slope > 0 else math.nan
            if not low[k] < step < high[k]:
                step = (low[k] + high[k]) / 2 if math.isfinite(low[k]) and math.isfinite(high[k]) else 2 * at[k] + (1 if gap < 0 else -1)
            if step == at[k]:
                live.discard(k)
            at[k] = step
    return at


def _cut_at(positions: DataFrame, room: DataFrame, low: float, high: float, wide=F.broadcast) -> DataFrame:
    """positions (k, t, size), room (k, room) -> (k, after, have): the t up to which sizes of k sum to its room at most, and that sum."""
    edge = room.select("k", "room", F.lit(low).alias("lo"), F.lit(high).alias("hi"), F.lit(0).cast("long").alias("have"))
    upto = Window.partitionBy("k").orderBy("bin")
    for _ in range(NARROWINGS):
        bins = F.floor((F.col("t") - F.col("lo")) / ((F.col("hi") - F.col("lo")) / BINS))
        sums = positions.join(wide(edge), "k").where("hi > lo").withColumn("bin", bins).where((F.col("bin") >= 0) & (F.col("bin") < BINS)).groupBy("k", "bin").agg(F.sum("size").alias("s"), F.first("room").alias("r"), F.first("have").alias("had"))
        summed = sums.withColumn("upto", F.col("had") + F.sum("s").over(upto))
        found = summed.groupBy("k").agg(F.min(F.when(F.col("upto") > F.col("r"), F.col("bin"))).alias("stop"), F.max(F.when(F.col("upto") <= F.col("r"), F.col("upto"))).alias("sum"))
        step = (F.col("hi") - F.col("lo")) / BINS
        edge = cut(
            edge.join(wide(found), "k", "left").select(
                "k", "room",
                F.when(F.col("stop").isNotNull(), F.col("lo") + step * F.col("stop")).otherwise(F.col("hi")).alias("lo"),
                F.when(F.col("stop").isNotNull(), F.greatest(F.col("lo") + step * (F.col("stop") + 1), F.col("lo") + step * F.col("stop") + 1e-12)).otherwise(F.col("hi")).alias("hi"),
                F.coalesce("sum", "have").alias("have"),
            )
        )
    return edge.select("k", F.col("lo").alias("after"), "have")


def _rows(docs: DataFrame) -> DataFrame:
    """(row, h, v, size, source) of every row: its columns as one struct, which keeps clashing names apart, a hash of id, text and source and one of the row."""
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    return rows.select("row", F.xxhash64("row.doc_id", "row.text", "row.source").alias("h"), F.xxhash64("row").alias("v"), size_of(F.col("row.text")).alias("size"), F.col("row.source").cast("string").alias("source"))


def _place(c: int) -> Column:
    return F.lit(float(c)) - F.col("rate") - F.col("u")


def _rated(rows: DataFrame, params: DataFrame, most: int) -> DataFrame:
    """rows (h, turn, size, source) with their source's parameters, rate and dither u."""
    z = F.col("lam") * F.col("size") / F.col("mean")
    rate = F.when((F.col("size") == 0) | (F.col("target") <= 0), F.lit(0.0)).when(F.col("lam").isNull(), F.lit(float(most))).when(z < -700, F.lit(0.0)).when(z > 700, F.lit(float(most))).otherwise(most / (1 + F.exp(-z)))
    found = rows.join(params, F.col("source").eqNullSafe(F.col("name"))).drop("name")
    return found.withColumn("rate", rate).withColumn("u", dither(F.col("h"), F.col("turn")))


def _copies(rated: DataFrame, most: int) -> DataFrame:
    """rated rows with `copies`; cuts and fits hold the turns of _cut_at of a row's source."""
    took = lambda c: F.coalesce(F.exists(F.arrays_zip("cuts", "fits"), lambda x: (_place(c) < x.cuts) & (F.col("size") <= x.fits)), F.lit(False)).cast("int")
    return rated.withColumn("copies", F.when((F.col("size") == 0) | (F.col("target") <= 0), F.lit(0)).otherwise(sum((took(c) for c in range(2, most + 1)), took(1))))


def balance(base: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """base: all rows (h, turn, size, source) -> a row for each source with all that decides its rows' copies.

    (k, name, source_size, target, lam, mean, cuts, fits). Sources are in order of code points, the null source last.
    """
    spark = base.sparkSession
    found = base.groupBy("source").agg(F.sum("size").alias("size"), F.sum((F.col("size") > 0).cast("int")).alias("n")).collect()  # a row for each source
    found.sort(key=lambda x: (x.source is None, (x.source or "").encode()))
    goals = targets([x.size for x in found], weights, share, most)
    goal, total, number = ({k: v for k, v in enumerate(vs)} for vs in (goals, [x.size for x in found], [x.n for x in found]))
    names = _params(spark, [(k, x.source) for k, x in enumerate(found)], T.StructType([T.StructField("k", T.IntegerType()), T.StructField("name", T.StringType())]))
    counts = cut(base.where("size > 0").join(names, F.col("source").eqNullSafe(F.col("name"))).groupBy("k", "size").agg(F.count(F.lit(1)).alias("n")))
    tilt = multipliers(counts, goal, total, number, most)
    params = [(k, x.source, x.size, goals[k], tilt.get(k), total[k] / number[k] if number[k] else 1.0) for k, x in enumerate(found)]
    schema = T.StructType([T.StructField("k", T.IntegerType()), T.StructField("name", T.StringType()), T.StructField("source_size", T.LongType()), *[T.StructField(c, T.DoubleType()) for c in ("target", "lam", "mean")]])
    known = spark.createDataFrame(params, schema)
    wide = F.broadcast if len(found) <= BROADCAST_SOURCES else lambda df: df
    rated = cut(_rated(base, wide(known), most).where("size > 0 and target > 0").select("k", "size", "rate", "u"))
    positions = rated.select("k", "size", F.explode(F.array(*[_place(c) for c in range(1, most + 1)])).alias("t"))
    state = known.where("target > 0").select("k", F.col("target").alias("room"), F.lit(float("-inf")).alias("low"), F.lit(float("inf")).alias("limit"), F.lit(None).cast("array<double>").alias("cuts"), F.lit(None).cast("array<double>").alias("fits"))
    for turn in range(FILLS + 1):
        rest = positions
        if turn and state.where("room >= 1").isEmpty():
            break
        if turn:  # what is not taken and fits
            rest = positions.join(wide(state), "k").where("t >= low and size <= limit").select("k", "t", "size")
        got = _cut_at(rest, state.where("room >= 1").select("k", "room"), -float(most), float(most) + 1, wide)
        grown = lambda xs, x: F.when(F.col("after").isNull(), F.col(xs)).otherwise(F.concat(F.coalesce(xs, F.array().cast("array<double>")), F.array(x)))
        left = F.col("room") - F.coalesce("have", F.lit(0))
        state = cut(
            state.join(wide(got), "k", "left").select(
                "k", left.alias("room"), F.greatest("low", F.coalesce("after", "low")).alias("low"), left.alias("limit"), grown("cuts", "after").alias("cuts"), grown("fits", "limit").alias("fits")
            )
        )
    return known.join(state.select("k", "cuts", "fits"), "k", "left")


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """(doc_id, source, size, source_size, target, rate, copies, taken), a row for each row of docs (doc_id, text, source, ...).

    A source without words has target 0 and takes nothing; null and empty texts get no copy. Repeated
    rows are separate documents with dithers of their own. Null ids are carried. An empty table gives an empty result.
    Other columns, whatever their names, change nothing.
    """
    base = cut(numbered(cut(_rows(docs).select("h", "v", "size", "source", F.col("row.doc_id").alias("doc_id")))))
    params = balance(base, weights, share, most)
    rated = _rated(base, F.broadcast(params) if params.count() <= BROADCAST_SOURCES else params, most)
    return _copies(rated, most).select("doc_id", "source", "size", "source_size", "target", "rate", "copies", (F.col("copies") * F.col("size")).cast("long").alias("taken"))


def mixed(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """The rows of docs, with all columns, each as often as mix() gives it copies.

    Copies follow from the row and its source's few numbers, so texts are not shuffled; only rows that are equal to
    others are checkpointed and numbered.
    """
    rows = _rows(docs)
    repeats = cut(rows.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("h"))
    repeats = F.broadcast(repeats) if repeats.count() <= BROADCAST_REPEATS else repeats
    once = rows.join(repeats, "h", "left_anti").withColumn("turn", F.lit(0).cast("long"))
    again = numbered(cut(rows.join(repeats, "h", "left_semi")))
    whole = once.select("row", "h", "size", "source", "turn").unionByName(again.select("row", "h", "size", "source", F.col("turn").cast("long").alias("turn")))
    params = balance(cut(numbered(cut(rows.select("h", "v", "size", "source")))), weights, share, most)
    found = _copies(_rated(whole, F.broadcast(params) if params.count() <= BROADCAST_SOURCES else params, most), most).where("copies > 0")
    return found.withColumn("copy", F.explode(F.sequence(F.lit(1), F.col("copies")))).select(*[F.col(f"row.`{c}`") for c in docs.columns])


def op10_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "rate", "copies")
