"""SimHash near-duplicates found by covering locality-sensitive hashing.

Fingerprint bits are majority votes of XXH64 shingle hashes. For radius r, every bit position gets a vector of
r+1 bits; for each of the 2**(r+1)-1 non-zero vectors v a table keeps the bits whose vector has product one with v
(over GF(2)). The at most r positions in which two close fingerprints differ span less than the whole space, so
some v has product zero with all of them; the table of v keeps the bits of product one, on which the pair agrees. No pair within the
radius can be missed, whatever the data.

Only distinct fingerprints enter the tables. A bucket yields a spanning forest of its links, not its pairs; a
bucket over `BLOCK` fingerprints is cut into blocks and every two blocks meet in a task of their own, which is
exact. Components are found by star contraction, and documents get their class by a join on the fingerprint.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.llm.components import components
from fadegossip.llm.frames import cut, shuffle_width, table
from fadegossip.llm.words import Words, chunked, strings, xxh64

SHINGLE_WORDS, RADIUS, SEED = 4, 4, 42
#: Fingerprints of a bucket that one task compares with each other.
BLOCK = 4096
#: Tasks over which the fingerprints of a class are dealt.
SALTS = 16


def bit_vectors(radius: int = RADIUS, bits: int = 64, seed: int = 7) -> list[int]:
    """A vector of radius+1 bits for each position, spread evenly over all vectors and shuffled."""
    rng, size = np.random.default_rng(seed), 2 ** (radius + 1)
    return [int(x) for x in rng.permutation(np.arange(bits) % size)]


def masks(radius: int = RADIUS, bits: int = 64) -> list[int]:
    """For each table the bits it keeps."""
    vectors = bit_vectors(radius, bits)
    return [sum(1 << i for i, m in enumerate(vectors) if bin(m & v).count("1") % 2) for v in range(1, 2 ** (radius + 1))]


def fingerprints_of(texts: pa.Array, k: int = SHINGLE_WORDS) -> np.ndarray:
    """A 64-bit fingerprint for each text of a large_string array."""
    words = Words(texts, lower=True)
    body, offsets = words.joined()
    n_docs = len(words.count)
    # byte ranges of the words in the joined text
    length = words.end - words.start
    stop = np.cumsum(length + 1)
    start = stop - length - 1
    skipped = np.cumsum(words.count > 0) - (words.count > 0)
    start = start - skipped[words.doc]
    end = start + length
    at = words.starts_of(k)
    short = np.flatnonzero((words.count > 0) & (words.count < k))
    begin = np.concatenate((start[at], offsets[short]))
    until = np.concatenate((end[at + k - 1], offsets[short + 1]))
    doc = np.concatenate((words.doc[at], short))
    out = np.zeros(n_docs, np.uint64)
    if not len(begin):
        return out
    hashed = xxh64(body, begin, until, SEED)
    order = np.argsort(doc, kind="stable")
    hashed, doc = hashed[order], doc[order]
    bits = np.unpackbits(hashed.astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
    first = np.flatnonzero(np.concatenate(([True], doc[1:] != doc[:-1])))
    votes = np.add.reduceat(bits, first, axis=0, dtype=np.int32)
    total = np.diff(np.concatenate((first, [len(doc)])))
    out[doc[first]] = np.packbits(2 * votes > total[:, None], axis=1).view(">u8")[:, 0]
    return out


def fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp): fp is the fingerprint as a signed long. Null and empty texts get zero."""

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "t"):
                fp = fingerprints_of(strings(part.column("t"))).view(np.int64)
                yield pa.RecordBatch.from_arrays([part.column("i"), pa.array(fp)], ["i", "fp"])

    kind = docs.schema[id_col].dataType.simpleString()
    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(run, f"i {kind}, fp long").withColumnRenamed("i", id_col)


def close(left: np.ndarray, right: np.ndarray, radius: int) -> np.ndarray:
    return np.bitwise_count(left[:, None] ^ right[None, :]) <= radius


def forest(fps: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Links that span the components of a set of fingerprints: every node is compared once with those not yet reached."""
    left = np.sort(fps)
    out_a, out_b = [], []
    while len(left):
        root, left = left[:1], left[1:]
        front = root
        while len(front) and len(left):
            hit = np.zeros(len(left), bool)
            for at in range(0, len(front), 256):
                hit |= close(front[at : at + 256], left, radius).any(0)
            front, left = left[hit], left[~hit]
            out_a.append(front)
            out_b.append(np.repeat(root, len(front)))
    joined = lambda x: np.concatenate(x) if x else np.zeros(0, np.uint64)
    return joined(out_a), joined(out_b)


def _runs(batches, most: int):
    """Runs of equal (t, key) from sorted batches of (t, key, fp); a run may go over batch ends.

    A run of more than `most` rows is left to the blocks and not kept: memory holds a batch and one run.
    """
    held: tuple[int, int] | None = None
    parts: list[np.ndarray] = []
    for batch in batches:
        t, key, fp = (np.asarray(batch.column(x)) for x in ("t", "key", "fp"))
        if not len(t):
            continue
        cuts = np.flatnonzero((t[1:] != t[:-1]) | (key[1:] != key[:-1])) + 1
        bounds = np.concatenate(([0], cuts, [len(t)]))
        if held is not None and held != (t[0], key[0]):
            yield np.concatenate(parts)
            parts = []
        size = np.diff(bounds)
        for i in np.flatnonzero((size > 1) | (np.arange(len(size)) == 0) | (np.arange(len(size)) == len(size) - 1)).tolist():
            run = fp[bounds[i] : bounds[i + 1]]
            if i == 0 and parts:
                run = np.concatenate([*parts, run])[: most + 1]
                parts = []
            if i == len(size) - 1:
                parts = [run]
            else:
                yield run
        held = (t[-1], key[-1])
    if parts:
        yield np.concatenate(parts)


def _batch(a: list, b: list) -> pa.RecordBatch:
    one = lambda x: pa.array(np.concatenate(x).view(np.int64) if x else np.zeros(0, np.int64))
    return pa.RecordBatch.from_arrays([one(a), one(b)], ["a", "b"])


def links(fps: DataFrame, radius: int = RADIUS, block: int = BLOCK) -> DataFrame:
    """fps: distinct (fp). Links (a, b) that connect the same fingerprints as all pairs within the radius do."""
    width = shuffle_width(fps.sparkSession)
    tables = F.explode(F.array(*[F.struct(F.lit(i).alias("t"), F.col("fp").bitwiseAND(F.lit(m - (1 << 64) if m >> 63 else m)).alias("key")) for i, m in enumerate(masks(radius))])).alias("x")
    rows = fps.select("fp", tables).select("x.t", "x.key", "fp")
    big = rows.groupBy("t", "key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > block)

    def within(batches):
        a, b, held = [], [], 0
        for run in _runs(batches, block):
            if 1 < len(run) <= block:
                x, y = forest(run.view(np.uint64), radius)
                if len(x):
                    a.append(x)
                    b.append(y)
                    held += len(x)
                    if held > 50_000:
                        yield _batch(a, b)
                        a, b, held = [], [], 0
        yield _batch(a, b)

    few = rows.repartition(width, "t", "key").sortWithinPartitions("t", "key").mapInArrow(within, "a long, b long")

    def across(members):
        x, y = forest(np.unique(np.asarray(members.column("fp")).view(np.uint64)), radius)
        return pa.Table.from_batches([_batch([x] if len(x) else [], [y] if len(y) else [])])

    parts = F.ceil(F.col("n") / block)
    own = F.pmod(F.xxhash64("fp"), parts)
    other = F.explode(F.sequence(F.lit(0).cast("long"), parts - 1))
    many = (
        rows.join(big, ["t", "key"]).select("t", "key", "fp", own.alias("own"), other.alias("other"))
        .select("t", "key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "fp")
        .groupBy("t", "key", "i", "j").applyInArrow(across, "a long, b long")
    )
    return few.union(many).distinct()


def near_duplicates(docs: DataFrame, radius: int = RADIUS, block: int = BLOCK) -> DataFrame:
    """(doc_id, fp, component_id): documents linked by fingerprints within the radius share the least doc_id reachable.

    Documents without a word have fingerprint zero and are linked like any other. Repeated rows keep their own row.
    A null doc_id gets a class as well; it is null only where the whole class has no id.
    """
    marked = cut(fingerprint(docs.select("doc_id", "text")))
    fps = cut(marked.groupBy("fp").agg(F.min("doc_id").alias("least")))
    roots = components(links(fps.select("fp"), radius, block))
    linked = cut(fps.join(roots, fps.fp == roots.node).select("fp", "least", "root"))
    # a class of many fingerprints is dealt to several tasks
    named = linked.groupBy("root").agg(F.min("least").alias("component_id")).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    own = linked.withColumn("salt", F.pmod(F.xxhash64("fp"), F.lit(SALTS)).cast("int")).join(named, ["root", "salt"]).select("fp", "component_id")
    alone = fps.join(linked.select("fp"), "fp", "left_anti").select("fp", F.col("least").alias("component_id"))
    return marked.join(cut(own.union(alone)), "fp").select("doc_id", "fp", "component_id")


def op3_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame) -> DataFrame:
    """The rows of `docs` of which each class of near copies keeps one: that with the least id, then the least hash.

    Texts are fingerprinted on shingles of five words and linked by the same tables as in `near_duplicates`; links are
    then checked on the shingles, which also find what is similar enough but further apart than the radius (`shingles`).
    A row without an id can't stand for a class and stays as it is.
    """
    from fadegossip.llm import shingles

    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("whole"))  # one name, whatever docs has
    hashed = rows.select("whole", F.xxhash64("whole").alias("row"))
    found = shingles.near_copies(hashed.select(F.col("whole.doc_id").alias("id"), "row", F.col("whole.text").alias("text")))
    least = found.where(F.col("id").isNotNull()).groupBy("root").agg(F.min(F.struct("id", "row")).alias("x")).select("x.id", F.col("x.row").alias("own"))
    kept = hashed.join(least, (F.col("whole.doc_id") == F.col("id")) & (F.col("row") == F.col("own"))).dropDuplicates(["id", "own"])
    return kept.select(*[F.col(f"whole.`{c}`") for c in docs.columns]).union(docs.where(F.col("doc_id").isNull()))
