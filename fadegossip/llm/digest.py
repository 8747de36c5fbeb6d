"""Quartile bucket digests of documents.

Byte triplets from a sliding window of five bytes are hashed into `BUCKETS` counters. Three quartiles of the
counters are found, and a counter is encoded by the quarter it lies in (two bits). The digest is a version byte,
the logarithmic length, the ratios of the quartiles, a checksum of the bytes and the coded counters, in hex.

The difference score adds a bounded penalty for length and quartile ratios to the distance of the codes (0, 1, 2
and `FAR_CODES` for codes three apart); likeness is one minus the score over its greatest possible value.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.llm.frames import cut, shuffle_width, table
from fadegossip.llm.words import chunked, mix, raw, strings

BUCKETS = 256
#: Offsets of the two partners of the first byte of a triplet within the window of five bytes.
TRIPLETS = ((1, 2), (1, 3), (2, 3), (2, 4))
FAR_CODES, LENGTH_CAP, RATIO_CAP = 6, 12, 7
GREATEST = FAR_CODES * BUCKETS + LENGTH_CAP + 2 * RATIO_CAP + 1
_PAIR = mix(np.arange(1 << 16, dtype=np.uint64) + np.uint64(1))
#: Of each triplet kind, the hash of the two partners and that of the first byte; their XOR is the bucket.
_PAIRS = [(mix(_PAIR + np.uint64(salt)) >> np.uint64(56)).astype(np.uint8) for salt in range(len(TRIPLETS))]
_BYTES = [(mix(_PAIR[:256] + np.uint64(99 + salt)) >> np.uint64(56)).astype(np.uint8) for salt in range(len(TRIPLETS))]


def digests(texts: pa.Array) -> np.ndarray:
    """One row of BUCKETS + 4 bytes for each text: length code, two ratios, checksum, then the codes."""
    body, offsets = raw(texts)
    n_docs, size = len(offsets) - 1, np.diff(offsets)
    counts = np.zeros(n_docs * BUCKETS, np.int64)
    if len(body) >= 5:
        doc = np.repeat(np.arange(n_docs) * BUCKETS, size)
        base = doc[:-4]
        if not (inside := doc[4:] == base).all():
            base = np.where(inside, base, n_docs * BUCKETS)  # windows over a document's end count in a spare row
        counts = np.zeros((n_docs + 1) * BUCKETS, np.int64)
        n, wide = len(base), body.astype(np.uint16)
        first = body[:n]
        for (i, j), pairs, bytes_ in zip(TRIPLETS, _PAIRS, _BYTES):
            bucket = pairs[(wide[i : n + i] << 8) | wide[j : n + j]] ^ bytes_[first]
            counts += np.bincount(base + bucket, minlength=len(counts))
        counts = counts[: n_docs * BUCKETS]
    counts = counts.reshape(n_docs, BUCKETS)
    ordered = np.sort(counts, axis=1)
    q = ordered[:, [BUCKETS // 4 - 1, BUCKETS // 2 - 1, 3 * BUCKETS // 4 - 1]]
    code = (counts > q[:, :1]).astype(np.uint8) + (counts > q[:, 1:2]) + (counts > q[:, 2:])
    top = np.maximum(q[:, 2], 1)
    head = np.zeros((n_docs, 4), np.uint8)
    head[:, 0] = np.minimum(np.round(8 * np.log2(1 + size)), 255)
    head[:, 1], head[:, 2] = q[:, 0] * 100 // top % 16, q[:, 1] * 100 // top % 16
    sums = np.zeros(len(body) + 1, np.uint64)
    np.cumsum(_PAIR[body.astype(np.int64)], out=sums[1:])
    head[:, 3] = mix(sums[offsets[1:]] - sums[offsets[:-1]]) >> np.uint64(56)
    return np.hstack([head, code])


def as_hex(rows: np.ndarray) -> list[str]:
    code = rows[:, 4:].reshape(len(rows), -1, 4)
    packed = code[:, :, 0] | code[:, :, 1] << 2 | code[:, :, 2] << 4 | code[:, :, 3] << 6
    both = np.hstack([rows[:, :4], packed]).astype(np.uint8)
    return [x.tobytes().hex() for x in both]


def from_hex(digest: str) -> np.ndarray:
    b = np.frombuffer(bytes.fromhex(digest), np.uint8)
    code = np.stack([b[4:] >> s & 3 for s in (0, 2, 4, 6)], axis=1).ravel()
    return np.concatenate([b[:4], code])


def likeness(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """1 for equal rows, else less, never below 0."""
    a, b = a.astype(np.int64), b.astype(np.int64)
    apart = np.abs(a[:, 4:] - b[:, 4:])
    score = np.where(apart == 3, FAR_CODES, apart).sum(1)
    score += np.minimum(np.abs(a[:, 0] - b[:, 0]), LENGTH_CAP)
    for i in (1, 2):
        gap = np.abs(a[:, i] - b[:, i])
        score += np.minimum(np.minimum(gap, 16 - gap), RATIO_CAP)
    score += a[:, 3] != b[:, 3]
    return 1 - score / GREATEST


def fingerprint(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, digest in hex) of every row; null texts count as empty."""
    kind = docs.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "t"):
                yield pa.RecordBatch.from_arrays([part.column("i"), pa.array(as_hex(digests(strings(part.column("t")))))], ["i", "d"])

    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(run, f"i {kind}, d string").toDF(id_col, "fingerprint")


def _edited(texts: list[str], nexts: list[str]) -> list[str]:
    out = []
    for a, b in zip(texts, nexts):
        k = len(a) // 2
        out.append(a[: len(a) - k] + b[:k])
    return out


_OUT = "doc_id {kind}, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"


def _compare(ids: pa.Array, texts: pa.Array, nexts: pa.Array, shifted: bool = False) -> pa.RecordBatch:
    """shifted: nexts are the texts from the second on, and one more."""
    edited = pa.array(_edited(texts.to_pylist(), nexts.to_pylist()), pa.large_string())
    own, changed = digests(texts), digests(edited)
    other = np.vstack([own[1:], digests(nexts.slice(len(nexts) - 1))]) if shifted else digests(nexts)
    body, offsets = raw(edited)
    data = body.tobytes()
    shas = [hashlib.sha256(data[a:b]).hexdigest() for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())]
    return pa.RecordBatch.from_arrays(
        [ids, pc.utf8_length(texts).cast(pa.int64()), pa.array(shas), pa.array(as_hex(own)), pa.array(as_hex(changed)), pa.array(likeness(own, changed)), pa.array(likeness(own, other))],
        ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
    )


def compare_with_next(docs: DataFrame) -> DataFrame:
    """Every document against its edited text and against the next document by id (after the last: the first).

    Rows are range-partitioned by id and sorted; within a partition the next row is at hand. The last row of each
    partition and the first of the next are a row or two per partition; those meet in a second small step. Rows
    that repeat an id are ordered by text, null ids come first, null texts count as empty.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    width = shuffle_width(docs.sparkSession)
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), F.monotonically_increasing_id().alias("seq"))
    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64("text"), F.col("seq")]  # the last splits rows that repeat
    ordered = rows.repartitionByRange(width, *order).sortWithinPartitions(*order).select("doc_id", "text", F.spark_partition_id().alias("part"))
    schema = _OUT.format(kind=kind) + ", part int, first_text string, last_text string"

    def within(batches):
        first = last = None  # the partition's first text; the row that waits for its next

        for batch in batches:
            for piece in chunked(batch, "text"):
                ids, texts, part = piece.column("doc_id"), strings(piece.column("text")), piece.column("part")[0].as_py()
                if first is None:
                    first = texts[0].as_py()
                if last is not None:
                    ids = pa.concat_arrays([last[0], ids])
                    texts = pa.concat_arrays([last[1], texts])
                last = ids.slice(len(ids) - 1), texts.slice(len(texts) - 1), part
                if len(ids) > 1:
                    done = _compare(ids.slice(0, len(ids) - 1), texts.slice(0, len(ids) - 1), texts.slice(1), True)
                    n = done.num_rows
                    yield pa.RecordBatch.from_arrays([*done.columns, pa.nulls(n, pa.int32()), pa.nulls(n, pa.string()), pa.nulls(n, pa.string())], [*done.schema.names, "part", "first_text", "last_text"])
        if last is not None:
            kinds = (pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64())
            yield pa.RecordBatch.from_arrays([last[0], *[pa.nulls(1, k) for k in kinds], pa.array([last[2]], pa.int32()), pa.array([first], pa.string()), last[1].cast(pa.string())], ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next", "part", "first_text", "last_text"])

    found = cut(ordered.mapInArrow(within, schema))
    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    ends = found.where(F.col("part").isNotNull()).select("part", "doc_id", "first_text", "last_text")
    parts = sorted(x.part for x in ends.select("part").collect())  # a number for each shuffle partition
    if not parts:
        return found.select(names)
    after = F.create_map(*[F.lit(x) for a, b in zip(parts, parts[1:] + parts[:1]) for x in (a, b)])
    pairs = ends.select("doc_id", F.col("last_text").alias("text"), after[F.col("part")].alias("to")).join(ends.select(F.col("part").alias("to"), F.col("first_text").alias("next")), "to")

    def across(batches):
        for batch in batches:
            if batch.num_rows:
                yield _compare(batch.column("doc_id"), strings(batch.column("text")), strings(batch.column("next")))

    return found.where(F.col("part").isNull()).select(names).union(pairs.select("doc_id", "text", "next").mapInArrow(across, _OUT.format(kind=kind)))


def op5_digest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compare_with_next(table(spark, sf_dir, "documents"))
