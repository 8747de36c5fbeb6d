"""Quality by nearest-neighbour voting in a latent-semantic space.

A document is a row of two hashed blocks, words and word shapes (character classes with runs collapsed, and how
near the last equal word is), in logarithmic counts weighted by inverse document frequency. The leading right
singular vectors of a bounded sample of labelled rows span the latent space; the same sample, projected, is the
set of labelled vectors. It is broadcast (at most `REFERENCES` x `DIMENSIONS` floats), every document's cosine
with every labelled vector is computed in matrix blocks, and the nearest vote with their similarity.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.llm.frames import held_out, table
from fadegossip.llm.words import WORD_BASE, Words, chunked, mix, span_hashes, strings

WORD_DIMS, SHAPE_DIMS = 1024, 512
#: Labelled rows that are fitted and broadcast at most (per label half of it), latent dimensions, and voters.
REFERENCES, DIMENSIONS, NEIGHBOURS = 4096, 48, 15
#: Documents of a block of cosines at most (a block has REFERENCES floats for each, their counts WORD_DIMS + SHAPE_DIMS).
BLOCK_ROWS = 256
#: Share of the shapes in the squared length of a row.
SHAPE_SHARE = 0.75
_CLASS = np.arange(256, dtype=np.uint64) + np.uint64(1000)  # punctuation stands for itself
_CLASS[97:123], _CLASS[65:91], _CLASS[48:58], _CLASS[128:] = 1, 2, 3, 1
_CLASS_CODE = mix(_CLASS)
_NEAR = (1, 2, 3, 4, 6, 8)


def rows_of(texts: pa.Array) -> np.ndarray:
    """Counts of hashed words and shapes of each text (float32, documents x WORD_DIMS + SHAPE_DIMS)."""
    words = Words(texts)
    n_docs, dims = len(words.count), WORD_DIMS + SHAPE_DIMS
    if not len(words.doc):
        return np.zeros((n_docs, dims), np.float32)
    names = words.hashes()
    code = _CLASS_CODE[words.body]
    keep = np.ones(len(code), bool)
    keep[1:] = code[1:] != code[:-1]
    keep[words.start] = True
    place = np.concatenate(([0], np.cumsum(keep)))
    shapes = span_hashes(code[keep], WORD_BASE, place[words.start], place[words.end])
    base = words.doc * dims
    flat = [base + (names % np.uint64(WORD_DIMS)).astype(np.int64), base + WORD_DIMS + (shapes % np.uint64(SHAPE_DIMS - 8)).astype(np.int64)]
    for i, gap in enumerate(_NEAR):
        again = np.flatnonzero((names[gap:] == names[:-gap]) & (words.doc[gap:] == words.doc[:-gap])) + gap
        flat.append(base[again] + dims - 8 + i)
    lines = np.bincount(np.repeat(np.arange(n_docs), np.diff(words.offsets)), words.body == 10, n_docs).astype(np.int64)
    out = np.bincount(np.concatenate(flat), minlength=n_docs * dims).reshape(n_docs, dims).astype(np.float32)
    out[:, dims - 1] = lines
    return out


class Space:
    """Inverse document frequencies, latent axes and the labelled vectors."""

    def __init__(self, counts: np.ndarray, labels: np.ndarray, dimensions: int = DIMENSIONS):
        seen = (counts > 0).sum(0)
        self.idf = np.log((1 + len(counts)) / (1 + seen)).astype(np.float32) + np.float32(1)
        x = self._weigh(counts)
        value, vector = np.linalg.eigh((x.T @ x).astype(np.float64))
        self.axes = np.ascontiguousarray(vector[:, ::-1][:, :dimensions], np.float32)
        self.vectors = self._unit(x @ self.axes)
        self.labels = labels.astype(np.float32)

    def _weigh(self, counts: np.ndarray) -> np.ndarray:
        total = np.maximum(counts[:, :WORD_DIMS].sum(1, keepdims=True), 1)
        x = np.log1p(counts * (1000 / total)) * self.idf
        out = np.zeros_like(x)
        for part, share in ((slice(0, WORD_DIMS), 1 - SHAPE_SHARE), (slice(WORD_DIMS, None), SHAPE_SHARE)):
            length = np.linalg.norm(x[:, part], axis=1, keepdims=True)
            out[:, part] = x[:, part] / np.maximum(length, 1e-9) * np.sqrt(share)
        return out.astype(np.float32)

    @staticmethod
    def _unit(x: np.ndarray) -> np.ndarray:
        return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)

    def scores(self, counts: np.ndarray, neighbours: int = NEIGHBOURS) -> np.ndarray:
        """Share of label 1 among the nearest labelled vectors, weighted by similarity; without a like one the overall share."""
        near = self._unit(self._weigh(counts) @ self.axes) @ self.vectors.T
        k = min(neighbours, near.shape[1])
        pick = np.argpartition(-near, k - 1, axis=1)[:, :k]
        weight = np.maximum(np.take_along_axis(near, pick, 1), 0).astype(np.float64) ** 4
        total = weight.sum(1)
        return np.where(total > 1e-12, (weight * self.labels[pick]).sum(1) / np.maximum(total, 1e-12), self.labels.mean())


def learnable(labels: DataFrame, column: str) -> DataFrame:
    """(doc_id, label), a row for each labelled document that may be learnt from: labels 0 or 1, not held out.

    Repeated rows of `labels` count once; of an id's conflicting labels the larger counts.
    """
    rows = labels.select("doc_id", F.col(column).cast("int").alias("label"))
    return rows.where(F.col("label").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out()).groupBy("doc_id").agg(F.max("label").alias("label"))


def labelled(docs: DataFrame, labels: DataFrame, column: str, bound: int) -> DataFrame:
    """(doc_id, label, text) of at most bound / 2 documents of each label, in the order of a hash of the id.

    Rows of docs that repeat an id are one document, that with the least text hash, so `bound` holds for rows too.
    """
    rows = learnable(labels, column)
    pick = lambda x: rows.where(F.col("label") == x).orderBy(F.xxhash64("doc_id"), "doc_id").limit(bound // 2)
    found = docs.select("doc_id", "text").join(F.broadcast(pick(0).union(pick(1))), "doc_id")
    least = found.groupBy("doc_id", "label").agg(F.min(F.struct(F.xxhash64("text").alias("h"), F.col("text"))).alias("x"))
    return least.select("doc_id", "label", "x.text")


def fit(docs: DataFrame, labels: DataFrame, bound: int = REFERENCES, dimensions: int = DIMENSIONS) -> Space | None:
    """The space of a bounded sample of labelled rows, in order of label and vector; None if no label can be learnt from.

    At most `bound` rows of counts come to the driver. Null texts count as empty. See labelled() for repeated rows.
    """

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "text", most=BLOCK_ROWS):
                counts = rows_of(strings(part.column("text")))
                yield pa.RecordBatch.from_arrays([part.column("label"), pa.array([x.tobytes() for x in counts.astype(np.float16)], pa.binary())], ["label", "x"])

    got = labelled(docs, labels, "quality", bound).select("label", "text").mapInArrow(run, "label int, x binary").collect()
    if not got:
        return None
    got = sorted(got)
    return Space(np.stack([np.frombuffer(x.x, np.float16) for x in got]).astype(np.float32), np.array([x.label for x in got]), dimensions)


def score(docs: DataFrame, space: Space | None, neighbours: int = NEIGHBOURS) -> DataFrame:
    """(doc_id, score), a row for each row of docs, whatever other columns it has.

    Null texts count as empty; empty texts, and any without a like vector, get the share of label 1. Repeated rows get
    equal scores. Among labelled vectors of equal similarity at the edge of the voters any may vote. A text of any
    length is counted whole, one at a time if it is longer than a chunk. Without a space every score is 0.5.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    if space is None:
        return docs.select("doc_id", F.lit(0.5).alias("score"))
    shared = docs.sparkSession.sparkContext.broadcast(space)

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "text", most=BLOCK_ROWS):
                found = shared.value.scores(rows_of(strings(part.column("text"))), neighbours)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(np.clip(found, 0, 1))], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, score double")


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, fit(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
