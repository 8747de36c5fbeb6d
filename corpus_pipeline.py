"""From raw documents to token ids in five stages, each reading what the one before wrote."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import wraps

from pyspark.sql import DataFrame, SparkSession

from fadegossip.llm import mixing, pieces, simhash, substrings, toxicity
from fadegossip.llm.frames import bound_batches, drop_shuffles, ensure_checkpoint_dir, remove, table


def _bounded(stage: Callable) -> Callable:
    """A stage whose batches for Python are bounded and whose shuffles go when they are read; each stage may run by itself."""

    @wraps(stage)
    def run_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
        bound_batches(spark)
        drop_shuffles(spark)
        return stage(spark, docs, sf_dir)

    return run_stage


@_bounded
def reject_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the toxicity score rejects go; the score is learnt from the labels of `sf_dir`.

    Null and empty texts score as clean. Repeated rows share their score; rows are kept or dropped whole, with nulls and
    columns of any name as they are. Without documents, or without toxic labels, nothing is rejected.
    """
    return toxicity.keep_clean(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")))


@_bounded
def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class of near copies stays (five-word shingles, similarity 0.8 or more, and what is reachable).

    That is the row with the least id, of equal ids the one with the least hash; equal rows leave one. Texts without a
    word are one class. Texts of one id are told apart. Rows without an id stay as they are, and stand for no class.
    """
    return simhash.keep_one(docs)


@_bounded
def remove_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words under a passage of 35 words that starts elsewhere too go, in every place; other texts stay as they are.

    Null texts become empty; repeated rows and columns of any name are carried; n_chars follows the text.
    """
    return substrings.without_repeats(docs)


@_bounded
def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as the mix takes it: null and empty texts never, a null source as a source of its own, the last."""
    return mixing.mixed(docs)


@_bounded
def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Piece ids of every row's whole text, and whether they decode to it; null texts as empty, repeated rows each."""
    return pieces.encode_checked(docs, pieces.load(spark))


STAGES = [
    ("toxicity", reject_toxic),
    ("near_duplicates", keep_one_of_near_copies),
    ("substrings", remove_repeated_passages),
    ("mixing", mix_sources),
    ("pieces", encode),
]

#: No stage but the mixing's size count is expressible in SQL; the tests hold the rows against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to the documents of `sf_dir`; intermediate tables go to the shared checkpoint folder.

    A table goes when the next one is written; the last is what the result reads, so it stays.
    """
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext._jsc.sc().getCheckpointDir().get()}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    before = None
    for name, stage in STAGES[:-1]:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
        if before:
            remove(spark, before)
        before = f"{folder}/{name}"
    return STAGES[-1][1](spark, docs, sf_dir)
