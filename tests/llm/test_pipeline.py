"""The pipeline on whole documents, and every registered query's columns."""

import collections
import glob
import hashlib
import time

import duckdb
import pyarrow as pa
import pytest
from test_shingles import slow_roots

import corpus_pipeline
from fadegossip.llm import mixing, queries, substrings, toxicity
from fadegossip.llm.frames import table


def test_stages_take_effect(spark, small, tmp_path):
    docs = table(spark, small, "documents")
    before = docs
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, small).write.parquet(str(tmp_path / name))
        got = spark.read.parquet(str(tmp_path / name))
        if name == "toxicity":
            lexicon = toxicity.fit(docs, table(spark, small, "labels"))
            want = {r.doc_id for r in toxicity.score(docs, lexicon).where("score < 0.5").collect()}
            assert {r.doc_id for r in got.collect()} == want
        elif name == "near_duplicates":
            texts = [(r.doc_id, r.text) for r in docs.orderBy("doc_id").collect()]
            assert sorted(r.doc_id for r in got.collect()) == sorted({texts[i][0] for i in slow_roots([t for _, t in texts])})
        elif name == "substrings":
            removed = {r.doc_id: r for r in substrings.repeated_spans(docs).collect()}
            old = {r.doc_id: r.text for r in docs.collect()}
            for r in got.collect():
                assert r.text == (removed[r.doc_id].kept_text if removed[r.doc_id].n_removed else old[r.doc_id])
        elif name == "mixing":
            copies = {r.doc_id: r.copies for r in mixing.mix(docs).collect()}
            assert collections.Counter(r.doc_id for r in got.collect()) == +collections.Counter(copies)
        if name != "pieces":
            assert got.columns == before.columns
            docs = got
    texts = collections.Counter((r.doc_id, hashlib.sha256((r.text or "").encode()).hexdigest()) for r in docs.collect())
    assert collections.Counter((r.doc_id, r.decoded_sha256) for r in got.collect()) == texts


def test_batches_for_python_are_bounded(spark, small, make_docs):
    """Ten texts of 4 MB are no single batch once a stage has been called."""
    spark.conf.unset("spark.sql.execution.arrow.maxBytesPerBatch")
    docs = make_docs([(i, "word " * 800_000, "en", "a") for i in range(10)]).coalesce(1)
    corpus_pipeline.encode(spark, docs, small)

    def sizes(batches):
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([batch.nbytes])], ["n"])

    assert max(r.n for r in docs.select("text").mapInArrow(sizes, "n long").collect()) < 16 << 20


def test_shuffle_files_go_with_their_query(spark, make_docs):
    """A stage leaves none behind, however long the driver's garbage waits."""
    folder = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()[0]
    files = lambda: {*glob.glob(f"{folder}/*/shuffle_*.data")}
    spark.conf.unset("spark.sql.classic.shuffleDependency.fileCleanup.enabled")
    before = files()
    docs = make_docs([(i, " ".join(f"w{j}" for j in range(60)) + f" {i % 7}", "en", "a") for i in range(40)])
    assert corpus_pipeline.keep_one_of_near_copies(spark, docs, "").count() == 1
    left = files() - before
    for _ in range(50):  # files go a moment after the query's end
        if not left:
            break
        time.sleep(0.2)
        left &= files()
    assert not left


def test_run(spark, small):
    assert corpus_pipeline.run(spark, small).where("round_trip").count() > 0


@pytest.mark.parametrize("name", list(queries.QUERIES))
def test_queries_run(spark, small, name):
    df = queries.QUERIES[name](spark, small)
    rows = "pages" if "pages" in name else "conversations" if "chats" in name else "documents"
    n = table(spark, small, rows).count()
    assert df.count() == n if rows != "conversations" else 0 < df.count() <= n


def test_chats_against_sql(spark, small):
    con = duckdb.connect()
    con.sql(f"CREATE VIEW conversations AS SELECT * FROM '{small}/conversations.parquet'")
    result = con.sql(queries.ORACLES["op8_chats"])
    want = sorted(result.fetchall())
    assert sorted(tuple(r[c] for c in result.columns) for r in queries.QUERIES["op8_chats"](spark, small).collect()) == want
