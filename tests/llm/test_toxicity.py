"""Misspelled terms, endings at every number of partitions, and long quotations."""

import random

import pyarrow as pa

from fadegossip.llm import toxicity
from fadegossip.llm.words import strings

INSULTS = ["idiot", "moron", "pathetic", "worthless"]


def labelled(spark, make_docs):
    """300 toxic and 300 clean documents; clean ones hold a word of their own that is one error from an insult."""
    rng, rows, labels = random.Random(2), [], []
    for i in range(600):
        toxic = i % 2
        body = [f"w{rng.randrange(300)}" for _ in range(40)]
        if toxic:
            body += [rng.choice(INSULTS) for _ in range(4)]
        elif i % 4 == 0:
            body += ["idiom"] * 4
        rows.append((i, " ".join(body), "en", "a"))
        labels.append((i, 1, toxic))
    return make_docs(rows), spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


def test_misspelled_terms_count_after_fit(spark, make_docs):
    docs, labels = labelled(spark, make_docs)
    lexicon = toxicity.fit(docs, labels)
    assert set(INSULTS) <= lexicon.words
    plain = " ".join(f"w{i}" for i in range(40))
    wrong = plain + " you idjot and mooron, so pathetik, so worthles, such an idiott and morom"
    got = lexicon.scores(strings(pa.array([wrong, plain, plain + " idiom" * 6, plain + " idiot moron pathetic worthless"])))
    assert got[0] >= 0.5 and got[3] >= 0.5
    assert got[1] < 0.5 and got[2] < 0.5


def test_stems_at_every_number_of_partitions(spark, make_docs):
    """Twelve endings of a stem that no task sees together."""
    rows = [(i, f"lowei{'abcdefghijkl'[i // 2 % 12]}x word{i % 5}" if i % 2 else f"fine word{i % 5}", "en", "a") for i in range(480)]
    labels = spark.createDataFrame([(i, 1, i % 2) for i, *_ in rows], "doc_id long, quality int, toxic int")
    docs = make_docs(rows)
    found = [toxicity.fit(docs.repartition(n, "doc_id"), labels) for n in (1, 3, 48)]
    assert len({(x.words, x.stems, x.bias, tuple(x.weight)) for x in found}) == 1
    assert found[0].stems and all(s.startswith("lowe") for s in found[0].stems), found[0].words


def test_quotations_of_any_length():
    lexicon = toxicity.Lexicon(["idiot", "moron"], [])
    long = "idiot moron " + "so it went on and on " * 200
    texts = [f'He read: "{long}" and left', f"“{long}”", f"„{long}“ then idiot", f'an " open mark {long}', f'"short" {long} "short"']
    assert lexicon.hits(strings(pa.array(texts))).tolist() == [[0, 0, 2], [0, 0, 2], [1, 0, 2], [2, 0, 0], [2, 0, 0]]
    assert lexicon.scores(strings(pa.array(texts[:1])))[0] < 0.5 < lexicon.scores(strings(pa.array([long])))[0]
