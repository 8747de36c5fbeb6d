"""Quality, toxicity, outliers and mixing: accuracy on held-out rows, brute force and constraints."""

import collections
import random
import re

import numpy as np
import pytest

from fadegossip.llm import mixing, outliers, quality, toxicity
from fadegossip.llm.frames import held_out, table
from fadegossip.llm.queries import QUERIES


def auc(scores, labels):
    order = np.argsort(scores)
    rank = np.empty(len(scores))
    rank[order] = np.arange(len(scores))
    good = labels == 1
    return (rank[good].sum() - good.sum() * (good.sum() - 1) / 2) / (good.sum() * (~good).sum())


@pytest.mark.parametrize("name, label, least", [("op6_quality", "quality", 0.95), ("op7_toxicity", "toxic", 0.75)])
def test_held_out_accuracy(spark, medium, name, label, least):
    got = QUERIES[name](spark, medium)
    assert got.count() == table(spark, medium, "documents").count()
    rows = got.join(table(spark, medium, "labels"), "doc_id").where("held_out").collect()
    scores, labels = np.array([r.score for r in rows]), np.array([r[label] for r in rows])
    assert ((scores >= 0) & (scores <= 1)).all()
    assert auc(scores, labels) >= least
    limit = 0.3 if label == "quality" else 0.5
    assert all(r.predicted == int(r.score >= limit) for r in rows)


def test_held_out_rows_teach_nothing(spark, medium):
    labels = table(spark, medium, "labels")
    flipped = labels.withColumn("quality", quality.F.when(held_out(), 1 - quality.F.col("quality")).otherwise(quality.F.col("quality")))
    docs = table(spark, medium, "documents")
    a, b = quality.fit(docs, labels), quality.fit(docs, flipped)
    assert (a.labels == b.labels).all() and np.allclose(a.vectors, b.vectors)


def test_scores_of_odd_rows(spark, make_docs, odd_rows):
    docs = make_docs([*odd_rows, (100, "good words here today", "en", "a"), (101, "idiot " * 5, "en", "a")], extra=True)
    labels = spark.createDataFrame([(1, 1, 0), (2, 0, 0), (7, 1, 0), (100, 1, 0), (101, 0, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")
    n = docs.count()
    assert quality.score(docs, quality.fit(docs, labels)).count() == n
    assert quality.score(docs, quality.fit(docs, labels.limit(0))).where("score = 0.5").count() == n
    lexicon = toxicity.fit(docs, labels)
    assert toxicity.score(docs, lexicon).count() == n
    kept = toxicity.keep_clean(docs, lexicon)
    assert kept.columns == docs.columns and kept.count() <= n
    assert quality.score(make_docs([]), None).count() == 0 and toxicity.score(make_docs([]), toxicity.Lexicon([], [])).count() == 0


def test_votes_against_brute_force(spark, small):
    """Scores of the nearest labelled vectors, one document and one neighbour at a time."""
    docs, labels = table(spark, small, "documents"), table(spark, small, "labels")
    space = quality.fit(docs, labels)
    texts = {r.doc_id: r.text or "" for r in docs.collect()}
    got = {r.doc_id: r.score for r in quality.score(docs, space).collect()}
    import pyarrow as pa

    from fadegossip.llm.words import strings

    for i, text in texts.items():
        counts = quality.rows_of(strings(pa.array([text])))
        x = (space._weigh(counts) @ space.axes)[0].astype(float)
        near = sorted(((float(x @ v) / max(float(np.sqrt(x @ x)), 1e-9), float(y)) for v, y in zip(space.vectors.astype(float), space.labels)), reverse=True)[: quality.NEIGHBOURS]
        weight = [max(c, 0.0) ** 4 for c, _ in near]
        want = sum(w * y for w, (_, y) in zip(weight, near)) / sum(weight) if sum(weight) > 1e-12 else float(space.labels.mean())
        assert got[i] == pytest.approx(want, abs=2e-3), i


def test_counts_of_words_against_loops():
    import pyarrow as pa

    from fadegossip.llm.words import strings

    texts = ["aa bb aa\ncc aa", "", "one two three two", "x\n\ny x"]
    got = quality.rows_of(strings(pa.array(texts)))
    for text, row in zip(texts, got):
        w = WORD.findall(text)
        assert row[: quality.WORD_DIMS].sum() == row[quality.WORD_DIMS : -8].sum() == len(w)
        assert row[-8:-2].tolist() == [sum(w[k] == w[k - gap] for k in range(gap, len(w))) for gap in quality._NEAR]
        assert row[-1] == text.count("\n")


def test_labels_of_repeated_rows(spark, make_docs):
    """Repeated labels and ids teach once, conflicting labels count as the larger, in every layout."""
    rows = [(i, f"good words {i} here today", "en", "a") for i in range(60)]
    labels = [(i, i % 2, i % 2) for i in range(60)]
    plain = quality.labelled(make_docs(rows), spark.createDataFrame(labels, "doc_id long, quality int, toxic int"), "quality", 40)
    twice = quality.labelled(make_docs(rows * 3).repartition(7), spark.createDataFrame(labels * 3 + [(1, 0, 0)], "doc_id long, quality int, toxic int"), "quality", 40)
    assert sorted(plain.collect()) == sorted(twice.collect()) and plain.count() <= 40


def test_toxicity_score_against_brute_force():
    """The score by its formula from hits that are found token by token with edit distance."""
    import pyarrow as pa

    from fadegossip.llm.words import strings

    words = ["idiot", "moron", "worthless"]
    lexicon = toxicity.Lexicon(words, ["lowei"])
    rng = random.Random(12)
    pool = [*words, "idjot", "mron", "worthles", "loweis", "fine", "day", "tree", "moronic", "said", "a", "worth"]
    texts = [" ".join(rng.choice(pool) for _ in range(rng.randrange(0, 30))) for _ in range(200)]
    for text, score in zip(texts, lexicon.scores(strings(pa.array(texts)))):
        plain = wrong = quoted = 0
        tokens = text.split()
        for i, t in enumerate(tokens):
            kind = 1 if t in words or t.startswith("lowei") else 2 if len(t) >= toxicity.FUZZY - 1 and any(edits(t, w) <= 1 for w in words) else 0
            if kind and "said" in tokens[max(0, i - toxicity.WINDOW) : i]:
                quoted += 1
            else:
                plain, wrong = plain + (kind == 1), wrong + (kind == 2)
        z = lexicon.bias + np.log1p(plain + toxicity.MISSPELLED * wrong) * lexicon.weight[0] + np.log1p(quoted) * lexicon.weight[1]
        assert score == pytest.approx(1 / (1 + np.exp(-z))), text


def test_fit_in_every_layout(spark, small):
    docs, labels = table(spark, small, "documents"), table(spark, small, "labels")
    found = [toxicity.fit(d, lab) for d, lab in ((docs, labels), (docs.repartition(64), labels.union(labels).union(labels)), (docs.union(docs).repartition(3), labels))]
    assert len({(x.words, x.stems, x.ordinary, x.bias, tuple(x.weight)) for x in found}) == 1


def edits(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        row = _next(row, i, x, b)
    return row[-1]


def _next(row, i, x, b):
    out = [i]
    for j, y in enumerate(b, 1):
        out.append(min(row[j] + 1, out[-1] + 1, row[j - 1] + (x != y)))
    return out


def test_automaton_against_edit_distance():
    words = ["idiot", "moron", "pathetic", "scum", "größe", "clown"]
    root, rng = toxicity.trie(words), random.Random(5)
    halves = toxicity.Halves(words, ["lowei"])
    import pyarrow as pa

    from fadegossip.llm.words import Words, strings

    for _ in range(3000):
        token = list(rng.choice(words))
        for _ in range(rng.randrange(3)):
            at = rng.randrange(len(token) + 1)
            token[at : at + rng.randrange(2)] = rng.choice(["", "x", "ö", "n"])
        token = "".join(token)
        near = any(len(w) >= toxicity.FUZZY and edits(token, w) <= 1 for w in words)
        assert (toxicity.within_one(token, root) is not None) == near
        if near and token:
            first, _ = halves.passes(Words(strings(pa.array([token]))))
            assert first[0] >= 0


def test_quotation_and_abuse():
    import pyarrow as pa

    from fadegossip.llm.words import strings

    lexicon = toxicity.Lexicon(["idiot", "worthless"], ["lowei"])
    texts = ["You idiot, you IDIOT!", "He called me an idiot yesterday", 'They wrote "idiot" on it', "idjot and wortless", "loweichen", "nothing at all", "an “idiot” and «worthless» thing", 'an " open mark and idiot']
    assert lexicon.hits(strings(pa.array(texts))).tolist() == [[2, 0, 0], [0, 0, 1], [0, 0, 1], [0, 2, 0], [1, 0, 0], [0, 0, 0], [0, 0, 2], [1, 0, 0]]


WORD = re.compile(r"[^\x20\x09-\x0D]+")


def slow_counts(text):
    text = text or ""
    w = WORD.findall(text)
    seen, dup = set(), 0
    for line in text.split("\n"):
        if WORD.search(line):
            dup += line in seen
            seen.add(line)
    runs = collections.Counter(tuple(w[i : i + 8]) for i in range(len(w) - 7))
    again = [False] * len(w)
    for i in range(len(w) - 7):
        if runs[tuple(w[i : i + 8])] > 1:
            again[i : i + 8] = [True] * 8
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text)), dup, sum(again)


def test_outliers(spark, make_docs, odd_rows):
    rng = random.Random(8)
    clean = [(i, " ".join(rng.choice(["the", "of", "and"] + [f"word{k}" for k in range(60)]) for _ in range(rng.randrange(60, 300))), "en", "a") for i in range(1000, 1300)]
    junk = [(i, " ".join(f"w{rng.randrange(900)}###$$%%" for _ in range(120)), "en", "a") for i in range(2000, 2010)]
    shout = [(i, " ".join(f"WORD{rng.randrange(900)}!!" for _ in range(120)), "en", "a") for i in range(3000, 3010)]
    lines = [(20, "same line\nsame line\n\n\nother\nsame line ", "en", "a")]
    rows = [*odd_rows, *clean, *junk, *shout, *lines]
    got = outliers.judge(make_docs(rows, extra=True)).collect()
    want = collections.Counter((r[0], *slow_counts(r[1])) for r in rows)
    assert collections.Counter((r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) for r in got) == want
    by = {r.doc_id: r for r in got}
    assert all(by[i].kept for i, *_ in clean)
    assert not any(by[i].kept for i, *_ in [*junk, *shout])
    for r in got:
        assert r.base_failed == (r.n_words < 20 or 100 * r.n_repeat_words > 30 * r.n_words)
        assert not (r.kept and r.base_failed)
    assert outliers.judge(make_docs([])).count() == 0


def slow_least(x, share, floor2):
    """The least log determinant over all subsets of share * n rows, with the one row that counts in part."""
    import itertools

    n, h, best = len(x), share * len(x), np.inf
    whole = int(h + 1e-9)
    for pick in itertools.combinations(range(n), whole):
        for extra in [None] if abs(h - whole) < 1e-9 else [i for i in range(n) if i not in pick]:
            w = np.zeros(n)
            w[list(pick)] = 1
            if extra is not None:
                w[extra] = h - whole
            best = min(best, np.linalg.slogdet(outliers.moments(x, w)[1] + floor2)[1])
    return best


def test_least_determinant_against_all_subsets(spark):
    """Small groups: the subset found has the least determinant of all subsets, or nearly."""
    rng = np.random.default_rng(6)
    names = list(outliers.FLOORS)
    floor2 = np.diag([outliers.FLOORS[n] ** 2 for n in names])
    groups = {k: np.vstack([rng.normal(0, 1, (9, 7)), rng.normal(rng.choice([0, 6]), 1, (3, 7))]) for k in range(6)}
    df = spark.createDataFrame([(g, *map(float, r)) for g, x in groups.items() for r in x], "gid long, " + ", ".join(f"{n} double" for n in names))
    got = {r.gid: r for r in outliers.estimate(df.repartition(5), names).collect()}
    few = {r.gid: r for r in outliers.estimate(df.repartition(3), names, groups_at_once=2).collect()}
    hits = 0
    for g, x in groups.items():
        least = slow_least(x, outliers.SHARE, floor2)
        assert least - 1e-3 <= got[g].logdet <= least + 0.3, (g, least, got[g].logdet)
        hits += got[g].logdet <= least + 1e-3
        assert got[g].n == few[g].n == len(x) and got[g].logdet == pytest.approx(few[g].logdet)
    assert hits >= 4


def test_concentration_ignores_a_third_of_bad_rows(spark):
    rng = np.random.default_rng(2)
    names = list(outliers.FLOORS)
    good, bad = rng.normal(0, 2, (700, len(names))), rng.normal(60, 1, (200, len(names)))
    same = np.repeat(rng.normal(0, 1, (1, len(names))), 3000, axis=0)  # a row that repeats
    rows = [(1, *map(float, x)) for x in np.vstack([good, bad])] + [(2, *map(float, x)) for x in same]
    df = spark.createDataFrame(rows, "gid long, " + ", ".join(f"{n} double" for n in names))
    found = {}
    for n in (1, 8, 64):
        got = {r.gid: r for r in outliers.estimate(df.repartition(n), names).collect()}
        assert np.abs(np.array(got[1].mean)).max() < 0.6
        assert np.allclose(got[2].mean, same[0])
        found[n] = np.array(got[1].mean + got[1].scatter)
    assert np.allclose(found[1], found[8]) and np.allclose(found[1], found[64])


def test_distances_against_numpy(spark, make_docs):
    """A large group's distances are those of the estimate, drawn towards its language's, by plain linear algebra."""
    rng = random.Random(18)
    rows = [(i, " ".join(rng.choice(["a", "bb", "ccc#", "Dd", "e1"]) + str(rng.randrange(50)) for _ in range(rng.randrange(30, 200))), "en", "a" if i % 5 else "b") for i in range(300)]
    docs = make_docs(rows)
    got = {r.doc_id: r for r in outliers.judge(docs).collect()}
    names = list(outliers.FLOORS)
    stats = outliers.counted(docs).select("doc_id", "source", *[x.alias(n) for n, x in outliers.statistics().items()]).collect()
    x = {r.doc_id: np.array([r[n] for n in names]) for r in stats}
    df = spark.createDataFrame([(0, "ab".index(r.source) + 1, *map(float, x[r.doc_id])) for r in stats], "whole long, own long, " + ", ".join(f"{n} double" for n in names))
    found = {r.gid: (r.n, (np.array(r.mean), np.array(r.scatter).reshape(7, 7), r.scale)) for r in outliers.estimate(df, names, ("whole", "own")).collect()}
    whole = found[0][1]
    lang = outliers.drawn_to(300, whole, whole)
    for r in stats:
        n, own = found["ab".index(r.source) + 1]
        mean, scatter, scale = outliers.drawn_to(n, own, lang)
        gap = x[r.doc_id] - mean
        if not got[r.doc_id].base_failed:
            assert got[r.doc_id].distance == pytest.approx(gap @ np.linalg.inv(scatter) @ gap / scale, rel=1e-6)
            assert got[r.doc_id].kept == (got[r.doc_id].distance <= outliers.chi_square(7, outliers.TAIL))


def test_targets():
    assert mixing.targets([100, 100, 100]) == [200.0, 83.33333333333333, 166.66666666666666]
    assert mixing.targets([0, 0]) == [0.0, 0.0]
    sizes = [10, 500, 30, 0, 44]
    got = mixing.targets(sizes)
    assert all(t <= 2 * s + 1e-9 for t, s in zip(got, sizes)) and abs(sum(got) - 1.5 * sum(sizes)) < 1e-6


def test_mix(spark, make_docs, odd_rows):
    rng = random.Random(4)
    rows = [*odd_rows, *[(i, "w " * rng.randrange(1, 200), "en", rng.choice(["a", "b", "c", "d", None])) for i in range(100, 700)]]
    got = mixing.mix(make_docs(rows, extra=True)).collect()
    assert len(got) == len(rows)
    sizes = collections.Counter((r[0], len(WORD.findall(r[1] or ""))) for r in rows)
    assert collections.Counter((r.doc_id, r.size) for r in got) == sizes
    taken, target = collections.Counter(), {}
    for r in got:
        assert r.taken == r.copies * r.size and 0 <= r.copies <= 2 and 0 <= r.rate <= 2
        taken[r.source] += r.taken
        target[r.source] = r.target
    own = collections.Counter()
    for r in rows:
        own[r[3]] += len(WORD.findall(r[1] or ""))
    order = sorted(own, key=lambda s: (s is None, s or ""))
    assert [round(target[s], 6) for s in order] == [round(x, 6) for x in mixing.targets([own[s] for s in order])]
    for s in order:
        assert abs(taken[s] - target[s]) <= max(5, 0.01 * target[s]), (s, taken[s], target[s])
    again = mixing.mix(make_docs(rows).repartition(3)).collect()
    key = lambda r: (str(r.doc_id), r.size, r.copies)
    assert sorted(map(key, got)) == sorted(map(key, again))
    assert mixing.mix(make_docs([])).count() == 0


def by_source(rows):
    taken, target = collections.Counter(), {}
    for r in rows:
        taken[r.source] += r.taken
        target[r.source] = r.target
    return taken, target


def test_a_source_of_equal_rows_meets_its_target(spark, make_docs):
    rng = random.Random(14)
    rows = [(i, "w " * rng.randrange(5, 60), "en", "ab"[i % 2]) for i in range(800)] + [(5000, "same words " * 5, "en", "c")] * 400
    found = {}
    for n in (1, 8, 64, 211):
        got = mixing.mix(make_docs(rows).repartition(n)).collect()
        taken, target = by_source(got)
        for s in "abc":
            assert abs(taken[s] - target[s]) <= max(10, 0.01 * target[s]), (n, s, taken[s], target[s])
        found[n] = sorted((r.doc_id, r.source, r.copies) for r in got)
    assert all(x == found[1] for x in found.values())
    docs = make_docs(rows, extra=True).repartition(5)
    kept = collections.Counter(r.doc_id for r in mixing.mixed(docs).collect())
    assert kept == collections.Counter(d for d, _, c in found[1] for _ in range(c))


def test_sizes_and_targets_against_sql(spark, small):
    """Sizes, source sizes and targets (weights 3, 1, 2, capped at twice a source, reshared until none is above) by DuckDB."""
    import duckdb

    sizes = duckdb.sql(f"SELECT doc_id, len(regexp_extract_all(coalesce(text, ''), '[^ \\t\\n\\x0b\\f\\r]+')) AS size, source FROM '{small}/documents.parquet'").fetchall()
    own = collections.Counter()
    for _, n, s in sizes:
        own[s] += n
    order = sorted(own, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: (3, 1, 2)[i % 3] for i, s in enumerate(order)}
    capped: set = set()
    while True:
        room = 1.5 * sum(own.values()) - sum(2 * own[s] for s in capped)
        share = {s: room * weight[s] / sum(weight[x] for x in order if x not in capped) for s in order if s not in capped}
        over = {s for s in share if share[s] > 2 * own[s]}
        if not over:
            break
        capped |= over
    target = {s: 2 * own[s] if s in capped else share[s] for s in order}
    got = QUERIES["op10_mixing"](spark, small).collect()
    by = {i: (n, s) for i, n, s in sizes}
    assert len(got) == len(sizes)
    taken = collections.Counter()
    for r in got:
        n, s = by[r.doc_id]
        assert (r.size, r.source_size) == (n, own[s]) and r.target == pytest.approx(target[s])
        assert r.taken in (0, n, 2 * n)
        taken[s] += r.taken
    largest = {s: max(n for n, x in by.values() if x == s) for s in order}  # ten documents a source: a whole one more or less
    assert all(abs(taken[s] - target[s]) <= largest[s] for s in order)


def test_counts_against_sql(spark, small):
    """Word, character, symbol and repeated-line counts of op9 by DuckDB over the whole table."""
    import duckdb

    want = duckdb.sql(f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM '{small}/documents.parquet'),
        l AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM d), m AS (SELECT doc_id, line, count(*) AS n FROM l WHERE regexp_matches(line, '[^ \\t\\n\\x0b\\f\\r]') GROUP BY 1, 2), dup AS (SELECT doc_id, sum(n - 1) AS n FROM m GROUP BY 1)
        SELECT d.doc_id, len(regexp_extract_all(t, '[^ \\t\\n\\x0b\\f\\r]+')), length(regexp_replace(t, '[ \\t\\n\\x0b\\f\\r]', '', 'g')), len(regexp_extract_all(t, '[#*$%&|<>]')), coalesce(dup.n, 0)::BIGINT FROM d LEFT JOIN dup USING (doc_id)""").fetchall()
    got = [(r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines) for r in QUERIES["op9_outliers"](spark, small).collect()]
    assert sorted(got) == sorted(want)


def test_multipliers_meet_the_targets(spark, make_docs):
    rng = random.Random(6)
    docs = make_docs([(i, "w " * rng.randrange(1, 400), "en", rng.choice("abc")) for i in range(400)])
    expected = collections.Counter()
    for r in mixing.mix(docs).collect():
        expected[r.source, r.target] += r.rate * r.size
    for (_, target), tokens in expected.items():
        assert abs(tokens - target) < 1e-3


def test_mixed_rows(spark, make_docs, odd_rows):
    docs = make_docs(odd_rows, extra=True)
    got = mixing.mixed(docs)
    assert got.columns == docs.columns
    want = collections.Counter({})
    for r in mixing.mix(docs).collect():
        want[r.doc_id] += r.copies
    assert collections.Counter(r.doc_id for r in got.collect()) == +want
