"""Near copies on shingles of five words against brute force over all pairs."""

import random
import re

from fadegossip.llm import shingles, simhash
from fadegossip.llm.frames import table


def words(n, seed, vocabulary=400):
    rng = random.Random(seed)
    return [f"w{rng.randrange(vocabulary)}" for _ in range(n)]


def slow_set(text):
    text = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


def slow_roots(texts):
    """The least index reachable from each text by pairs of similarity 0.8."""
    sets, root = [slow_set(t) for t in texts], list(range(len(texts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    where = {}
    for i, s in enumerate(sets):
        near = where.setdefault(None, set()) if not s else set().union(*(where.setdefault(x, set()) for x in s))
        for j in near:
            both = len(s & sets[j])
            if 5 * both >= 4 * (len(s) + len(sets[j]) - both):
                x, y = sorted((find(i), find(j)))
                root[y] = x
        for x in s or (None,):
            where[x].add(i)
    return [find(i) for i in range(len(texts))]


def classes(found):
    out = {}
    for key, root in found:
        out.setdefault(root, set()).add(key)
    return {frozenset(x) for x in out.values()}


def compare(spark, texts, **how):
    df = spark.createDataFrame([(i, i, t) for i, t in enumerate(texts)], "id long, row long, text string")
    got = [(r.id, r.root) for r in shingles.near_copies(df, **how).collect()]
    assert len(got) == len(texts)
    assert classes(got) == classes(enumerate(slow_roots(texts)))


def edited(base, n, rng):
    out = list(base)
    for at in rng.sample(range(len(out)), n):
        out[at] = f"e{rng.randrange(10**9)}"
    return " ".join(out)


def test_edits_around_the_threshold(spark):
    """Chains, a large group, a line that all share, short and empty texts; also with buckets cut into blocks of three."""
    rng = random.Random(4)
    base, texts = [words(rng.randrange(40, 200), i) for i in range(12)], ["", None, " \t", "one", "One", "a b c d", "a b c d e", "a b c d e f"]
    for b in base:
        texts += [edited(b, rng.randrange(0, 1 + len(b) // 25), rng) for _ in range(6)]
    texts += [edited(base[0], 3, rng) for _ in range(40)]
    texts += ["the very common line of every page " + " ".join(words(8, 100 + i)) for i in range(20)]
    compare(spark, texts)
    compare(spark, texts, block=3)


def test_a_group_of_edits_and_stragglers(spark):
    """A text and many edits of it, from few words to a third of them, in buckets of one block and of several."""
    rng = random.Random(21)
    base = words(146, 1, 10**6)
    texts = [" ".join(base)] + [edited(base, rng.randrange(0, 12), rng) for _ in range(250)]
    compare(spark, texts)
    compare(spark, texts, block=16)


def test_given_documents(spark, medium):
    texts = [r.text for r in table(spark, medium, "documents").orderBy("doc_id").collect()]
    compare(spark, texts)


def test_the_stage_drops_copies_beyond_four_bits(spark, make_docs):
    """Edits of three words in 150: similarity over 0.8, fingerprints often more than four bits apart."""
    rng = random.Random(9)
    bases = [words(150, 50 + i, 10**6) for i in range(20)]
    rows = [(2 * i + k, edited(b, 3 * k, rng), "en", "a") for i, b in enumerate(bases) for k in (0, 1)]
    assert sorted(r.doc_id for r in simhash.keep_one(make_docs(rows)).collect()) == [2 * i for i in range(20)]


def test_rows_that_repeat_an_id_keep_their_own_class(spark, make_docs):
    """A text that shares its id with a copy of another document stays, whatever the order of the rows."""
    one, two, three = (" ".join(words(60, 70 + i)) for i in range(3))
    rows = [(1, one, "en", "a"), (2, one, "en", "a"), (2, two, "en", "a"), (2, three, "en", "a"), (2, three, "en", "a"), (3, two, "en", "b")]
    for order in (rows, rows[::-1]):
        got = sorted((r.doc_id, r.text) for r in simhash.keep_one(make_docs(order)).collect())
        assert got == sorted([(1, one), (2, two), (2, three)])


def test_the_stage_settles_what_simhash_links(spark, make_docs, monkeypatch):
    """A bucket's star never sees these pairs; the covering tables alone bring them to the check, which passes near copies only."""
    rng = random.Random(31)
    base = words(400, 90, 10**6)
    rows = [(0, " ".join(base), "en", "a"), (1, edited(base, 1, rng), "en", "a"), (2, " ".join(words(80, 91)), "en", "a")]
    rows += [(3 + i, " ".join(base[:100] * i), "en", "a") for i in (1, 2)]  # other sets, whose fingerprints are a few bits apart
    monkeypatch.setattr(shingles, "_stars", lambda pairs, batch_of: batch_of(0, [shingles.np.zeros(0, int)] * 4))
    pairs, verified = [], shingles.verified
    monkeypatch.setattr(shingles, "verified", lambda p, t: pairs.append(p.count()) or verified(p, t))
    got = sorted(r.doc_id for r in simhash.keep_one(make_docs(rows)).collect())
    assert got == sorted({rows[i][0] for i in slow_roots([r[1] for r in rows])})
    assert pairs[0] > 0 and pairs[1] == 0  # nothing is left to the pairs of the buckets


def test_simhash_links_are_those_within_the_radius(spark):
    """Texts of one fingerprint are a star, others are linked by the tables."""
    got = shingles.alike(spark.createDataFrame([(1, 0), (2, 0), (3, 15), (4, 31 << 20), (5, 0)], "sid long, fp long"))
    assert sorted(map(tuple, got.collect())) == [(1, 2), (1, 3), (1, 5)]
