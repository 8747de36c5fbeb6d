"""SimHash by covering hashing, components, and the digest comparison, against brute force."""

import hashlib
import importlib
import random
import re

import numpy as np
import pyarrow as pa
import xxhash
from test_shingles import slow_roots

from fadegossip.llm import digest, simhash
from fadegossip.llm.components import components
from fadegossip.llm.words import strings, xxh64


def slow_fingerprint(text):
    text = "".join(c.lower() if "A" <= c <= "Z" else c for c in text or "")
    w = re.findall(r"[^\x20\x09-\x0D]+", text)
    shingles = [" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))] if w else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def slow_classes(rows):
    """Least id reachable for each row of (id, fingerprint)."""
    fps = sorted({f for _, f in rows})
    parent = list(range(len(fps)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, f in enumerate(fps):
        for j in range(i):
            if bin(f ^ fps[j]).count("1") <= 4:
                parent[find(i)] = find(j)
    least = {}
    for i, f in rows:
        root = find(fps.index(f))
        if i is not None:
            least[root] = min(i, least.get(root, i))
    return [(i, least.get(find(fps.index(f)))) for i, f in rows]


def test_every_close_pair_collides():
    rng = np.random.default_rng(1)
    tables = simhash.masks()
    assert len(tables) == 31
    for _ in range(2000):
        a = int(rng.integers(0, 2**63))
        b = a
        for bit in rng.choice(64, rng.integers(0, 5), replace=False):
            b ^= 1 << int(bit)
        assert any(a & m == b & m for m in tables)


def test_documents(spark, make_docs, odd_rows):
    docs = make_docs(odd_rows, extra=True)
    got = simhash.near_duplicates(docs).collect()
    want = {}
    for i, t, *_ in odd_rows:
        want.setdefault(i, []).append(slow_fingerprint(t))
    assert len(got) == len(odd_rows)
    for r in got:
        assert r.fp % 2**64 in want[r.doc_id]
    rows = [(i, slow_fingerprint(t)) for i, t, *_ in odd_rows]
    key = lambda x: (x[0] is None, x[0] or 0, x[1] or 0)
    assert sorted([(r.doc_id, r.component_id) for r in got], key=key) == sorted(slow_classes(rows), key=key)


def test_large_buckets_are_cut_into_blocks(spark):
    """A dense ball of fingerprints, with blocks of three: the same classes as brute force."""
    rng = random.Random(3)
    centre = rng.getrandbits(64)
    fps = {centre ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for _ in range(60)} | {rng.getrandbits(64) for _ in range(40)}
    signed = [(f - 2**64 if f >> 63 else f,) for f in fps]
    df = spark.createDataFrame(signed, "fp long")
    roots = {block: {r.node: r.root for r in components(simhash.links(df, block=block)).collect()} for block in (3, 4096)}
    for found in roots.values():
        groups = {}
        for f, in signed:
            groups.setdefault(found.get(f, f), set()).add(f % 2**64)
        brute = {}
        for i, least in slow_classes([(f, f) for f in fps]):
            brute.setdefault(least, set()).add(i)
        assert sorted(map(sorted, groups.values())) == sorted(map(sorted, brute.values()))


def test_components_of_a_chain_and_a_hub(spark):
    chain = [(i, i + 1) for i in range(100, 160)]
    hub = [(0, i) for i in range(1, 50)]
    got = {r.node: r.root for r in components(spark.createDataFrame(chain + hub, "a long, b long")).collect()}
    assert set(got) == set(range(50)) | set(range(100, 161))
    assert all(got[i] == (0 if i < 50 else 100) for i in got)


def test_rounds_of_few_links_run_in_one_task(spark, monkeypatch):
    """The same classes whether a round's links are dealt out, in one task, or first one and then the other."""
    rng = random.Random(5)
    edges = spark.createDataFrame([(rng.randrange(300), rng.randrange(300)) for _ in range(160)] + [(i, i + 1) for i in range(400, 460)], "a long, b long").repartition(7)
    module, tasks = importlib.import_module("fadegossip.llm.components"), []
    real = module.cut

    def cut(df):
        out = real(df)
        tasks.append(out.rdd.getNumPartitions())
        return out

    monkeypatch.setattr(module, "cut", cut)
    found = []
    for few in (0, 10**6, 215):
        tasks.clear()
        found.append(sorted(components(edges, few).collect()))
        assert few < 10**6 or set(tasks[1:]) == {1}
    assert found[0] == found[1] == found[2] and len(found[0]) > 200


def test_keep_one(spark, make_docs, odd_rows):
    """Two texts under one id both stay unless one is a near copy; the row kept is the same in every layout."""
    docs = make_docs(odd_rows, extra=True)
    kept = simhash.keep_one(docs)
    assert kept.columns == docs.columns
    rows = [(r.doc_id, r.text) for r in kept.collect()]
    texts = [r[1] for r in odd_rows if r[0] is not None]
    roots = slow_roots(texts)
    ids = [r[0] for r in odd_rows if r[0] is not None]
    assert sorted(i for i, _ in rows if i is not None) == sorted(min(ids[k] for k in range(len(ids)) if roots[k] == r) for r in set(roots))
    assert [i for i, _ in rows].count(None) == 1
    again = sorted((str(r.doc_id), str(r.text)) for r in simhash.keep_one(docs.repartition(11)).collect())
    assert again == sorted((str(i), str(t)) for i, t in rows)


def test_xxh64_of_spans():
    rng = np.random.default_rng(3)
    body = rng.integers(0, 256, 5000).astype(np.uint8)
    start = rng.integers(0, 4800, 3000)
    end = np.minimum(start + rng.integers(0, 150, 3000), 5000)
    assert xxh64(body, start, end, 42).tolist() == [xxhash.xxh64_intdigest(body[a:b].tobytes(), 42) for a, b in zip(start, end)]
    assert xxh64(body[:0], start[:0], end[:0], 42).tolist() == []


def test_digest_against_sql(spark, small):
    """The edit, its digest and the lengths by DuckDB over the whole table."""
    import duckdb

    from fadegossip.llm.queries import QUERIES

    want = duckdb.sql(f"""WITH d AS (SELECT doc_id, coalesce(text, '') AS t, row_number() OVER (ORDER BY doc_id) AS n, count(*) OVER () AS all_ FROM '{small}/documents.parquet')
        SELECT a.doc_id, length(a.t), sha256(left(a.t, length(a.t) - length(a.t) // 2) || left(b.t, length(a.t) // 2)) FROM d a JOIN d b ON b.n = a.n % a.all_ + 1""").fetchall()
    assert sorted((r.doc_id, r.n_chars, r.edited_sha256) for r in QUERIES["op5_digest"](spark, small).collect()) == sorted(want)


def slow_digest(text):
    """The digest by loops over one text, from the description alone: hashed triplets, quartiles, codes."""
    data = text.encode()
    count = [0] * digest.BUCKETS
    for (i, j), pairs, bytes_ in zip(digest.TRIPLETS, digest._PAIRS, digest._BYTES):
        for k in range(len(data) - 4):
            count[int(pairs[data[k + i] << 8 | data[k + j]] ^ bytes_[data[k]])] += 1
    ordered = sorted(count)
    q = [ordered[len(count) * x // 4 - 1] for x in (1, 2, 3)]
    return [sum(c > x for x in q) for c in count]


def test_digest_codes_against_loops():
    texts = ["", "abcd", "the same text " * 9, "é ñ 漢字 🙂 " * 20, "a" * 300]
    for text, row in zip(texts, digest.digests(strings(pa.array(texts)))):
        assert row[4:].tolist() == slow_digest(text)


def test_empty_table(spark, make_docs):
    assert simhash.near_duplicates(make_docs([])).count() == 0
    assert digest.compare_with_next(make_docs([])).count() == 0


def test_digest_with_next(spark, make_docs, odd_rows):
    rows = [r for r in odd_rows if r[0] not in (None, 2)]
    got = {r.doc_id: r for r in digest.compare_with_next(make_docs(rows, extra=True)).collect()}
    order = sorted(rows, key=lambda r: r[0])
    assert len(got) == len(rows)
    for n, (i, text, *_) in enumerate(order):
        text, after = text or "", order[(n + 1) % len(order)][1] or ""
        k = len(text) // 2
        edited = text[: len(text) - k] + after[:k]
        assert got[i].n_chars == len(text)
        assert got[i].edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        three = digest.digests(strings(pa.array([text, edited, after])))
        assert [got[i].fingerprint, got[i].edited_fingerprint] == digest.as_hex(three[:2])
        assert got[i].near_edited == digest.likeness(three[:1], three[1:2])[0]
        assert got[i].near_next == digest.likeness(three[:1], three[2:])[0]
        assert 0 <= got[i].near_next <= 1


def test_digest_of_repeated_ids_keeps_rows(spark, make_docs, odd_rows):
    assert digest.compare_with_next(make_docs(odd_rows)).count() == len(odd_rows)


def test_digest_round_trip_and_order():
    texts = pa.array(["the same text " * 40, "the same text " * 40, "other words stand here " * 40, ""])
    rows = digest.digests(strings(texts))
    codes = digest.as_hex(rows)
    assert codes[0] == codes[1] != codes[2]
    assert (digest.from_hex(codes[2]) == rows[2]).all()
    assert digest.likeness(rows[:1], rows[1:2])[0] == 1 > digest.likeness(rows[:1], rows[2:3])[0]
