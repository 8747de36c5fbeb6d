"""Repeated passages, pages, pieces and chats, against brute force or the public library."""

import collections
import hashlib
import re

import pyarrow as pa
import pyarrow.compute as pc
import pytest
import sentencepiece

from fadegossip.llm import chats, pages, pieces, substrings
from fadegossip.llm.words import Words, mix, strings, to_strings

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_words():
    texts = ["a bb  c\n", None, "", "  ", "x", "é ñ\tü", "a b", "a bb c"]
    words = Words(strings(pa.array(texts)))
    body, offsets = words.joined()
    assert to_strings(body, offsets).to_pylist() == [" ".join(WORD.findall(t or "")) for t in texts]
    assert words.count.tolist() == [len(WORD.findall(t or "")) for t in texts]
    h = words.hashes()
    assert (h[:3] == h[-3:]).all()


def slow_removal(texts, window):
    docs = [WORD.findall(t or "") for t in texts]
    seen = collections.Counter(tuple(w[i : i + window]) for w in docs for i in range(len(w) - window + 1))
    out = []
    for w in docs:
        gone = [False] * len(w)
        for i in range(len(w) - window + 1):
            if seen[tuple(w[i : i + window])] > 1:
                gone[i : i + window] = [True] * window
        out.append((len(w), sum(gone), " ".join(x for x, g in zip(w, gone) if not g)))
    return out


@pytest.mark.parametrize("window, gram, group, cluster", [(35, 8, 256, 1024), (35, 8, 2, 2), (10, 3, 3, 1), (5, 5, 4, 1024)])
def test_repeats(spark, make_docs, odd_rows, window, gram, group, cluster):
    docs = make_docs(odd_rows, extra=True)
    got = substrings.repeated_spans(docs, window, gram, group, cluster).collect()
    want = slow_removal([r[1] for r in odd_rows], window)
    key = lambda r: tuple(map(str, r))
    assert sorted([(r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in got], key=key) == sorted([(r[0], *w) for r, w in zip(odd_rows, want)], key=key)
    texts = {str(r[0]): WORD.findall(r[1] or "") for r in odd_rows}
    for r in got:
        assert sum(s["to"] - s["from"] for s in r.spans) == r.n_removed
        for f in r.factors:  # factors keep to the length rule, lie in the spans and stand elsewhere as a whole
            assert f["to"] - f["from"] >= window and any(s["from"] <= f["from"] and f["to"] <= s["to"] for s in r.spans)
            own = texts[str(r.doc_id)][f["from"] : f["to"]]
            assert sum(w[i : i + len(own)] == own for i_, w in [(x[0], WORD.findall(x[1] or "")) for x in odd_rows] for i in range(len(w) - len(own) + 1)) > 1


def test_random_repeats(spark, make_docs):
    """Copies, passages in other surroundings, and edits, at few words so that anchors have many surroundings."""
    import random

    rng = random.Random(7)
    pool = [[rng.choice("abcdefgh") for _ in range(rng.randrange(3, 30))] for _ in range(12)]
    rows = []
    for i in range(150):
        w = [x for _ in range(rng.randrange(1, 7)) for x in rng.choice(pool)]
        if rng.random() < 0.3 and w:
            w[rng.randrange(len(w))] = "z"
        rows.append((i, " ".join(w), "en", "a"))
    for window, gram, group, cluster in ((12, 3, 10, 4), (6, 2, 40, 1024)):
        got = sorted((r.doc_id, r.n_words, r.n_removed, r.kept_text) for r in substrings.repeated_spans(make_docs(rows), window, gram, group, cluster).collect())
        assert got == [(i, *x) for (i, *_), x in zip(rows, slow_removal([r[1] for r in rows], window))]


def test_whole_rows(spark, make_docs, odd_rows):
    docs = make_docs(odd_rows, extra=True)
    got = substrings.without_repeats(docs)
    assert got.columns == docs.columns
    by = {r.doc_id: r for r in got.collect()}
    assert by[7].text == odd_rows[8][1] and by[1].text == "" and by[1].n_chars == 0 and by[5].g == "x"
    assert substrings.repeated_spans(make_docs([])).count() == 0


PAGE = """<html><head><title>T</title><script>var a="</p>";</script></head><body><nav><a href=x>Menu</a></nav><!-- <p>no</p> -->
<div class="cookie-notice">We use <div>cookies</div></div><{tag}><h1>Head &amp; more</h1><p>First   <b>bold<br>line<p>Second&nbsp;one</p><aside>side</aside>
<section class="comments"><p>reader</p></section></{tag}><footer>&copy; host</footer></body></html>"""


def test_blocks():
    three = ["Head & more", "First bold line", "Second one"]
    assert pages.blocks(PAGE.replace("{tag}", "article")) == (three, [True] * 3)
    assert pages.blocks(PAGE.replace("{tag}", "div")) == (three, [False] * 3)
    assert pages.blocks("<nav>never closed <article><p>text</article>") == (["text"], [True])
    assert pages.blocks("plain < text & more") == (["plain < text & more"], [False])
    assert pages.blocks("") == ([], [])
    assert pages.blocks("<p>" * 20000 + "x")[0] == ["x"]


@pytest.mark.parametrize(
    "page, text",
    [
        ('<main>story</main><section class="comments"><article class="comment">reader</article></section>', "story"),
        ("<aside><article>teaser</article></aside><article>story</article>", "story"),
        ("<article hidden>secret</article><article>story</article>", "story"),
        ("<article>story<section id=comments><article><p>reader</p></article></section></article>", "story"),
        ('<article class="comment-item">reader</article><article>story</article>', "story"),
        ('<div class="related"><article>teaser</article></div><article>story</article>', "story"),
        ('<div class="page sidebar-right"><article>story</article></div>', "story"),
        ('<div class="has-sidebar"><p>story</p></div>', "story"),
        ('<div class="social"><p>story</p></div>', "story"),
        ('<body class="has-sidebar"><main class="with-sidebar">story</main><form>ask</form>', "story"),
        ("<p>one</p><script>if (a<b) document.write('<article>no</article><!--')</script><p>two</p>", "one\n\ntwo"),
        ("<footer><div><article>old</article></div></footer>", ""),
    ],
)
def test_what_markup_rules_out(page, text):
    found, inside = pages.blocks(page)
    assert "\n\n".join(b for b, i in zip(found, inside) if i or not any(inside)) == text


def test_anchors_find_every_repeat():
    """In every repeat of run + winnow - 1 tokens a run is covered, and nothing outside repeats of `run` tokens is."""
    import random

    import numpy as np

    rng = random.Random(3)
    for _ in range(200):
        run = rng.randrange(2, 7)
        winnow = rng.randrange(1, run + 1)
        texts = [[rng.choice("abc") for _ in range(rng.randrange(1, 40))] for _ in range(2)]
        words = Words(strings(pa.array([" ".join(t) for t in texts])))
        place, keys = pages.anchors(words, run, winnow)
        doc = words.doc[place]
        shared = np.array([any(k == keys[j] and doc[j] != d for j in range(len(keys))) for k, d in zip(keys, doc)], bool)
        under = pages.covered(words, place, shared, run, 10**9)
        grams = lambda t, n: {tuple(t[i : i + n]) for i in range(len(t) - n + 1)}
        at = 0
        for own, other in (texts, texts[::-1]):
            got = [bool(under[at + i]) for i in range(len(own))]
            repeats = lambda n: [i for i in range(len(own) - n + 1) if tuple(own[i : i + n]) in grams(other, n)]  # noqa: B023, E731
            for i in repeats(run + winnow - 1):
                assert any(all(got[p : p + run]) for p in range(i, i + winnow))
            inner = {j for i in repeats(run) for j in range(i, i + run)}  # and less than `run` tokens beside one
            assert {i for i, x in enumerate(got) if x} <= {j + d for j in inner for d in range(-run, run + 1)}
            at += len(own)


def test_best_stretch():
    import numpy as np

    rng = np.random.default_rng(5)
    for _ in range(200):
        w = rng.choice([-1, 1], rng.integers(0, 30))
        a, b = pages.best_stretch(w)
        best = max([w[i:j].sum() for i in range(len(w)) for j in range(i + 1, len(w) + 1)], default=0)
        assert w[a:b].sum() == max(best, 0) and (a, b) != (0, 0) or best <= 0 and (a, b) == (0, 0)


def test_main_text(spark):
    shared = "these twelve words and a few more stand on every page of the host"
    long = [" ".join(f"{c}{i}" for i in range(40)) for c in "abcdef"]
    own = [" ".join(f"{c}{i}" for i in range(40)) for c in "mnop"]
    rows = [
        (1, "http://a.example.com/1", PAGE.replace("{tag}", "article")), (2, "http://a.example.com/2", f"<p>{shared}</p><p>{own[0]}</p>"),
        (3, "http://a.example.com/3", f"<p>{shared}</p><p>{own[1]}</p><p>{shared}</p>"), (4, "http://b.example.com/1", f"<p>{shared}</p>"), (5, None, None), (6, "no url", ""),
        (2, "http://a.example.com/2", f"<p>{shared}</p><p>{own[0]}</p>"), (None, "http://a.example.com/9", "<main>m</main>"),
        (7, "http://a.example.com/7", f"<p>{own[2]}</p><p>{shared}</p><p>{own[3]}</p>"), (8, "http://a.example.com/8", f"<p>{shared}</p>"),
        (9, "http://a.example.com/10", "<p>" + "</p><p>".join(long * 2) + "</p>"), (10, "http://a.example.com/11", "<p>" + "</p><p>".join([*long * 2, "x"]) + "</p>"),
        (11, "http://c.example.com/1", "<p>" + "word " * 200_000 + "</p>"), (12, "http://a.example.com/12", f"<article><p>{shared}</p></article>"),
    ]
    # what every page of a host holds goes at the ends and stays between unique text; copies of a stream are one; a long copy is an article
    want = [
        (1, "Head & more\n\nFirst bold line\n\nSecond one"), (2, own[0]), (2, own[0]), (3, own[1]), (4, shared), (5, ""), (6, ""), (None, "m"),
        (7, f"{own[2]}\n\n{shared}\n\n{own[3]}"), (8, ""), (9, "\n\n".join(long * 2)), (10, "\n\n".join([*long * 2, "x"])), (11, ("word " * 200_000).strip()), (12, shared),
    ]
    df = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("row", pages.F.lit(1)).withColumn("body", pages.F.lit("x")).withColumn("g", pages.F.lit(1))
    for groups in (256, 2):
        got = collections.Counter((r.page_id, r.text, r.n_chars) for r in pages.main_text(df, group_rows=groups).collect())
        assert got == collections.Counter((i, t, len(t)) for i, t in want)
    assert pages.main_text(df.limit(0)).count() == 0


def test_template_of_a_host_in_declared_articles(spark):
    """A block in most distinct streams of a host goes from a declared article, wherever it stands; what fewer articles share stays."""
    say = lambda name, i, n=20: " ".join(f"{name}{i}x{j}" for j in range(n))
    notice, short, some, law = say("notice", 0), "Subscribe now", say("some", 0), say("law", 0, 200)
    rows, want = [], {}

    def page(host, i, blocks, kept, copies=1):
        for _ in range(copies):
            rows.append((i, f"http://{host}.example.com/{i}", "<nav>menu</nav><article>" + "".join(f"<p>{b}</p>" for b in blocks) + "</article>"))
        want[i] = "\n\n".join(kept)

    for i in range(8):
        own, more = say("own", i, 3 if i == 3 else 20), say("more", i)
        shared = [some] if i < 5 else []
        page("most", i, [short, own, notice, more, *shared, law], [own, more, *shared, law])
        page("few", 10 + i, [own, more] + [notice, short] * (i < 5), [own, more] + [notice, short] * (i < 5))  # 5 of 8
        page("copies", 20 + i, [own, notice] if i == 0 else [own], [own, notice] if i == 0 else [own], 30 if i == 0 else 1)
        if i < 4:
            page("small", 30 + i, [own, notice], [own, notice])
    page("most", 8, [notice, short], [notice, short])  # nothing else is left of it
    page("most", 9, [f"{notice} {say('own', 9)}"], [f"{notice} {say('own', 9)}"])
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    for groups in (256, 2):
        got = pages.main_text(df, group_rows=groups).collect()
        assert collections.Counter((r.page_id, r.text) for r in got) == collections.Counter((i, want[i]) for i, _, _ in rows)
        assert {r.page_id: r.n_common for r in got if r.page_id < 10} == {**dict.fromkeys(range(9), 22), 9: 0}


def test_counts_of_the_exchange(spark):
    """Every group is told with how many contents each hash stands, in one step and in two."""
    import random

    import numpy as np

    from fadegossip.llm import exchange

    rng = random.Random(5)
    pairs = {g: [(rng.randrange(40), rng.randrange(300 if g % 2 else 3)) for _ in range(60)] for g in range(9)}
    kinds = collections.Counter(h for h, _ in {p for ps in pairs.values() for p in ps})

    def merged(g):
        entries = np.zeros(len(pairs[g]), exchange.ENTRY)
        entries["h"] = mix(np.array([h for h, _ in pairs[g]], np.uint64) + np.uint64(1))
        entries["v"] = np.array([v for _, v in pairs[g]], np.uint64) * np.uint64(2)
        entries["src"] = exchange.NOWHERE
        return exchange.Merged(entries)

    by_group = spark.createDataFrame([(g,) for g in pairs], "g long").groupBy("g")
    for cluster in (2, 1024):
        told = exchange.ask(lambda rows: by_group.applyInArrow(lambda key, members: rows(key[0].as_py(), merged(key[0].as_py()).distinct), "c int, s int, g long, items binary"), len(pairs), cluster, 1, counted=True)
        table = told.toArrow()
        for g, entries in pairs.items():
            mine = merged(g)
            got = exchange.told_to(mine.distinct, table.filter(pc.equal(table.column("g"), g)), True)["kinds"][mine.which]
            assert got.tolist() == [kinds[h] for h, _ in entries]


def test_pages_without_article_tags(spark, small):
    """The host's repeats alone, on the given pages with their article tags cut, leave the declared article on nearly all."""
    from fadegossip.llm.frames import table

    df = table(spark, small, "pages")
    cut = df.withColumn("html", pages.F.regexp_replace("html", "</?article>", ""))
    want = {r.page_id: r.text for r in pages.main_text(df).collect()}
    got = {r.page_id: r.text for r in pages.main_text(cut).collect()}
    assert sum(want[i] == got[i] for i in want) >= 0.9 * len(want)


@pytest.fixture(scope="module")
def model():
    with open(pieces.MODEL, "rb") as f:
        return f.read()


@pytest.fixture(scope="module")
def vocabulary(model):
    return pieces.Pieces(model)


TEXTS = ["", "a", " ", "   ", "  hi  there\n x\tü 漢 whndsh", "hello world, this is a test.", "x" * 300 + " y", "🙂🙂 zß", "<0x41> <s> </s>", "\n\n", "Les élèves naïfs", "den größten Überblick", "日本語のテキスト"]


def worth(vocabulary, ids):
    """Score of a path; a character without a piece costs `unknown` once, however many bytes stand for it."""
    fallen = bytes(int(vocabulary.text[vocabulary.text_at[i]]) for i in ids if vocabulary.is_fallback[i])
    return sum(vocabulary.score[i] for i in ids if not vocabulary.is_fallback[i]) + vocabulary.unknown * len(fallen.decode())


def slow_best(vocabulary, model, text):
    """Score of the best path, by trying every piece that ends at every character."""
    reader = sentencepiece.SentencePieceProcessor(model_proto=model)
    known = {reader.id_to_piece(int(i)): vocabulary.score[i] for i in vocabulary.ids}
    text = "▁" + text.replace(" ", "▁") if text else ""
    best = [0.0] + [float("-inf")] * len(text)
    for end in range(1, len(text) + 1):
        for start in range(max(0, end - 48), end):
            piece = text[start:end]
            if piece in known:
                best[end] = max(best[end], best[start] + known[piece])
        if text[end - 1] not in known:
            best[end] = max(best[end], best[end - 1] + vocabulary.unknown)
    return best[-1]


def test_best_path(model, vocabulary):
    """The exact optimum by brute force. The library, told to read the file as a Unigram model, is never better.

    It is worse at times (on "there" it scores -21 where -16 is possible), so its pieces are not compared.
    """
    library = sentencepiece.SentencePieceProcessor(model_proto=model + bytes([0x12, 2, 0x18, 1]))
    texts = [*TEXTS, *" ".join(TEXTS).split()]
    for text, ids in zip(texts, vocabulary.encode(strings(pa.array(texts))).to_pylist()):
        assert worth(vocabulary, ids) == pytest.approx(slow_best(vocabulary, model, text), abs=1e-6), text
        assert worth(vocabulary, ids) >= worth(vocabulary, library.encode(text)) - 1e-6


def test_round_trip(vocabulary, odd_rows):
    texts = strings(pa.array([*TEXTS, "a▁b ▁", *[r[1] for r in odd_rows]]))
    body, offsets = vocabulary.decode(vocabulary.encode(texts))
    assert to_strings(body, offsets).to_pylist() == texts.to_pylist()


def test_double_array():
    keys = [b"a", b"ab", b"abc", b"b", b"bcd", b"\xff", b"\xffa"]
    tree = pieces.DoubleArray(keys)
    import numpy as np

    body = np.frombuffer(b"abcd\xffab", np.uint8)
    s, e, k = tree.matches(body, np.arange(len(body)), np.full(len(body), len(body)))
    want = {(i, i + len(key), n) for n, key in enumerate(keys) for i in range(len(body)) if body[i : i + len(key)].tobytes() == key}
    assert set(zip(s.tolist(), e.tolist(), k.tolist())) == want


def test_encoded_rows(spark, make_docs, odd_rows, vocabulary):
    docs = make_docs(odd_rows, extra=True)
    rows = pieces.encode_checked(docs, vocabulary).collect()
    assert len(rows) == len(odd_rows) and all(r.round_trip for r in rows)
    texts = collections.Counter((i, hashlib.sha256((t or "").encode()).hexdigest()) for i, t, *_ in odd_rows)
    assert collections.Counter((r.doc_id, r.decoded_sha256) for r in rows) == texts
    back = pieces.decode(pieces.encode(docs, vocabulary), vocabulary)
    assert collections.Counter((r.doc_id, r.text) for r in back.collect()) == collections.Counter((i, t or "") for i, t, *_ in odd_rows)
    assert pieces.encode(make_docs([]), vocabulary).count() == 0


def test_chats(spark):
    a = [("user", "hi"), ("assistant", "hello"), ("user", "more"), ("assistant", None)]
    logs = {1: a[:1], 2: a[:2], 3: a, 4: a, 5: a[:3], 6: [("user", "hi"), ("assistant", "bye")], 7: [("assistant", "hi")], 8: [("user", "<|end|> trick")], None: [("user", "lost")], 9: [("user", None)], 10: [("user", "")]}
    rows = [(i, t, r, x, "z") for i, turns in logs.items() for t, (r, x) in enumerate(turns)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, part string").repartition(7)
    got = {r.conv_id: r for r in chats.collapse(df).collect()}
    assert set(got) == {3, 6, 7, 8, 9, 10, None}
    assert got[3].n_copies == 2 and got[3].n_turns == 4
    assert got[3].rendered == "<|user|>\nhi<|end|>\n<|assistant|>\nhello<|end|>\n<|user|>\nmore<|end|>\n<|assistant|>\n<|end|>\n"
    assert got[8].rendered == "<|user|>\n< |end|> trick<|end|>\n"
    assert chats.collapse(df.limit(0)).count() == 0


def test_repeated_turns(spark):
    """A turn row that is logged twice is two turns, alike in every order of the rows."""
    rows = [(1, 0, "user", "hi"), (1, 0, "user", "hi"), (1, 1, "assistant", "yes"), (2, 0, "user", "hi"), (2, 0, "user", "hi"), (3, 0, "user", "hi")]
    for order in (rows, rows[::-1]):
        df = spark.createDataFrame(order, "conv_id long, turn long, role string, text string")
        assert {(r.conv_id, r.n_turns, r.n_copies) for r in chats.maximal(df).collect()} == {(1, 3, 1)}


def test_long_chat_over_partitions(spark):
    """A conversation over many range partitions has the prefixes of its shorter copy."""
    rows = [(i, t, "user", f"turn {t}") for i, n in ((1, 400), (2, 399), (3, 10)) for t in range(n)] + [(4, 0, "user", "turn 1")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    assert {(r.conv_id, r.n_turns) for r in chats.maximal(df).collect()} == {(1, 400), (4, 1)}
