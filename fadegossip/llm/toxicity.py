"""Toxicity from a learned lexicon, matched with spelling errors, and weighed by context.

The lexicon is learned from a bounded sample of labelled rows: words, and stems with several endings, that occur
in toxic documents far more often than in others. Its words stand in a trie. A Levenshtein automaton of the
token (one insertion, deletion or substitution) is run against that trie, so that both fail as early as
possible; tokens reach it only if half of them is the half of a word of about their length, which no token within
one error can fail. Stems match the beginnings of tokens exactly.

A hit counts as abuse or as quotation: quotation if the token stands between an opening and a closing quotation
mark, however far apart, or a word of reporting stands in the window before it. Both numbers are the features of a logistic model whose prior lets
quotations count little. A misspelled hit is `MISSPELLED` of a plain one, so it shares the weight learnt from plain
hits. Only words of very high odds may be misspelled, and a near token that clean documents of the sample hold as
well is a word of its own, not an error.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.llm.frames import cut, held_out, table
from fadegossip.llm.quality import labelled, learnable
from fadegossip.llm.words import BYTE_BASE, BYTE_CODE, Words, chunked, raw, span_hashes, strings, to_strings

#: Labelled rows that are learnt from at most (half of them toxic), and entries of the lexicon at most.
SAMPLE, LEXICON = 4096, 2000
#: Least toxic documents of an entry and least share of them, least log odds, least endings of a stem, shortest word or stem that is learnt and shortest word that may be misspelled.
SUPPORT, SUPPORT_SHARE, ODDS, ENDINGS, STEM, FUZZY = 5, 0.015, 3.0, 8, 4, 5
#: A stem needs this many times the documents of a word.
STEM_SUPPORT = 3
#: What a misspelled hit counts in plain ones, and the least log odds of a word that may be misspelled.
MISSPELLED, SURE = 0.5, 4.0
#: Tokens before a hit in which a word of reporting makes it a quotation.
WINDOW = 6
# fixed values: words of reporting
REPORTING = frozenset("said says say saying called calls wrote writes quoted quotes quote term word phrase reported alleged claimed dit disait écrit appelé mot terme citation dice dijo llamó escribió palabra término cita sagte sagt schrieb nannte wort begriff zitat".split())
#: Bytes between tokens: everything in ASCII but letters and digits.
BETWEEN = np.array([b < 128 and not chr(b).isalnum() for b in range(256)])
# letters and digits in any script, or a quotation mark; U+0080-U+00BF and U+2000-U+207F are punctuation
_TOKEN = re.compile(r"[0-9a-z\u00c0-\u1fff\u2080-\U0010ffff]+|[\"“”„«»]")


def _without_marks(texts: pa.Array) -> pa.Array:
    """The texts with a space for each byte of the punctuation beyond ASCII."""
    body, offsets = raw(texts)
    wide = np.flatnonzero(body == 0xE2)
    wide = wide[(body[wide + 1] | 1) == 0x81]
    narrow = np.flatnonzero(body == 0xC2)
    if not len(wide) and not len(narrow):
        return texts
    body = body.copy()
    for at in (wide, wide + 1, wide + 2, narrow, narrow + 1):
        body[at] = 0x20
    return to_strings(body, offsets)


def trie(words: list[str]) -> dict:
    root: dict = {}
    for w in words:
        node = root
        for c in w:
            node = node.setdefault(c, {})
        node[""] = w
    return root


def within_one(token: str, root: dict) -> str | None:
    """A word of the trie within one error of the token, walking both together; None if there is none.

    The automaton's states are pairs (position in the token, errors so far).
    """
    n = len(token)

    def walk(node: dict, states: frozenset) -> str | None:
        if "" in node and len(node[""]) >= FUZZY and any(n - i + e <= 1 for i, e in states):
            return node[""]
        for c, child in node.items():
            if not c:
                continue
            after = set()
            for i, e in states:
                if i < n and token[i] == c:
                    after.add((i + 1, e))
                if e == 0:
                    after.add((i, 1))  # the token lacks c
                    if i < n:
                        after.add((i + 1, 1))  # another letter stands for c
                    if i + 1 < n and token[i + 1] == c:
                        after.add((i + 2, 1))  # a letter too many before c
            if after and (found := walk(child, frozenset(after))):
                return found
        return None

    return walk(root, frozenset([(0, 0)]))


class Halves:
    """Hashes of first and last halves of words: a filter that passes every token within one error of a word."""

    def __init__(self, words: list[str], stems: list[str], sure: list[str] | None = None):
        hashed = lambda xs: np.sort(self._hash([x.encode() for x in xs]))
        self.exact = hashed(words)
        self.stems = {n: hashed([s for s in stems if len(s.encode()) == n]) for n in {len(s.encode()) for s in stems}}
        self.sizes = {}
        sure = [w for w in (words if sure is None else sure) if len(w) >= FUZZY]
        for n in {len(w.encode()) for w in sure}:
            same = [w.encode() for w in sure if len(w.encode()) == n]
            self.sizes[n] = np.sort(self._hash([w[: n // 2] for w in same])), np.sort(self._hash([w[n - (n // 2) :] for w in same]))

    @staticmethod
    def _hash(words: list[bytes]) -> np.ndarray:
        if not words:
            return np.zeros(0, np.uint64)
        body = np.frombuffer(b"".join(words), np.uint8)
        stop = np.cumsum([len(w) for w in words])
        return span_hashes(BYTE_CODE[body], BYTE_BASE, stop - [len(w) for w in words], stop)

    def passes(self, words: Words) -> tuple[np.ndarray, np.ndarray]:
        """Indexes of distinct tokens (their first place in `words`) that may hit, and for every token which distinct one it is."""
        spans = words.spans()
        names = spans.of(words.start, words.end)
        _, first, which = np.unique(names, return_index=True, return_inverse=True)
        start, end = words.start[first], words.end[first]
        size = end - start
        ok = _in(names[first], self.exact)
        for n, known in self.stems.items():
            at = np.flatnonzero(size >= n)
            ok[at] |= _in(spans.of(start[at], start[at] + n), known)
        for n, (heads, tails) in self.sizes.items():
            # one error may be a character of up to four bytes
            at = np.flatnonzero((size >= n - 4) & (size <= n + 4) & (size >= n // 2) & ~ok)
            hit = _in(spans.of(start[at], start[at] + n // 2), heads) | _in(spans.of(end[at] - n // 2, end[at]), tails)
            ok[at] |= hit
        return np.where(ok, first, -1), which


def _in(values: np.ndarray, ordered: np.ndarray) -> np.ndarray:
    if not len(ordered) or not len(values):
        return np.zeros(len(values), bool)
    return ordered[np.minimum(np.searchsorted(ordered, values), len(ordered) - 1)] == values


class Lexicon:
    """Words with their trie, stems, and the weights of a document's hits."""

    FEATURES = ("abuse", "quoted")

    def __init__(self, words: list[str], stems: list[str], sure: list[str] | None = None):
        """sure: the words that may be misspelled, all of them by default."""
        self.words, self.stems = frozenset(words), tuple(stems)
        self.root, self.halves = trie(words if sure is None else sure), Halves(words, stems, sure)
        self.known: dict[str, int] = {}
        #: Tokens near a word that are words of their own.
        self.ordinary: frozenset[str] = frozenset()
        self.bias, self.weight = -3.0, np.array([3.0, 0.3])

    def kind(self, token: str) -> int:
        """0: no hit, 1: word or stem, 2: misspelled word."""
        if token in self.words or token.startswith(self.stems):
            return 1
        if len(token) < FUZZY - 1 or token in self.ordinary:
            return 0
        got = self.known.get(token)
        if got is None:
            if len(self.known) > 50_000:
                self.known.clear()
            got = self.known[token] = 2 if within_one(token, self.root) else 0
        return got

    def hits(self, texts: pa.Array) -> np.ndarray:
        """Numbers of plain, misspelled and quoted hits of each text."""
        out = np.zeros((len(texts), 3))
        for doc, found in self.found(texts):
            for _, kind, quoted in found:
                out[doc, 2 if quoted else kind - 1] += 1
        return out

    def found(self, texts: pa.Array) -> Iterator[tuple[int, list[tuple[str, int, bool]]]]:
        """(index, hits) of each text with hits; a hit is the token, its kind and whether it is quoted."""
        lowered = pc.utf8_lower(texts)
        words = Words(_without_marks(lowered), space=BETWEEN)
        first, which = self.halves.passes(words)
        real = np.zeros(len(first), bool)
        kinds: dict[str, int] = {}
        for i in np.flatnonzero(first >= 0).tolist():
            w = first[i]
            token = words.body[words.start[w] : words.end[w]].tobytes().decode("utf-8", "replace")
            if kind := self.kind(token):
                real[i], kinds[token] = True, kind
        if kinds:
            for doc in np.unique(words.doc[real[which]]).tolist():
                yield doc, self._weigh(lowered[doc].as_py(), kinds)

    def _weigh(self, text: str, kinds: dict[str, int]) -> list[tuple[str, int, bool]]:
        """kinds: the tokens that hit, and whether plainly (1) or misspelled (2)."""
        out, inside = [], []
        opened, last = "", -WINDOW - 1
        for i, m in enumerate(_TOKEN.finditer(text)):
            token = m[0]
            if token in "\"“”„«»":
                if not opened:
                    opened = token if token in '"“„«' else ""
                elif token in '"”»' or opened == "„" and token == "“":
                    out += [(t, k, True) for t, k, _ in inside]
                    opened, inside = "", []
                continue
            if token in REPORTING:
                last = i
                continue
            kind = kinds.get(token)
            if kind:
                (inside if opened else out).append((token, kind, i - last <= WINDOW))
        out += inside  # a quotation mark that is never closed covers nothing
        return out

    @staticmethod
    def features(hits: np.ndarray) -> np.ndarray:
        return np.log1p(np.column_stack((hits[:, 0] + MISSPELLED * hits[:, 1], hits[:, 2])))

    def scores(self, texts: pa.Array) -> np.ndarray:
        z = self.bias + self.features(self.hits(texts)) @ self.weight
        return 1 / (1 + np.exp(-np.clip(z, -500, 500)))

    def calibrate(self, hits: np.ndarray, labels: np.ndarray, toxic_share: float, prior: float = 1.0) -> None:
        """Logistic weights with a Gaussian prior on the given ones; the bias is then set for the real share of toxic rows."""
        x = np.hstack([np.ones((len(hits), 1)), self.features(hits)])
        centre = np.concatenate(([self.bias], self.weight))
        w = centre.copy()
        for _ in range(50):
            p = 1 / (1 + np.exp(-np.clip(x @ w, -500, 500)))
            step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + prior * np.eye(len(w)), x.T @ (p - labels) + prior * (w - centre))
            w = w - step
            if np.abs(step).max() < 1e-9:
                break
        share, own = np.clip([toxic_share, labels.mean()], 1e-4, 1 - 1e-4)
        w[1:] = np.maximum(w[1:], 0)  # a hit never speaks for a text
        w[0] += np.log(share / (1 - share)) - np.log(own / (1 - own))
        self.bias, self.weight = float(w[0]), w[1:]


def _terms(sample: DataFrame) -> DataFrame:
    """(term, stem, toxic, clean, endings): documents of the sample with a word, or with a word that begins with a stem.

    Distinct endings are counted over the whole sample; a batch tells no more of them than ENDINGS and one document's.
    """

    def run(batches):
        for batch in batches:
            seen: dict[tuple[str, int], list] = {}
            for text, label in zip(batch.column("text").to_pylist(), batch.column("label").to_pylist()):
                words = {w for w in _TOKEN.findall((text or "").lower()) if len(w) >= STEM}
                stems: dict[str, set] = {}
                for w in words:
                    for n in range(STEM, min(len(w), 9)):
                        stems.setdefault(w[:n], set()).add(w[n:])
                for key, ends in [*(((w, 0), ()) for w in words), *(((s, 1), e) for s, e in stems.items())]:
                    row = seen.setdefault(key, [0, 0, set()])
                    row[1 - label] += 1
                    if len(row[2]) < ENDINGS:
                        row[2].update(ends)
            yield pa.RecordBatch.from_arrays([pa.array([k[0] for k in seen], pa.string()), pa.array([k[1] for k in seen], pa.int32()), *[pa.array([r[i] for r in seen.values()], pa.int64()) for i in range(2)], pa.array([sorted(r[2]) for r in seen.values()], pa.list_(pa.string()))], ["term", "stem", "toxic", "clean", "endings"])

    found = sample.select("text", "label").mapInArrow(run, "term string, stem int, toxic long, clean long, endings array<string>")
    distinct = F.size(F.array_distinct(F.flatten(F.collect_list("endings"))))
    return found.groupBy("term", "stem").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"), distinct.alias("endings"))


def fit(docs: DataFrame, labels: DataFrame, bound: int = SAMPLE) -> Lexicon:
    """Lexicon and weights from at most `bound` labelled documents; without toxic ones the lexicon is empty.

    Of more than LEXICON entries those of most toxic documents are kept, ties by code points. Repeated rows of labels
    or docs count once (see quality.labelled); null texts count as empty. The result depends on the rows alone, not
    on how they are dealt.
    """
    sample = cut(labelled(docs, labels, "toxic", bound))
    share = {x.label: x.n for x in learnable(labels, "toxic").groupBy("label").agg(F.count(F.lit(1)).alias("n")).collect()}
    toxic, clean = share.get(1, 0), share.get(0, 0)
    sizes = F.lit(float(min(toxic, bound // 2) + 1)), F.lit(float(min(clean, bound // 2) + 1))
    odds = F.log((F.col("toxic") + 0.5) / sizes[0]) - F.log((F.col("clean") + 0.5) / sizes[1])
    least = max(SUPPORT, SUPPORT_SHARE * min(toxic, bound // 2))
    terms = _terms(sample).where(F.col("toxic") >= least).withColumn("odds", odds).where(F.col("odds") > ODDS).where((F.col("stem") == 0) | (F.col("endings") >= ENDINGS) & (F.col("toxic") >= STEM_SUPPORT * least))
    best = terms.orderBy(F.col("toxic").desc(), "term", "stem").limit(LEXICON).collect()
    stems = _closed({x.term: x.toxic for x in best if x.stem})
    words = sorted(x.term for x in best if not x.stem and not x.term.startswith(tuple(stems)))
    lexicon = Lexicon(words, stems, sorted(x.term for x in best if not x.stem and x.odds >= SURE))
    if not words and not stems:
        lexicon.bias = float(np.log((toxic + 0.5) / (clean + 0.5)))
        return lexicon
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "text"):
                found = dict(shared.value.found(strings(part.column("text"))))
                hits = [[(t if k == 2 else "", k, q) for t, k, q in found.get(i, ())] for i in range(part.num_rows)]
                yield pa.RecordBatch.from_arrays([part.column("label"), *[pa.array([[h[j] for h in x] for x in hits], pa.list_(t)) for j, t in enumerate((pa.string(), pa.int32(), pa.bool_()))]], ["label", "near", "kind", "quoted"])

    rows = sample.select("label", "text").mapInArrow(run, "label int, near array<string>, kind array<int>, quoted array<boolean>").collect()
    rows.sort(key=lambda x: (x.label, x.near, x.kind, x.quoted))  # sums in one order, however the rows were dealt
    seen: dict[str, list[int]] = {}
    for row in rows:
        for token in {t for t in row.near if t}:
            seen.setdefault(token, [0, 0])[row.label] += 1
    size = [sum(row.label == label for row in rows) + 1 for label in (0, 1)]
    lexicon.ordinary = frozenset(t for t, (c, x) in seen.items() if c and np.log((x + 0.5) / size[1]) - np.log((c + 0.5) / size[0]) <= ODDS)
    hits = np.zeros((len(rows), 3))
    for i, row in enumerate(rows):
        for token, kind, quoted in zip(row.near, row.kind, row.quoted):
            if token not in lexicon.ordinary:
                hits[i, 2 if quoted else kind - 1] += 1
    lexicon.known.clear()
    lexicon.calibrate(hits, np.array([x.label for x in rows], float), toxic / max(toxic + clean, 1))
    return lexicon


def _closed(stems: dict[str, int]) -> list[str]:
    """Of stems that begin alike, the longest that holds nearly all documents of the shorter, else the shorter."""
    out: list[str] = []
    for s in sorted(stems, key=len):
        longer = [t for t in stems if len(t) == len(s) + 1 and t.startswith(s) and stems[t] >= 0.9 * stems[s]]
        if not longer and not s.startswith(tuple(out)):
            out.append(s)
    return sorted(out)


def score(docs: DataFrame, lexicon: Lexicon) -> DataFrame:
    """(doc_id, score), a row for each row of docs, whatever other columns it has; repeated rows get equal scores.

    Null texts count as empty. Texts of any length are read whole, and a quotation may be of any length.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)  # at most LEXICON entries

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "text"):
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(shared.value.scores(strings(part.column("text"))))], ["doc_id", "score"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, score double")


def keep_clean(docs: DataFrame, lexicon: Lexicon, threshold: float = 0.5) -> DataFrame:
    """The rows of docs that score below the threshold, with all their columns, in one pass without a join.

    Nulls in any column and repeated rows are kept as they are; a null text counts as empty.
    """
    shared = docs.sparkSession.sparkContext.broadcast(lexicon)

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "text"):
                yield part.filter(pa.array(shared.value.scores(strings(part.column("text"))) < threshold))

    return docs.mapInArrow(run, docs.schema)


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = score(docs, fit(docs, table(spark, sf_dir, "labels")))
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
