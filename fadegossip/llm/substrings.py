"""Repeated-passage removal by relative Lempel-Ziv parsing against an index of the whole corpus.

The corpus is its own reference. Every document is cut into pieces at anchors: a window of `window` words is
represented by its least hashed `gram` of words, and consecutive windows with one anchor are a piece, the words that
they cover. Equal windows have equal anchors at equal places. The index of all pieces is dealt to reference shards by the
hash of the anchor (`exchange`); a group of documents asks for all its pieces at once, so each document meets every
reference shard that can hold a match, and no other.

1. Factors. A piece that stands elsewhere too comes back with the place of its least other occurrence, its source. A
   factor is parsed greedily: it goes on as long as the next piece's source follows on in the same text, and is
   the longest copy of that source from its start. Each piece has `window` words at least, and so has a factor; what is
   shorter stays literal. All windows of a factor are repeated.
2. Boundaries. A window at the edge of a factor, or in a literal stretch, may still stand elsewhere, where its
   anchor has other surroundings. Only pieces whose anchor has those are open: one occurrence of each such piece
   names its windows to the shards by two 63-bit hashes, and one bit comes back for each.

A word goes if and only if a covering window stands elsewhere too (but for collisions of 127 bits of hash). Rows are dealt
to groups by hash and row number, so equal rows don't meet in one group; what a third of all documents hold
is one entry for each group in a task and for each cluster of groups in a shard. Text is shuffled once and Spark reuses
that exchange; partitions hold `GROUPS_A_TASK` groups at every size.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fadegossip.llm.exchange import CLUSTER, ENTRY, NOWHERE, REST, Merged, ask, told_to
from fadegossip.llm.frames import shuffle_width, table
from fadegossip.llm.words import WORD_BASE, WORD_BASE_2, Spans, Words, chunked, least_in_windows, mix, strings, to_strings

WINDOW, GRAM = 35, 8
#: Documents of a group, about a MB of text, and groups of a partition.
GROUP_ROWS, GROUPS_A_TASK = 256, 16


class Pieces:
    """The pieces of a chunk: first word, number of windows, anchor, and the entries that ask for them."""

    def __init__(self, part, before: int, group: int, window: int, gram: int):
        """before: words of the group in earlier chunks."""
        self.part, self.window = part, window
        self.words = words = Words(strings(part.column("text")))
        hashes = words.hashes()
        start = words.starts_of(window)
        grams = np.full(len(hashes), np.iinfo(np.uint64).max, np.uint64)
        at = words.starts_of(gram)
        self.spans, self.checks = Spans(hashes, WORD_BASE), Spans(hashes, WORD_BASE_2)
        grams[at] = self.spans.of(at, at + gram)
        place = least_in_windows(grams, window - gram + 1)[start] if len(start) else start
        fresh = np.ones(len(start), bool)
        fresh[1:] = place[1:] != place[:-1]
        first = np.flatnonzero(fresh)
        self.start, self.count = start[first], np.diff(np.append(first, len(start)))
        self.place = place[first] + before
        self.entries = np.zeros(len(first), ENTRY)
        # least hashes crowd near zero; scrambled, they spread evenly over the shards
        self.entries["h"] = mix(grams[place[first]])
        self.entries["v"] = self.checks.of(self.start, self.start + self.count + window - 1) & REST
        self.entries["src"] = np.uint64(group << 32) + self.place.astype(np.uint64)

    def windows(self, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """First words of the windows of some pieces, and their entries."""
        n = self.count[asked]
        stop = np.cumsum(n)
        start = np.repeat(self.start[asked] - (stop - n), n) + np.arange(int(stop[-1]) if len(stop) else 0)
        entries = np.zeros(len(start), ENTRY)
        entries["h"], entries["v"], entries["src"] = self.spans.of(start, start + self.window), self.checks.of(start, start + self.window) & REST, NOWHERE
        return start, entries

    def factors(self, found: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(first word, word behind the last, source of the first word) of the greedy factors; found: the answers to the pieces."""
        again, source, doc = found["again"], found["src"].astype(np.int64), self.words.doc[self.start]
        on = np.zeros(len(doc), bool)
        on[1:] = again[1:] & again[:-1] & (doc[1:] == doc[:-1]) & (source[1:] - source[:-1] == self.place[1:] - self.place[:-1])
        begin = np.flatnonzero(again & ~on)
        follows = np.append(on[1:], False)
        end = np.flatnonzero(again & ~follows)
        first = self.start[begin]
        return first, self.start[end] + self.count[end] + self.window - 1, source[begin] - (self.place[begin] - first)


def _pieces(table: pa.Table, group: int, window: int, gram: int) -> list[Pieces]:
    out, before = [], 0
    for part in chunked(table, "text"):
        out.append(Pieces(part, before, group, window, gram))
        before += len(out[-1].words.doc)
    return out


def _joined(parts) -> np.ndarray:
    return np.concatenate([np.zeros(0, ENTRY), *parts])


def _found(pieces: list[Pieces], told) -> list[np.ndarray]:
    """The answers to each chunk's pieces; told: rows (c, items)."""
    entries = _joined(x.entries for x in pieces)
    merged = Merged(entries)
    answers = merged.answers(entries, told_to(merged.distinct, told))
    cuts = np.cumsum([len(x.entries) for x in pieces])[:-1]
    return np.split(answers, cuts) if pieces else []


def _open(piece: Pieces, found: np.ndarray) -> np.ndarray:
    """Pieces whose windows are named: the anchor has several surroundings, and no earlier piece is the same."""
    return found["other"] & (piece.entries["src"] < found["src"])


def _parsed(docs: DataFrame, window: int, gram: int, group_rows: int, untouched: bool, cluster: int) -> DataFrame:
    """docs -> (row, n_words, n_removed, spans, factors, kept_text); row is a struct of all columns but the text.

    untouched: kept_text of a row that loses nothing is its text as it was, not its words.
    """
    groups = max(1, -(-docs.count() // group_rows))
    row = F.struct(*[F.col(f"`{c}`") for c in docs.columns if c != "text"])
    rows = docs.select(row.alias("row"), "text")
    dealt = rows.select(F.pmod(F.xxhash64("row", "text", F.monotonically_increasing_id()), F.lit(groups)).alias("g"), "row", "text")
    by_group = dealt.repartition(max(shuffle_width(docs.sparkSession), -(-groups // GROUPS_A_TASK)), "g").groupBy("g")
    sent = "c int, s int, g long, items binary"

    def ask_pieces(name):
        return by_group.applyInArrow(lambda key, members: name(key[0].as_py(), Merged(_joined(x.entries for x in _pieces(members, key[0].as_py(), window, gram))).distinct), sent)

    about_pieces = ask(ask_pieces, groups, cluster)

    def ask_windows(name):
        def send(key, members, told):
            pieces = _pieces(members, key[0].as_py(), window, gram)
            return name(key[0].as_py(), Merged(_joined(x.windows(_open(x, y))[1] for x, y in zip(pieces, _found(pieces, told)))).distinct)

        return by_group.cogroup(about_pieces.groupBy("g")).applyInArrow(send, sent)

    about_windows = ask(ask_windows, groups, cluster)

    def remove(key, members, told):
        pieces = _pieces(members, key[0].as_py(), window, gram)
        about = np.asarray(told.column("about"))
        found = _found(pieces, told.filter(pa.array(about == 0)))
        windows = [x.windows(_open(x, y)) for x, y in zip(pieces, found)]
        entries = _joined(x for _, x in windows)
        merged = Merged(entries)
        repeated = merged.answers(entries, told_to(merged.distinct, told.filter(pa.array(about == 1))))["again"]
        at, tables = 0, []
        for x, y, (start, own) in zip(pieces, found, windows):
            hit = start[repeated[at : at + len(own)]]
            at += len(own)
            n = len(x.words.doc)
            depth = np.zeros(n + 1, np.int32)
            np.add.at(depth, hit, 1)
            np.add.at(depth, hit + window, -1)
            factors = x.factors(y)
            np.add.at(depth, factors[0], 1)
            np.add.at(depth, factors[1], -1)
            tables.append(_cleaned(x.part, x.words, np.cumsum(depth[:n]) > 0, factors, untouched))
        return pa.concat_tables(tables)

    schema = T.StructType([dealt.schema["row"], *T._parse_datatype_string("n_words long, n_removed long, spans array<struct<from:long,to:long>>, factors array<struct<from:long,to:long,source:long>>, kept_text string").fields])
    told = about_pieces.withColumn("about", F.lit(0)).union(about_windows.withColumn("about", F.lit(1)))
    return by_group.cogroup(told.groupBy("g")).applyInArrow(remove, schema)


def repeated_spans(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, group_rows: int = GROUP_ROWS, cluster: int = CLUSTER) -> DataFrame:
    """docs (doc_id, text) -> (doc_id, n_words, n_removed, spans, factors, kept_text), one row for each row.

    spans are [from, to) word ranges covered by windows of `window` words whose sequence also starts elsewhere
    in `docs` (before any removal); factors are the greedy copies among them, with the place of their source in the
    index (group * 2**32 + word of the group); kept_text has the other words joined by one space. Null texts have no word;
    repeated rows are each other's repeats; null ids are carried; a text of any length is one value. An empty table
    gives an empty result.
    """
    return _parsed(docs.select("doc_id", "text"), window, gram, group_rows, False, cluster).select("row.doc_id", "n_words", "n_removed", "spans", "factors", "kept_text")


def without_repeats(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, group_rows: int = GROUP_ROWS, cluster: int = CLUSTER) -> DataFrame:
    """The rows of docs, with all columns, without the words of repeated_spans(); n_chars, if there, follows.

    A text that loses words has the others joined by one space, any other text stays as it is (null: empty). Nulls
    in other columns, repeated rows and columns of any name are carried.
    """
    found = _parsed(docs, window, gram, group_rows, True, cluster)
    return found.select(*[F.col("kept_text").alias("text") if c == "text" else F.length("kept_text").cast("long").alias(c) if c == "n_chars" else F.col(f"row.`{c}`") for c in docs.columns])


def _cleaned(part: pa.Table, words: Words, gone: np.ndarray, factors: tuple[np.ndarray, np.ndarray, np.ndarray], untouched: bool) -> pa.Table:
    n_docs = len(words.count)
    removed = np.bincount(words.doc[gone], minlength=n_docs)
    before = np.zeros(len(gone), bool)
    before[1:] = gone[:-1] & (words.doc[1:] == words.doc[:-1])
    after = np.zeros(len(gone), bool)
    after[:-1] = gone[1:] & (words.doc[1:] == words.doc[:-1])
    begin, end = np.flatnonzero(gone & ~before), np.flatnonzero(gone & ~after) + 1

    def listed(at: np.ndarray, **columns: np.ndarray) -> pa.Array:
        """A list for each document of structs, each of the document of word `at`."""
        return pa.ListArray.from_arrays(pa.array(np.searchsorted(words.doc[at], np.arange(n_docs + 1)), pa.int32()), pa.StructArray.from_arrays([pa.array(x) for x in columns.values()], list(columns)))

    base = words.first[:-1]
    spans = listed(begin, **{"from": begin - base[words.doc[begin]], "to": end - base[words.doc[begin]]})
    first, last, source = factors
    parsed = listed(first, **{"from": first - base[words.doc[first]], "to": last - base[words.doc[first]], "source": source})
    text = to_strings(*words.joined(~gone))
    if untouched:
        text = pc.if_else(pa.array(removed > 0), text, strings(part.column("text")))
    text = text.cast(pa.string())
    return pa.table({"row": part.column("row"), "n_words": pa.array(words.count, pa.int64()), "n_removed": pa.array(removed, pa.int64()), "spans": spans, "factors": parsed, "kept_text": text})


def op4_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = repeated_spans(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept_text").cast("binary"), 256).alias("kept_sha256"))
