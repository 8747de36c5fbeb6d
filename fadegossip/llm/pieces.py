"""SentencePiece encoding and decoding: Unigram Viterbi over a double-array trie.

A piece model file is read with the public library; matching, search and decoding are done here, vectorised over
the distinct segments of a chunk of documents. Inside this module the whitespace marker is one byte (0xFF, which
UTF-8 never uses), so a marker that stands literally in a text is an ordinary character: it has no piece, falls
back to bytes and survives decoding. Encoding then loses nothing: decode(encode(text)) == text for every string.

Search is exact on whole texts. No piece has a marker behind another character, so every best path breaks
before each run of markers; segments between these breaks are searched once per chunk however often they occur.
Ties go to the path whose last piece starts first.
"""

from __future__ import annotations

import hashlib
import os
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.llm.frames import table
from fadegossip.llm.words import BYTE_CODE, BYTE_BASE, chunked, raw, span_hashes, strings

#: Default place of the public piece model; a parameter everywhere.
MODEL = "/opt/tokenizers/piece_bpe_32k.model"
MARK = 0xFF
UNKNOWN_PENALTY = 10.0
#: Segments up to this many bytes are searched side by side, longer ones one by one.
SHORT = 64
CHUNK = 1 << 19


class DoubleArray:
    """Trie over byte strings: child(state, c) = base[state] + c if check[child] == state."""

    def __init__(self, keys: list[bytes]):
        children: list[dict[int, int]] = [{}]
        ends: dict[int, int] = {}
        for i, key in enumerate(keys):
            node = 0
            for c in key:
                nxt = children[node].get(c)
                if nxt is None:
                    nxt = children[node][c] = len(children)
                    children.append({})
                node = nxt
            ends[node] = i
        size = len(children) * 2 + 1024
        base, check, value = np.zeros(size, np.int32), np.full(size, -1, np.int32), np.full(size, -1, np.int32)
        used = bytearray(size)
        used[0] = 1
        place, queue = {0: 0}, [0]
        tried: dict[tuple[int, int], int] = {}  # by number of children and first code, where the search for a place goes on
        # dense nodes first, so that the many single children fill the holes
        while queue:
            later = []
            for node in sorted(queue, key=lambda x: -len(children[x])):
                kids = children[node]
                if not kids:
                    continue
                codes = sorted(kids)
                at = tried.get((len(codes), codes[0]), 1)
                while True:
                    free = used.find(0, at + codes[0])
                    if free < 0 or free + 300 > len(used):
                        grow = len(used)
                        used.extend(bytearray(grow))
                        base, check, value = np.append(base, np.zeros(grow, np.int32)), np.append(check, np.full(grow, -1, np.int32)), np.append(value, np.full(grow, -1, np.int32))
                        continue
                    at = free - codes[0]
                    if not any(used[at + c] for c in codes[1:]):
                        break
                    at += 1
                base[place[node]] = tried[len(codes), codes[0]] = at
                for c in codes:
                    spot, kid = at + c, kids[c]
                    used[spot], check[spot], place[kid] = 1, place[node], spot
                    value[spot] = ends.get(kid, -1)
                    later.append(kid)
            queue = later
        self.base, self.check, self.value = (np.append(x, np.full(300, -1, np.int32)) for x in (base, check, value))
        self.base[-300:] = 0

    def matches(self, body: np.ndarray, start: np.ndarray, limit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All keys that body holds from each start on, not beyond its limit: (start, end, key number)."""
        at, pos, stop, state = start, start, limit, np.zeros(len(start), np.int32)
        out = []
        while len(at):
            nxt = self.base[state] + body[pos]
            ok = self.check[nxt] == state
            at, pos, stop, state = at[ok], pos[ok] + 1, stop[ok], nxt[ok]
            found = self.value[state]
            hit = found >= 0
            out.append((at[hit], pos[hit], found[hit]))
            on = pos < stop
            at, pos, stop, state = at[on], pos[on], stop[on], state[on]
        return tuple(np.concatenate([x[i] for x in out]) if out else np.zeros(0, np.int64) for i in range(3))


def _fields(data: bytes):
    """(number, value) of a protocol-buffer message."""
    at = 0

    def varint():
        nonlocal at
        out = shift = 0
        while True:
            b = data[at]
            at += 1
            out |= (b & 127) << shift
            shift += 7
            if b < 128:
                return out

    while at < len(data):
        tag = varint()
        kind = tag & 7
        if kind == 0:
            yield tag >> 3, varint()
        else:
            n = varint() if kind == 2 else {1: 8, 5: 4}[kind]
            yield tag >> 3, data[at : at + n]
            at += n


class Pieces:
    """Pieces, log scores, trie and byte fallback of a model file (bytes of a `ModelProto`)."""

    def __init__(self, proto: bytes):
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_proto=proto)
        size = model.get_piece_size()
        rules = dict(x for number, value in _fields(proto) if number == 3 for x in _fields(value))
        if rules.get(2) or rules.get(4, 1):
            raise ValueError("the model rewrites its input (character map or extra white space); exact decoding needs one that doesn't")
        self.prefix = bool(rules.get(3, 1))
        self.score = np.array([model.get_score(i) for i in range(size)], np.float64)
        self.byte_id = np.full(256, model.unk_id(), np.int32)
        text: list[bytes] = [b""] * size
        ids, keys = [], []
        for i in range(size):
            piece = model.id_to_piece(i)
            if model.is_byte(i):
                b = int(piece[3:5], 16)
                self.byte_id[b], text[i] = i, bytes([b])
            elif not (model.is_control(i) or model.is_unknown(i) or model.is_unused(i)):
                key = b"\xff".join(x.encode() for x in piece.split("▁"))
                ids.append(i)
                keys.append(key)
                text[i] = key.replace(b"\xff", b" ")
        if (self.byte_id == model.unk_id()).any():
            raise ValueError("the model has no byte fallback")
        self.breaks = not any(b"\xff" in k.lstrip(b"\xff") for k in keys)
        self.ids = np.array(ids, np.int32)
        self.unknown = float(self.score[self.ids].min() - UNKNOWN_PENALTY)
        self.trie = DoubleArray(keys)
        length = np.array([len(x) for x in text], np.int64)
        self.text_at = np.concatenate(([0], np.cumsum(length)))
        self.text = np.frombuffer(b"".join(text), np.uint8)
        self.is_fallback = np.zeros(size, bool)
        self.is_fallback[self.byte_id] = True

    # -- search ------------------------------------------------------------------------------------------------

    def _paths(self, body: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Best pieces of every segment body[bounds[i]:bounds[i+1]]: ids, and how many each segment has."""
        n, size = len(body), np.diff(bounds)
        segment = np.repeat(np.arange(len(size)), size)
        char = np.flatnonzero((body & 0xC0) != 0x80)
        char_end = np.append(char[1:], n)  # segments start and end at characters
        s, e, k = self.trie.matches(body, char, bounds[1:][segment[char]])
        width = np.zeros(n + 1, np.int64)
        width[char] = char_end - char
        single = np.zeros(n + 1, bool)
        single[s[e - s == width[s]]] = True
        odd = ~single[char]
        s, e = np.concatenate((s, char[odd])), np.concatenate((e, char_end[odd]))
        ids = np.concatenate((self.ids[k], np.full(int(odd.sum()), -1, np.int32)))
        gain = np.where(ids >= 0, self.score[ids], self.unknown)
        seg = segment[s]
        step = e - bounds[seg]
        # rows end + segment number: every segment has a node before its first byte
        from_, to = s + seg, e + seg
        best, back = np.full(n + len(size), -np.inf), np.full(n + len(size), -1, np.int64)
        best[bounds[:-1] + np.arange(len(size))] = 0
        long = size[seg] > SHORT
        order = np.lexsort((from_, to, step, long))
        from_, to, gain, step = from_[order], to[order], gain[order], step[order]
        n_short = int((~long).sum())
        cuts = np.searchsorted(step[:n_short], np.arange(1, SHORT + 2))
        for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist()):
            if a == b:
                continue
            t = to[a:b]
            value = best[from_[a:b]] + gain[a:b]
            first = np.flatnonzero(np.concatenate(([True], t[1:] != t[:-1])))
            top = np.maximum.reduceat(value, first)
            best[t[first]] = top
            win = np.flatnonzero(value == np.repeat(top, np.diff(np.append(first, b - a))))[::-1]
            back[t[win]] = win + a
        if n_short < len(to):
            # long segments one edge after another, ordered by end
            rest = np.argsort(to[n_short:], kind="stable") + n_short
            known: dict[int, float] = {}
            for i, f, t, g in zip(rest.tolist(), from_[rest].tolist(), to[rest].tolist(), gain[rest].tolist()):
                v = (known[f] if f in known else best[f]) + g
                if v > known.get(t, -np.inf):
                    known[t] = v
                    back[t] = i
        at = bounds[1:] + np.arange(len(size))
        floor = bounds[:-1] + np.arange(len(size))
        live = at > floor
        at, floor, who = at[live], floor[live], np.flatnonzero(live)
        picked, owner = [], []
        slow = size[who] > SHORT
        for a, f, w in zip(at[slow].tolist(), floor[slow].tolist(), who[slow].tolist()):
            way = []
            while a > f:
                way.append(back[a])
                a = from_[way[-1]]
            picked.append(np.array(way, np.int64))
            owner.append(np.full(len(way), w))
        at, floor, who = at[~slow], floor[~slow], who[~slow]
        while len(at):
            edge = back[at]
            picked.append(edge)
            owner.append(who)
            at = from_[edge]
            on = at > floor
            at, floor, who = at[on], floor[on], who[on]
        if not picked:
            return np.zeros(0, np.int32), np.zeros(len(size), np.int64)
        edge, owner = np.concatenate(picked), np.concatenate(owner)
        turn = np.argsort(from_[edge])
        edge, owner = edge[turn], owner[turn]
        chosen = ids[order][edge]
        begin, span = from_[edge] - owner, to[edge] - from_[edge]
        times = np.where(chosen < 0, span, 1)
        out = np.repeat(chosen, times)
        stop = np.cumsum(times)
        inner = np.arange(len(out)) - np.repeat(stop - times, times)
        fallen = out < 0
        out[fallen] = self.byte_id[body[(np.repeat(begin, times) + inner)[fallen]]]
        return out, np.bincount(np.repeat(owner, times), minlength=len(size))

    def encode(self, texts: pa.Array) -> pa.Array:
        """list<int32> of piece ids for each text of a large_string array."""
        body, offsets = raw(texts)
        size = np.diff(offsets)
        lead = (size > 0).astype(np.int64) if self.prefix else np.zeros(len(size), np.int64)
        at = offsets + np.concatenate(([0], np.cumsum(lead)))
        inner = np.full(at[-1], MARK, np.uint8)
        keep = np.ones(at[-1], bool)
        keep[at[:-1][lead > 0]] = False
        inner[keep] = np.where(body == 0x20, MARK, body)
        starts = np.zeros(at[-1], bool)
        starts[at[:-1][np.diff(at) > 0]] = True
        if self.breaks:
            mark = inner == MARK
            starts[1:] |= mark[1:] & ~mark[:-1]
        begin = np.flatnonzero(starts)
        end = np.append(begin[1:], at[-1])[: len(begin)]
        if not len(begin):
            return pa.array([[]] * len(size), pa.list_(pa.int32()))
        name = span_hashes(BYTE_CODE[inner], BYTE_BASE, begin, end)
        _, first, which = np.unique(name, return_index=True, return_inverse=True)
        length = end[first] - begin[first]
        bounds = np.concatenate(([0], np.cumsum(length)))
        pool = inner[np.repeat(begin[first] - bounds[:-1], length) + np.arange(bounds[-1])]
        ids, count = self._paths(pool, bounds)
        stop = np.cumsum(count)
        n = count[which]
        upto = np.concatenate(([0], np.cumsum(n)))
        out = ids[np.repeat((stop - count)[which] - upto[:-1], n) + np.arange(upto[-1])]
        return pa.ListArray.from_arrays(pa.array(upto[np.searchsorted(begin, at)], pa.int32()), pa.array(out, pa.int32()))

    def decode(self, ids: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Bytes and offsets of the texts of list<int32> rows; the marker in front is taken away, nulls are empty."""
        if isinstance(ids, pa.ChunkedArray):
            ids = ids.combine_chunks()
        flat = np.asarray(ids.flatten().to_numpy(zero_copy_only=False), np.int64)
        rows = np.concatenate(([0], np.cumsum(np.asarray(pa.compute.fill_null(pa.compute.list_value_length(ids), 0)))))
        length = self.text_at[flat + 1] - self.text_at[flat]
        stop = np.concatenate(([0], np.cumsum(length)))
        out = self.text[np.repeat(self.text_at[flat] - stop[:-1], length) + np.arange(stop[-1])]
        offsets = stop[rows]
        if self.prefix:
            has = np.diff(offsets) > 0
            first = offsets[:-1][has]
            lead = first[out[first] == 0x20]
            out = np.delete(out, lead)
            offsets = offsets - np.searchsorted(lead, offsets)
        return out, offsets


def load(spark: SparkSession, model: str = MODEL) -> Pieces:
    """Reads a model file of bounded size on the driver, once for each file and process; tasks get it with their code."""
    facts = os.stat(model)
    return _loaded(model, facts.st_size, facts.st_mtime_ns)


@lru_cache(maxsize=4)
def _loaded(model: str, size: int, changed: int) -> Pieces:
    with open(model, "rb") as f:
        return Pieces(f.read())


def encode(docs: DataFrame, pieces: Pieces, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens, n_fallback, ids): pieces of every whole text, null texts as empty, empty texts without a piece."""
    kind = docs.schema[id_col].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(pieces)  # a fixed vocabulary, about two MB

    def run(batches):
        model = shared.value
        for batch in batches:
            for part in chunked(batch, "t", CHUNK):
                ids = model.encode(strings(part.column("t")))
                flat = np.asarray(ids.values)
                upto = np.concatenate(([0], np.cumsum(model.is_fallback[flat])))
                offsets = np.asarray(ids.offsets)
                yield pa.RecordBatch.from_arrays([part.column("i"), pa.array(np.diff(offsets), pa.int64()), pa.array(np.diff(upto[offsets]), pa.int64()), ids], ["i", "n_tokens", "n_fallback", "ids"])

    return docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).mapInArrow(run, f"i {kind}, n_tokens long, n_fallback long, ids array<int>").withColumnRenamed("i", id_col)


def decode(encoded: DataFrame, pieces: Pieces, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, text). Byte sequences that are no UTF-8 become replacement characters, as in the library."""
    kind = encoded.schema[id_col].dataType.simpleString()
    shared = encoded.sparkSession.sparkContext.broadcast(pieces)

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                body, offsets = shared.value.decode(part.column("k"))
                data = body.tobytes()
                yield pa.RecordBatch.from_arrays([part.column("i"), pa.array([data[a:b].decode("utf-8", "replace") for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist())], pa.string())], ["i", "text"])

    return encoded.select(F.col(id_col).alias("i"), F.col(ids_col).alias("k")).mapInArrow(run, f"i {kind}, text string").withColumnRenamed("i", id_col)


def encode_checked(docs: DataFrame, pieces: Pieces) -> DataFrame:
    """encode() of (doc_id, text), each row with the digest of its decoded text and whether that is the text.

    Null texts count as empty and have no piece; null ids and repeated rows are carried; a text of any length is encoded
    whole; of paths with equal scores that whose last piece starts first is taken; other columns of any name change nothing.
    """
    kind = docs.schema["doc_id"].dataType.simpleString()
    shared = docs.sparkSession.sparkContext.broadcast(pieces)

    def run(batches):
        model = shared.value
        for batch in batches:
            for part in chunked(batch, "text", CHUNK):
                texts = strings(part.column("text"))
                ids = model.encode(texts)
                offsets, flat = np.asarray(ids.offsets), np.asarray(ids.values)
                upto = np.concatenate(([0], np.cumsum(model.is_fallback[flat])))
                body, at = model.decode(ids)
                own, own_at = raw(texts)
                data, source = body.tobytes(), own.tobytes()
                back = [data[a:b] for a, b in zip(at[:-1].tolist(), at[1:].tolist())]
                same = [x == source[a:b] for x, a, b in zip(back, own_at[:-1].tolist(), own_at[1:].tolist())]
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(np.diff(offsets), pa.int64()), pa.array(np.diff(upto[offsets]), pa.int64()), ids, pa.array([hashlib.sha256(x).hexdigest() for x in back]), pa.array(same)],
                    ["doc_id", "n_tokens", "n_fallback", "ids", "decoded_sha256", "round_trip"],
                )

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_tokens long, n_fallback long, ids array<int>, decoded_sha256 string, round_trip boolean")


def op1_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_checked(table(spark, sf_dir, "documents"), load(spark))
