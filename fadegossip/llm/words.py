"""Vectorised word handling on Arrow string columns.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D, which on UTF-8 is the same as a maximal run of
such characters. All loops over words are NumPy operations on the bytes of a chunk of documents.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from fadegossip.llm.frames import CHUNK_BYTES

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

_RANDOM = np.random.default_rng(20240229)
BYTE_CODE = _RANDOM.integers(1, 2**63, 256, dtype=np.uint64)
BYTE_BASE, WORD_BASE, WORD_BASE_2 = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F))


def strings(column) -> pa.Array:
    """One large_string array without nulls."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.string())
    return pc.fill_null(column.cast(pa.large_string()), "")


def raw(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (starting at 0) of a large_string array."""
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    body = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return body, offsets - offsets[0]


def chunked(batch, column: str, limit: int = CHUNK_BYTES, most: int = 1 << 16) -> Iterator:
    """Slices of a batch or table of about `limit` bytes of text and `most` rows; a longer document is a slice of its own."""
    n = batch.num_rows
    if not n:
        return
    size = pc.binary_length(batch.column(column))
    size = np.asarray(pc.fill_null(size.combine_chunks() if isinstance(size, pa.ChunkedArray) else size, 0).to_numpy(zero_copy_only=False), np.int64)
    upto = np.cumsum(size)
    at = 0
    while at < n:
        base = upto[at - 1] if at else 0
        end = min(max(at + 1, int(np.searchsorted(upto, base + limit, "right"))), at + most)
        yield batch.slice(at, end - at)
        at = end


# fixed values: the multipliers of XXH64
_P1, _P2, _P3, _P4, _P5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))


def _turned(x: np.ndarray, n: int) -> np.ndarray:
    return x << np.uint64(n) | x >> np.uint64(64 - n)


def xxh64(body: np.ndarray, start: np.ndarray, end: np.ndarray, seed: int) -> np.ndarray:
    """XXH64 of body[start:end] for any spans at once: stripes, lanes and tails are steps over all spans that have them."""
    data = np.concatenate((np.ascontiguousarray(body), np.zeros(8, np.uint8)))
    eight = np.ndarray(len(body) + 1, "<u8", data, strides=(1,))
    four = np.ndarray(len(body) + 1, "<u4", data, strides=(1,))
    size = end - start
    lane = lambda acc, x: _turned(acc + x * _P2, 31) * _P1
    out = np.full(len(start), np.uint64(seed) + _P5, np.uint64)
    at = start.copy()
    wide = np.flatnonzero(size >= 32)
    if len(wide):
        seeds = np.array([seed], np.uint64)
        accs = [np.repeat(x, len(wide)) for x in (seeds + _P1 + _P2, seeds + _P2, seeds, seeds - _P1)]
        left = size[wide].copy()
        on = np.arange(len(wide))
        while len(on):
            for i in range(4):
                accs[i][on] = lane(accs[i][on], eight[at[wide[on]] + 8 * i])
            at[wide[on]] += 32
            left[on] -= 32
            on = on[left[on] >= 32]
        acc = sum((_turned(x, n) for x, n in zip(accs[1:], (7, 12, 18))), _turned(accs[0], 1))
        for x in accs:
            acc = (acc ^ lane(np.uint64(0), x)) * _P1 + _P4
        out[wide] = acc
    out += size.astype(np.uint64)
    while len(on := np.flatnonzero(end - at >= 8)):
        out[on] = _turned(out[on] ^ lane(np.uint64(0), eight[at[on]]), 27) * _P1 + _P4
        at[on] += 8
    on = np.flatnonzero(end - at >= 4)
    out[on] = _turned(out[on] ^ four[at[on]].astype(np.uint64) * _P1, 23) * _P2 + _P3
    at[on] += 4
    while len(on := np.flatnonzero(end > at)):
        out[on] = _turned(out[on] ^ data[at[on]].astype(np.uint64) * _P5, 11) * _P1
        at[on] += 1
    out = (out ^ out >> np.uint64(33)) * _P2
    out = (out ^ out >> np.uint64(29)) * _P3
    return out ^ out >> np.uint64(32)


def powers(base: np.uint64, n: int) -> np.ndarray:
    out = np.full(n + 1, base, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


def inverse(base: np.uint64) -> np.uint64:
    return np.uint64(pow(int(base), -1, 2**64))


_POWERS: dict[int, np.ndarray] = {}


def _kept_powers(base: np.uint64, n: int) -> np.ndarray:
    have = _POWERS.get(int(base))
    if have is None or len(have) <= n:
        have = powers(base, max(n, 1 << 16) * 5 // 4)
        if n <= 4 * CHUNK_BYTES:
            _POWERS[int(base)] = have
    return have


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of 64 bits."""
    x = x ^ (x >> np.uint64(33))
    x *= np.uint64(0xFF51AFD7ED558CCD)
    x ^= x >> np.uint64(33)
    x *= np.uint64(0xC4CEB9FE1A85EC53)
    x ^= x >> np.uint64(33)
    return x


class Spans:
    """Polynomial hashes of codes[start:end] for any spans, from one prefix sum modulo 2**64."""

    def __init__(self, codes: np.ndarray, base: np.uint64):
        n = len(codes)
        self.total = np.zeros(n + 1, np.uint64)
        np.cumsum(codes * _kept_powers(base, n)[:n], out=self.total[1:])
        self.back = _kept_powers(inverse(base), n)

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        return mix((self.total[end] - self.total[start]) * self.back[start])


def span_hashes(codes: np.ndarray, base: np.uint64, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    return Spans(codes, base).of(start, end)


def least_in_windows(values: np.ndarray, span: int) -> np.ndarray:
    """For each start the position of the least of `span` values, the leftmost of equals. Starts near the end are clipped."""
    n = len(values)
    at, reach = np.arange(n), 1

    def better(left: np.ndarray, step: int) -> np.ndarray:
        right = left.copy()
        right[: n - step] = left[step:]
        return np.where(values[right] < values[left], right, left)

    while 2 * reach <= span:
        at, reach = better(at, reach), 2 * reach
    return better(at, span - reach) if reach < span else at


class Words:
    """The words of a chunk of documents: byte ranges, document of each word, first word of each document."""

    def __init__(self, texts: pa.Array, lower: bool = False, space: np.ndarray = SPACE):
        body, self.offsets = raw(texts)
        self.body = LOWER[body] if lower else body
        inside = ~space[self.body]
        n = len(body)
        edge = self.offsets[:-1][self.offsets[:-1] < n]
        before = np.zeros(n, bool)
        before[1:] = inside[:-1]
        before[edge] = False
        self.start = np.flatnonzero(inside & ~before)
        after = np.zeros(n, bool)
        after[:-1] = inside[1:]
        after[edge[edge > 0] - 1] = False
        self.end = np.flatnonzero(inside & ~after) + 1
        self.first = np.searchsorted(self.start, self.offsets)
        self.count = np.diff(self.first)
        self.doc = np.repeat(np.arange(len(self.count)), self.count)

    def spans(self) -> Spans:
        """Hashes of any byte ranges."""
        return Spans(BYTE_CODE[self.body], BYTE_BASE)

    def hashes(self) -> np.ndarray:
        return self.spans().of(self.start, self.end)

    def starts_of(self, k: int) -> np.ndarray:
        """Word indexes at which k consecutive words of one document start."""
        n = len(self.doc)
        if n < k:
            return np.zeros(0, np.int64)
        return np.flatnonzero(self.doc[k - 1 :] == self.doc[: n - k + 1])

    def joined(self, keep: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of the kept words, one space between words of a document, and the document offsets."""
        start, end, doc = (self.start, self.end, self.doc) if keep is None else (self.start[keep], self.end[keep], self.doc[keep])
        length = end - start + 1
        stop = np.cumsum(length)
        out = np.append(self.body, np.uint8(32))[np.repeat(start - (stop - length), length) + np.arange(stop[-1] if len(stop) else 0)]
        out[stop - 1] = 32
        last = np.searchsorted(doc, np.arange(len(self.count)), "right")
        ends = np.concatenate(([0], stop))[last]
        has = np.diff(np.concatenate(([0], last))) > 0
        # the space behind the last word of a document goes
        drop = ends[has] - 1
        out = np.delete(out, drop)
        return out, np.concatenate(([0], ends - np.cumsum(has)))


def to_strings(body: np.ndarray, offsets: np.ndarray) -> pa.Array:
    return pa.LargeStringArray.from_buffers(len(offsets) - 1, pa.py_buffer(np.ascontiguousarray(offsets, np.int64)), pa.py_buffer(np.ascontiguousarray(body)))
