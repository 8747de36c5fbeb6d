"""Which contents of a group of rows occur elsewhere too: entries go to shards by content, answers come back.

A group names each of its contents once: its hash `h`, a second number `v` (63 bits, and a flag in the lowest), and a
place `src`. Contents are the same if (h, v) are. Groups lie in clusters of `CLUSTER`; a task first merges the entries
of a cluster's groups in one of `COARSE` ranges of h, and sends what is distinct to the shard that owns it. A content in
a third of all documents is therefore one entry for each group in a cluster's task and one for each cluster in a shard, never one
for each document. Up to a cluster of groups the second step has nothing to add and is left out.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

ENTRY = np.dtype([("h", "<u8"), ("v", "<u8"), ("src", "<u8")])
#: What comes back for an entry: `again` (another place has the content), `other` (the same h stands with another v), the least other place, and
#: the number of v the h stands with (only if it is asked for, else 0).
ANSWER = np.dtype([("again", "?"), ("other", "?"), ("src", "<u8"), ("kinds", "<u4")])
NOWHERE = np.uint64(2**64 - 1)
COARSE, CLUSTER, FINE = 64, 1024, 16
FLAG, REST = np.uint64(1), np.uint64(2**64 - 2)


def shard_of(h: np.ndarray, shards: int) -> np.ndarray:
    """Grows with h."""
    return ((h >> np.uint64(32)) * np.uint64(shards)) >> np.uint64(32)


class Merged:
    """Distinct contents of entries in order of (h, v), and which of them each entry is."""

    def __init__(self, entries: np.ndarray):
        v = entries["v"] & REST
        order = np.lexsort((entries["src"], v, entries["h"]))
        h, v, src = entries["h"][order], v[order], entries["src"][order]
        new_h = np.ones(len(h), bool)
        new_h[1:] = h[1:] != h[:-1]
        new = new_h.copy()
        new[1:] |= v[1:] != v[:-1]
        self.which = np.empty(len(h), np.int64)
        self.which[order] = np.cumsum(new) - 1
        first = np.flatnonzero(new)
        count = np.diff(np.append(first, len(h)))
        flagged = np.bincount(np.cumsum(new) - 1, (entries["v"][order] & FLAG).astype(float), len(first)) > 0
        self.distinct = np.zeros(len(first), ENTRY)
        self.distinct["h"], self.distinct["src"] = h[first], src[first]
        self.distinct["v"] = v[first] | ((count > 1) | flagged).astype(np.uint64)
        self.second = np.where(count > 1, src[np.minimum(first + 1, max(len(h) - 1, 0))] if len(h) else NOWHERE, NOWHERE)
        kinds = np.bincount(np.cumsum(new_h[first]) - 1, minlength=0) if len(first) else np.zeros(0, np.int64)
        self.kinds = kinds[np.cumsum(new_h[first]) - 1] if len(first) else kinds
        self.other = self.kinds > 1

    def answers(self, entries: np.ndarray, above: np.ndarray | None = None) -> np.ndarray:
        """For each entry what these entries, and the answers from above to the distinct ones, tell of its content."""
        out = np.zeros(len(entries), ANSWER)
        out["again"] = (self.distinct["v"] & FLAG).astype(bool)[self.which]
        out["other"] = self.other[self.which]
        out["kinds"] = self.kinds[self.which]
        least = self.distinct["src"][self.which]
        out["src"] = np.where(least == entries["src"], self.second[self.which], least)
        if above is not None:
            out["again"] |= above["again"][self.which]
            out["other"] |= above["other"][self.which]
            out["kinds"] = np.maximum(out["kinds"], above["kinds"][self.which])
            out["src"] = np.minimum(out["src"], above["src"][self.which])
        return out


def _planes(values: np.ndarray) -> bytes:
    """All first bytes, then all second ones: the equal high bytes of sorted or small numbers lie side by side and compress."""
    return np.ascontiguousarray(values).view(np.uint8).reshape(len(values), values.dtype.itemsize).T.tobytes()


def _from_planes(data: bytes, dtype: str, n: int, at: int) -> np.ndarray:
    wide = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(data, np.uint8, wide * n, at).reshape(wide, n).T).view(dtype)[:, 0]


def _packed(entries: np.ndarray) -> bytes:
    """Column by column: h in planes, then v (or the few values it has and a byte for each entry), and places only where there are any."""
    n, places = len(entries), entries["src"]
    kinds, which = np.unique(entries["v"], return_inverse=True)
    few = len(kinds) <= 256 and 8 * len(kinds) + n < 8 * n
    v = kinds.tobytes() + which.astype(np.uint8).tobytes() if few else entries["v"].tobytes()
    has = bool((places != NOWHERE).any())
    return np.array([n, len(kinds) if few else 0, has], "<u4").tobytes() + _planes(entries["h"]) + v + (places.tobytes() if has else b"")


def _unpacked(blob: bytes) -> np.ndarray:
    n, kinds, has = np.frombuffer(blob, "<u4", 3).tolist()
    out, at = np.zeros(n, ENTRY), 12 + 8 * n

    def column(size: int, dtype=np.uint64) -> np.ndarray:
        nonlocal at
        at += size * np.dtype(dtype).itemsize
        return np.frombuffer(blob, dtype, size, at - size * np.dtype(dtype).itemsize)

    out["h"] = _from_planes(blob, "<u8", n, 12)
    out["v"] = column(kinds)[column(n, np.uint8)] if kinds else column(n)
    out["src"] = column(n) if has else NOWHERE
    return out


def _pack(parts: list[np.ndarray]) -> pa.Array:
    return pa.array([_packed(x) for x in parts], pa.binary())


def packed_answers(answers: np.ndarray, counted: bool = False) -> bytes:
    """Bits of again and other, and the places of those that have one; counted: also the kinds of those with others, low bytes first."""
    has = answers["src"] != NOWHERE
    kinds = _planes(answers["kinds"][answers["other"]]) if counted else b""
    return b"".join(np.packbits(x).tobytes() for x in (answers["again"], answers["other"], has)) + answers["src"][has].tobytes() + kinds


def unpacked_answers(data: bytes, n: int, counted: bool = False) -> np.ndarray:
    out = np.zeros(n, ANSWER)
    wide = (n + 7) // 8
    bits = [np.unpackbits(np.frombuffer(data, np.uint8, wide, i * wide), count=n).astype(bool) for i in range(3)] if n else [np.zeros(0, bool)] * 3
    out["again"], out["other"] = bits[:2]
    out["src"] = NOWHERE
    places, others = int(bits[2].sum()), int(bits[1].sum())
    out["src"][bits[2]] = np.frombuffer(data, np.uint64, places, 3 * wide)
    if counted:
        out["kinds"] = 1
        out["kinds"][bits[1]] = _from_planes(data, "<u4", others, 3 * wide + 8 * places)
    return out


def _split(distinct: np.ndarray, shards: int) -> tuple[list[int], list[np.ndarray]]:
    bounds = np.searchsorted(shard_of(distinct["h"], shards), np.arange(shards + 1))
    full = np.flatnonzero(np.diff(bounds)).tolist()
    return full, [distinct[bounds[i] : bounds[i + 1]] for i in full]


def _read(column) -> tuple[np.ndarray, np.ndarray]:
    """All entries of blobs, and where each blob ends."""
    parts = [_unpacked(blob) for blob in column.to_pylist()]
    return np.concatenate([np.zeros(0, ENTRY), *parts]), np.cumsum([len(x) for x in parts], dtype=np.int64)


def told_to(distinct: np.ndarray, told, counted: bool = False) -> np.ndarray:
    """The answers to a group's distinct entries, in their order; told: its rows (c, items)."""
    by = dict(zip(told.column("c").to_pylist(), told.column("items").to_pylist()))
    full, parts = _split(distinct, COARSE)
    return np.concatenate([np.zeros(0, ANSWER), *[unpacked_answers(by[c], len(x), counted) for c, x in zip(full, parts)]])


def ask(send: Callable[[Callable], DataFrame], groups: int, cluster: int = CLUSTER, fine: int = FINE, counted: bool = False) -> DataFrame:
    """(g, c, items): answers to the entries of each group, for told_to(); counted: with the number of v of each h.

    send(rows) gives the DataFrame (c, s, g, items) of a grouped frame, where rows(g, entries) makes a group's rows.
    """

    def rows(g: int, distinct: np.ndarray) -> pa.Table:
        full, parts = _split(distinct, COARSE)
        n = len(full)
        return pa.table({"c": pa.array(full, pa.int32()), "s": pa.array([g // cluster] * n, pa.int32()), "g": pa.array([g] * n, pa.int64()), "items": _pack(parts)})

    sent = send(rows)
    clusters = -(-groups // cluster)
    shards = COARSE * max(1, clusters // fine)

    def reply(members, above):
        entries, ends = _read(members.column("items"))
        merged = Merged(entries)
        if above is not None:
            by = dict(zip(above.column("f").to_pylist(), above.column("items").to_pylist()))
            full, parts = _split(merged.distinct, shards)
            above = np.concatenate([np.zeros(0, ANSWER), *[unpacked_answers(by[f], len(x), counted) for f, x in zip(full, parts)]])
        found = merged.answers(entries, above)
        starts = np.concatenate(([0], ends))
        return pa.table({"g": members.column("g"), "c": members.column("c"), "items": pa.array([packed_answers(found[a:b], counted) for a, b in zip(starts[:-1].tolist(), starts[1:].tolist())], pa.binary())})

    schema = "g long, c int, items binary"
    if clusters == 1:
        return sent.groupBy("c", "s").applyInArrow(lambda members: reply(members, None), schema)

    def up(members):
        distinct = Merged(_read(members.column("items"))[0]).distinct
        full, parts = _split(distinct, shards)
        n = len(full)
        return pa.table({"f": pa.array(full, pa.int32()), "c": pa.array([members.column("c")[0].as_py()] * n, pa.int32()), "s": pa.array([members.column("s")[0].as_py()] * n, pa.int32()), "items": _pack(parts)})

    def down(members):
        entries, ends = _read(members.column("items"))
        found = Merged(entries).answers(entries)
        starts = np.concatenate(([0], ends))
        return pa.table({"c": members.column("c"), "s": members.column("s"), "f": members.column("f"), "items": pa.array([packed_answers(found[a:b], counted) for a, b in zip(starts[:-1].tolist(), starts[1:].tolist())], pa.binary())})

    above = sent.groupBy("c", "s").applyInArrow(up, "f int, c int, s int, items binary").groupBy("f").applyInArrow(down, "c int, s int, f int, items binary")
    return sent.groupBy("c", "s").cogroup(above.groupBy("c", "s")).applyInArrow(reply, schema)
