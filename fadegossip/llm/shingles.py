"""Near copies by exact Jaccard similarity of word shingles: every pair that reaches the threshold is found.

Two sets of similarity 4/5 share at least four fifths of the larger, so in any common order of the shingles their
first fifths (`prefix`) meet. Frequent shingles, as a bounded sample of texts counts them, come last in that order;
the sample decides the cost, never the result. Texts of equal sets are one node, and prefixes are dealt by shingle.

Links come first from SimHash: fingerprints of the same shingles meet in the covering tables of `simhash`, which miss no
pair within its radius, and each text is settled with the likeliest of those it is linked to. Pairs of the least
similarity are about ten bits apart, so the rest comes from the prefixes. A bucket
links its members to the one with the fewest shingles before the bucket's (a star around the text
that the others are edits of), and each member is settled with the likeliest of its centres, so large groups are
joined by a pair for each member. Then all pairs of a bucket whose ends are still in different components are looked
at: sizes, places of the shingle and parity sketches rule out nearly all that don't reach the threshold, and never one
that does. That happens inside the bucket's task; only what is left becomes a row and is settled on the sets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fadegossip.llm.components import components
from fadegossip.llm.frames import cut, shuffle_width
from fadegossip.llm.simhash import RADIUS, fingerprints_of, links
from fadegossip.llm.words import BYTE_BASE, BYTE_CODE, Words, chunked, span_hashes, strings

#: Words of a shingle; the least similarity is PART / WHOLE.
SHINGLE_WORDS, PART, WHOLE = 5, 4, 5
#: Texts whose shingles are counted, least count and number of those that come last in the order.
SAMPLE, FREQUENT, LAST = 10_000, 5, 1 << 16
#: Members of a bucket, and followers of a centre, that one task takes together.
BLOCK, FOLLOWERS = 2048, 512
#: Rows that name wanted texts are broadcast up to this number.
WANTED = 200_000
#: Links of which a round of their components runs in one task.
FEW = 50_000
#: Rows that wait for a batch, and tasks over which the rows of one set are dealt.
HELD, SALTS = 16_384, 16


def sets_of(texts: pa.Array, k: int = SHINGLE_WORDS) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each text, one after the other, and the offsets of the texts.

    A text of fewer than k words is one shingle; ASCII letters count as small ones.
    """
    words = Words(texts, lower=True)
    body, offsets = words.joined()
    length = words.end - words.start
    stop = np.cumsum(length + 1)
    skipped = np.cumsum(words.count > 0) - (words.count > 0)
    start = stop - length - 1 - skipped[words.doc]
    end = start + length
    at = words.starts_of(k)
    short = np.flatnonzero((words.count > 0) & (words.count < k))
    begin = np.concatenate((start[at], offsets[short])).astype(np.int64)
    until = np.concatenate((end[at + k - 1], offsets[short + 1])).astype(np.int64)
    doc = np.concatenate((words.doc[at], short)).astype(np.int64)
    hashed = span_hashes(BYTE_CODE[body], BYTE_BASE, begin, until)
    order = np.lexsort((hashed, doc))
    hashed, doc = hashed[order], doc[order]
    fresh = np.ones(len(doc), bool)
    fresh[1:] = (hashed[1:] != hashed[:-1]) | (doc[1:] != doc[:-1])
    hashed, doc = hashed[fresh], doc[fresh]
    return hashed, np.searchsorted(doc, np.arange(len(words.count) + 1))


def prefix_size(n: np.ndarray) -> np.ndarray:
    return np.where(n > 0, n - (PART * n + WHOLE - 1) // WHOLE + 1, 0)


def prefixes(values: np.ndarray, offsets: np.ndarray, last: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first shingles of each set and their offsets; `last` (sorted) come behind all others, by their rank."""
    n = np.diff(offsets)
    place = np.zeros(len(values), np.int64)
    if len(last):
        at = np.minimum(np.searchsorted(last, values), len(last) - 1)
        place = np.where(last[at] == values, rank[at], 0)
    doc = np.repeat(np.arange(len(n)), n)
    order = np.lexsort((values, place, doc))
    take = np.arange(len(values)) - np.repeat(offsets[:-1], n) < np.repeat(prefix_size(n), n)
    return values[order][take], np.concatenate(([0], np.cumsum(prefix_size(n))))


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether two sorted sets reach the threshold."""
    if not len(a) or not len(b):
        return len(a) == len(b)
    both = int((a[np.minimum(np.searchsorted(a, b), len(a) - 1)] == b).sum())
    return WHOLE * both >= PART * (len(a) + len(b) - both)


def sketch(own: np.ndarray) -> bytes:
    """Of each class of hashes with equal low bits whether it has an odd number; at least as many classes as hashes."""
    m = 1 << max(6, len(own).bit_length())
    return np.packbits(np.bincount((own & np.uint64(m - 1)).astype(np.int64), minlength=m) & 1, bitorder="little").tobytes()


def differ(a: bytes, b: bytes) -> int:
    """A number of shingles in which the sets of two sketches differ at least."""
    x, y = np.frombuffer(a, np.uint8), np.frombuffer(b, np.uint8)
    while len(x) > len(y):
        x = x[: len(x) // 2] ^ x[len(x) // 2 :]
    while len(y) > len(x):
        y = y[: len(y) // 2] ^ y[len(y) // 2 :]
    return int(np.bitwise_count(x ^ y).sum())


def _frequent(docs: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Hashes, sorted, of the most frequent shingles of a sample of distinct texts, and their ranks from 1."""
    every = max(docs.count() // SAMPLE, 1)
    some = docs.select(F.col("text").alias("t")).where(F.col("t").isNotNull() & (F.pmod(F.xxhash64("t"), F.lit(every)) == 0)).distinct()

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "t"):
                h, n = np.unique(sets_of(strings(part.column("t")))[0], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(n)], ["h", "n"])

    found = some.mapInArrow(run, "h long, n long").groupBy("h").agg(F.sum("n").alias("n")).where(F.col("n") >= FREQUENT).orderBy(F.col("n").desc(), "h").limit(LAST)
    rows = found.collect()
    hashes = np.array([r.h for r in rows], np.int64).view(np.uint64)
    order = np.argsort(hashes)
    return hashes[order], (len(rows) - np.arange(len(rows)))[order]


def _gathered(found: Iterator[tuple], names: list[str]) -> Iterator[pa.RecordBatch]:
    """Batches of the distinct rows of some thousand tuples of arrays; `HELD` bounds what waits."""

    def batch() -> pa.RecordBatch:
        columns = [np.concatenate(y) for y in zip(*parts)]
        order = np.lexsort(columns)
        columns = [c[order] for c in columns]
        fresh = np.zeros(len(order), bool)
        fresh[:1] = True
        for c in columns:
            fresh[1:] |= c[1:] != c[:-1]
        return pa.RecordBatch.from_arrays([pa.array(c[fresh]) for c in columns], names)

    parts, held = [], 0
    for x in found:
        parts.append(x)
        held += len(x[0])
        if held > HELD or len(parts) > HELD // 8:
            yield batch()
            parts, held = [], 0
    if parts:
        yield batch()


def _fits(n: np.ndarray, pos: np.ndarray, n0: int, pos0: int) -> np.ndarray:
    """Whether sizes, and what may follow a common shingle at these places, allow the threshold."""
    size = WHOLE * np.minimum(n, n0) >= PART * np.maximum(n, n0)
    # before their first common shingle sets have none in common
    return size & ((WHOLE + PART) * np.minimum(n - pos, n0 - pos0) >= PART * (n + n0))


def _shared(batches):
    """(kind, h, sid, pos, n) of rows sorted by h, pos, n, sid: 1 for the rows of buckets with two members or more, 0 for stars.

    A star is a pair of a centre (as h) and a member (as sid); a size that no centre can reach gets a centre of its own.
    """
    names = ["kind", "h", "sid", "pos", "n"]

    def batch_of(kind: int, columns: list[np.ndarray]) -> pa.RecordBatch:
        n = len(columns[0])
        return pa.RecordBatch.from_arrays([pa.array(np.full(n, kind), pa.int32()), *[pa.array(x, pa.int64()) for x in columns[:2]], *[pa.array(x, pa.int32()) for x in columns[2:]]], names)

    def members(data: list[np.ndarray], held: list[np.ndarray] | None):
        """Rows of this batch, and the one that waits from the batch before, that have a fellow."""
        if held is not None:
            data = [np.concatenate(x) for x in zip(held, data)]
        same = data[0][1:] == data[0][:-1]
        return data, np.concatenate((same, [False])) | np.concatenate(([False], same))

    held, fellow = None, False  # the last row, and whether it is known to have a fellow
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    waiting = 0
    now, centres = None, []
    for batch in batches:
        h, pos, n, sid = (np.asarray(batch.column(c)) for c in ("h", "pos", "n", "sid"))
        if not len(h):
            continue
        data, keep = members([h, sid, pos, n], held)
        if held is not None:
            keep[0] |= fellow
        fellow, held = bool(keep[-1]), [x[-1:] for x in data]
        keep[-1] = False  # it waits for the next batch
        if keep.any():
            yield batch_of(1, [x[keep] for x in data])
        bounds = np.concatenate(([0], np.flatnonzero(h[1:] != h[:-1]) + 1, [len(h)]))
        size = np.diff(bounds)
        size[[0, -1]] = 2  # a bucket may go over batch ends
        for k in np.flatnonzero(size > 1).tolist():
            start, end = bounds[k], bounds[k + 1]
            if h[start] != now:
                now, centres = h[start], []
            open_ = np.ones(end - start, bool)
            at = 0
            while open_.any():
                if at == len(centres):
                    i = int(np.argmax(open_))
                    open_[i] = False
                    centres.append((int(n[start + i]), int(pos[start + i]), sid[start + i]))
                n0, pos0, sid0 = centres[at]
                own_n = n[start:end].astype(np.int64)
                hit = open_ & _fits(own_n, pos[start:end].astype(np.int64), n0, pos0)
                open_ &= WHOLE * np.minimum(own_n, n0) < PART * np.maximum(own_n, n0)
                if hit.any():
                    pairs.append((np.repeat(sid0, int(hit.sum())), sid[start:end][hit]))
                    waiting += int(hit.sum())
                at += 1
        if waiting > HELD:
            yield _stars(pairs, batch_of)
            pairs, waiting = [], 0
    if held is not None and fellow:
        yield batch_of(1, held)
    if pairs:
        yield _stars(pairs, batch_of)


def _stars(pairs: list[tuple[np.ndarray, np.ndarray]], batch_of) -> pa.RecordBatch:
    """The distinct ones."""
    both = np.unique(np.column_stack([np.concatenate([p[0] for p in pairs]), np.concatenate([p[1] for p in pairs])]), axis=0)
    zero = np.zeros(len(both), np.int32)
    return batch_of(0, [both[:, 0], both[:, 1], zero, zero])


def _folded(x: np.ndarray) -> np.ndarray:
    """Sketches (rows of bytes) with half as many classes."""
    half = x.shape[1] // 2
    return x[:, :half] ^ x[:, half:]


def _pairs(pos, n, sid, root, drawn) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs in different components that sizes, places and sketches allow."""
    order = np.lexsort((sid, n))
    pos, n, sid, root = pos[order], n[order], sid[order], root[order]
    drawn = [drawn[i] for i in order.tolist()]
    wide = np.array([len(x) for x in drawn])  # grows with n
    own = {w: np.frombuffer(b"".join(x for x in drawn if len(x) == w), np.uint8).reshape(-1, w) for w in np.unique(wide).tolist()}
    first = {w: int(np.searchsorted(wide, w)) for w in own}
    half = {w: _folded(own[w]) for w in own if w // 2 in own}
    for x in range(len(n) - 1):
        most = int(np.searchsorted(PART * n, WHOLE * n[x], "right"))
        other = x + 1 + np.flatnonzero((root[x + 1 : most] != root[x]) & _fits(n[x + 1 : most], pos[x + 1 : most], n[x], pos[x]))
        if not len(other):
            continue
        w = int(wide[x])
        mine = own[w][x - first[w]]
        least = np.empty(len(other), np.int64)
        for v in np.unique(wide[other]).tolist():
            of = wide[other] == v
            rows = (own[v] if v == w else half[v])[other[of] - first[v]]
            least[of] = np.bitwise_count(rows ^ mine).sum(1)
        other = other[(WHOLE + PART) * least <= (WHOLE - PART) * (n[x] + n[other])]
        if len(other):
            yield np.repeat(sid[x], len(other)), sid[other]


def _met(batches):
    """Pairs (a, b) of the rows of each (h, i, j), sorted by them."""

    def each():
        held: tuple | None = None
        parts: list = []
        for batch in batches:
            if not batch.num_rows:
                continue
            h, i, j = (np.asarray(batch.column(c)) for c in ("h", "i", "j"))
            bounds = np.concatenate(([0], np.flatnonzero((h[1:] != h[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])) + 1, [len(h)]))
            for s, e in zip(bounds[:-1].tolist(), bounds[1:].tolist()):
                key = (h[s], i[s], j[s])
                if key != held and parts:
                    yield from pairs(parts)
                    parts = []
                held = key
                parts.append(batch.slice(s, e - s))
        if parts:
            yield from pairs(parts)

    def pairs(parts):
        column = lambda c: np.concatenate([np.asarray(x.column(c)) for x in parts])
        yield from _pairs(column("pos").astype(np.int64), column("n").astype(np.int64), column("sid"), column("root"), [y for x in parts for y in x.column("sketch").to_pylist()])

    yield from _gathered(each(), ["a", "b"])


def _likeliest(pairs: DataFrame, nodes: DataFrame) -> DataFrame:
    """Of each member's pairs that their sketches don't rule out the one with the least difference."""
    side = lambda x: nodes.select(F.col("sid").alias(x), F.col("n").alias(f"n{x}"), F.col("sketch").alias(f"s{x}"))

    def run(batches):
        for batch in batches:
            size = np.asarray(batch.column("na")) + np.asarray(batch.column("nb"))
            least = np.array([differ(x, y) for x, y in zip(batch.column("sa").to_pylist(), batch.column("sb").to_pylist())], np.int64)
            may = pa.RecordBatch.from_arrays([batch.column("a"), batch.column("b"), pa.array(least)], ["a", "b", "least"])
            yield may.filter(pa.array((WHOLE + PART) * least <= (WHOLE - PART) * size))

    found = pairs.join(side("a"), "a").join(side("b"), "b").mapInArrow(run, "a long, b long, least long")
    return found.groupBy("b").agg(F.min(F.struct("least", "a")).alias("x")).select("x.a", "b")


def verified(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """Of distinct pairs (a, b) those whose sets reach the threshold; texts (sid, text) has a row for each end."""
    width = shuffle_width(pairs.sparkSession)
    parts = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / FOLLOWERS).alias("parts"))
    dealt = pairs.join(parts, "a").select("a", "b", F.pmod(F.xxhash64("b"), "parts").alias("part"))
    centres = dealt.select("a", "part").distinct().join(texts, F.col("a") == F.col("sid")).select("a", "part", F.lit(0).alias("kind"), F.col("a").alias("b"), "text")
    rows = centres.union(dealt.join(texts, F.col("b") == F.col("sid")).select("a", "part", F.lit(1), "b", "text"))

    def run(batches):
        centre = np.zeros(0, np.uint64)
        for batch in batches:
            for slice_ in chunked(batch, "text"):
                values, offsets = sets_of(strings(slice_.column("text")))
                a, kind, b = (slice_.column(c).to_pylist() for c in ("a", "kind", "b"))
                out_a, out_b = [], []
                for i, what in enumerate(kind):
                    own = values[offsets[i] : offsets[i + 1]]
                    if not what:
                        centre = own.copy()
                    elif similar(centre, own):
                        out_a.append(a[i])
                        out_b.append(b[i])
                yield pa.RecordBatch.from_arrays([pa.array(out_a, pa.int64()), pa.array(out_b, pa.int64())], ["a", "b"])

    return rows.repartition(width, "a", "part").sortWithinPartitions("a", "part", "kind").mapInArrow(run, "a long, b long")


def alike(nodes: DataFrame, radius: int = RADIUS) -> DataFrame:
    """Pairs (a, b) of the texts of `nodes` (sid, fp) that SimHash links; a fingerprint of several texts has its least one as centre."""
    least = cut(nodes.groupBy("fp").agg(F.min("sid").alias("sid")))
    ends = lambda x, y: least.select(F.col("fp").alias(x), F.col("sid").alias(y))
    near = links(least.select("fp"), radius).withColumnsRenamed({"a": "fa", "b": "fb"}).join(ends("fa", "x"), "fa").join(ends("fb", "y"), "fb")
    same = nodes.join(least.withColumnRenamed("sid", "a"), "fp").where("a <> sid").select("a", F.col("sid").alias("b"))
    return near.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).union(same)


def near_copies(docs: DataFrame, block: int = BLOCK) -> DataFrame:
    """(id, row, root): docs (id, row, text), where row tells texts of an id apart, with the component of each.

    Rows are linked if their shingle sets have a Jaccard similarity of 4/5 at least; texts without a word are equal.
    """
    spark = docs.sparkSession
    width = shuffle_width(spark)
    shared = spark.sparkContext.broadcast(_frequent(docs))  # at most LAST hashes
    kind = docs.schema["id"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            for part in chunked(batch, "text"):
                values, offsets = sets_of(strings(part.column("text")))
                first, bounds = prefixes(values, offsets, *shared.value)
                n = np.diff(offsets)
                data = values.tobytes()
                sid = np.array([xxhash.xxh64_intdigest(data[8 * s : 8 * e]) if e > s else 0 for s, e in zip(offsets[:-1].tolist(), offsets[1:].tolist())], np.uint64)
                drawn = pa.array([sketch(values[s:e]) for s, e in zip(offsets[:-1].tolist(), offsets[1:].tolist())], pa.binary())
                fp = pa.array(fingerprints_of(strings(part.column("text")), SHINGLE_WORDS).view(np.int64))
                listed = pa.ListArray.from_arrays(pa.array(bounds, pa.int32()), pa.array(first.view(np.int64)))
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("row"), pa.array(sid.view(np.int64)), pa.array(n, pa.int64()), fp, listed, drawn], ["id", "row", "sid", "n", "fp", "prefix", "sketch"])

    marked = cut(docs.select("id", "row", "text").mapInArrow(run, f"id {kind}, row long, sid long, n long, fp long, prefix array<long>, sketch binary"))
    nodes = marked.groupBy("sid").agg(F.min("row").alias("row"), F.first("n").alias("n"), F.first("prefix").alias("prefix"))
    sketches = marked.dropDuplicates(["sid"]).select("sid", "n", "sketch")

    def settled(pairs: DataFrame) -> DataFrame:
        pairs = cut(pairs)
        ends = pairs.select(F.col("a").alias("sid")).union(pairs.select("b")).distinct()
        want = cut(nodes.select("sid", "row").join(ends, "sid", "left_semi"))
        few = want.count() <= WANTED
        texts = cut(docs.select("row", "text").join(F.broadcast(want) if few else want, "row").select("sid", "text").dropDuplicates(["sid"]))
        return cut(verified(pairs, texts))

    every = nodes.select("sid", F.col("n").cast("int").alias("n"), F.posexplode("prefix").alias("pos", "h"))
    # from here on only buckets with two members or more count
    found = cut(every.repartition(width, "h").sortWithinPartitions("h", "pos", "n", "sid").mapInArrow(_shared, "kind int, h long, sid long, pos int, n int"))
    rows = found.where("kind = 1").drop("kind")
    stars = found.where("kind = 0").select(F.col("h").alias("a"), F.col("sid").alias("b"))
    # texts of equal sets may repeat shingles, and so differ in their fingerprints; one of them will do
    alikes = alike(marked.groupBy("sid").agg(F.min("fp").alias("fp")))
    joined = settled(_likeliest(alikes, sketches).union(_likeliest(stars.distinct(), sketches)).distinct())
    roots = cut(components(joined, FEW))
    rooted = roots.select(F.col("node").alias("sid"), "root")
    root = F.coalesce("root", "sid")
    buckets = rows.select("h", "sid").join(rooted, "sid", "left").groupBy("h").agg(F.min(root).alias("low"), F.max(root).alias("high"), F.count(F.lit(1)).alias("size"))
    opened = cut(buckets.where("low <> high").select("h", "size"))
    # members of buckets with several components and what their pairs are judged by; a bucket over `block` is cut, and every two parts meet
    members = cut(rows.join(F.broadcast(opened) if opened.count() <= WANTED else opened, "h"))
    ends = cut(members.select("sid").distinct().join(sketches.select("sid", "sketch"), "sid").join(rooted, "sid", "left").select("sid", "sketch", root.alias("root")))
    parts = F.ceil(F.col("size") / block)
    own = F.pmod(F.xxhash64("sid"), parts)
    split = members.join(ends, "sid").select("h", "sid", "pos", "n", "root", "sketch", own.alias("own"), F.explode(F.sequence(F.lit(0).cast("long"), parts - 1)).alias("other"))
    dealt = split.select("h", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "sid", "pos", "n", "root", "sketch")
    met = dealt.repartition(width, "h", "i", "j").sortWithinPartitions("h", "i", "j").mapInArrow(_met, "a long, b long")
    roots = cut(components(joined.union(settled(met.distinct())), FEW))
    # a set that many rows have is dealt to several tasks
    copies = roots.select(F.col("node").alias("sid"), "root", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    own = F.pmod(F.xxhash64("row", "id"), F.lit(SALTS)).cast("int")
    return marked.select("id", "row", "sid", own.alias("salt")).join(copies, ["sid", "salt"], "left").select("id", "row", F.coalesce("root", "sid").alias("root"))
