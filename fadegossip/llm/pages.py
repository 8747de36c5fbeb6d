"""Main text of web pages: the unique run of a page against the repeated substrings of its host, with markup as a prior.

A page is cut into blocks once. Blocks inside menus, headers, footers, asides, forms, notices, adverts or comments
are left out by their markup. The token streams of all other blocks of a host's pages are put side by side, and
substrings that two distinct streams share are looked for as a sorted suffix array would group them: by their first
`run` tokens, at anchors only (of every `WINNOW` consecutive places the one of least hash, so that any repeated
substring of run + WINNOW - 1 tokens or more has an anchor in common). Tokens under a shared anchor are covered.
Copies of a whole stream are one stream, so they don't erase each other, and a covered stretch of more than
`LONGEST` tokens is a copied article, not boilerplate. Whole blocks are repeats of any length: how many distinct streams
of the host hold a block is counted, and a block in at least `SHARE` of them, and in `LEAST` or more, is common.

The main text is the stretch of the stream with the greatest weight: a token weighs one if it is unique and minus
one if it is covered, which leaves the boilerplate around the article outside and keeps a passage that the article
shares with another. Markup is the prior: a token weighs two more inside a declared article (`article`, `main`, role
main), and on a page that declares one the other blocks don't count. There what a few articles of the host share never
outweighs the prior; but a common block is the host's template, wherever it stands, and goes from a declared article
too, unless nothing would be left of that.

Pages are dealt to groups, anchors to shards by their hash. A group names each stream of an anchor once (`exchange`), so
copies make no task larger than others; a phrase or host has 16 bytes in a shard for each distinct stream that holds it.
"""

from __future__ import annotations

import html
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fadegossip.llm.exchange import ENTRY, NOWHERE, REST, Merged, ask, told_to
from fadegossip.llm.frames import table
from fadegossip.llm.words import WORD_BASE, Words, chunked, least_in_windows, mix, span_hashes, strings

#: Tokens of an anchor, and places of which one is an anchor.
RUN, WINNOW = 8, 5
#: Tokens of a covered stretch (gaps up to twice `RUN` closed) beyond which it is a copy of an article.
LONGEST = 150
#: What a token of a declared article weighs more.
PRIOR = 2
#: Share of a host's streams, and number of them, from which a block is the host's template. In the given tables lines of
#: the articles themselves reach 0.25 (sf0.1) and 0.41 (check_h) of a host's streams.
SHARE, LEAST = 0.75, 5
#: How hard blocks are compressed for the shuffle.
LEVEL = 6
#: What sets the hashes of whole blocks and of hosts apart from those of anchors.
WHOLE, HOST = np.uint64(0x9FB21C651E98DF25), np.uint64(0xC2B2AE3D27D4EB4F)
#: Pages of a group.
GROUP_ROWS = 256

_TAG = re.compile(
    r"""<!--.*?(?:-->|\Z) | <!\[CDATA\[.*?(?:\]\]>|\Z) | <[!?][^>]*> | <(/?)([a-zA-Z][^\s/>]*)((?>[^>"']|"[^"]*"|'[^']*')*+)> | <(/?)([a-zA-Z][^\s/>]*)([^>]*)>""",
    re.S | re.X,
)
_NAMED = re.compile(r"""(?:^|\s)(class|id|role|aria-hidden|hidden)\s*(?:=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I | re.S)
# fixed values: elements and names by their role on a page
RAW = frozenset("script style textarea title noscript template iframe xmp noembed noframes".split())
DROPPED = frozenset("nav header footer aside form button select dialog menu svg canvas audio video object fieldset".split()) | RAW
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
ARTICLE = frozenset("article main".split())
BLOCK = frozenset(
    "address article blockquote body caption center dd details div dl dt figcaption figure h1 h2 h3 h4 h5 h6 head hr html li main ol p pre section summary table tbody td tfoot th thead tr ul".split()
) | DROPPED
NOISE = frozenset(
    "ad ads advert adverts advertisement adsense banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices sidebar comment comments reply replies respond disqus nav navbar navigation menu breadcrumb breadcrumbs footer header masthead social share sharing related recommended teaser teasers newsletter subscribe subscription signup popup modal overlay pagination widget search".split()
)
ROLES = frozenset("navigation banner contentinfo complementary search dialog alert menu form".split())
#: First parts of a class that tell of something else on the page ("has-sidebar").
ABOUT = frozenset("has with no without show hide is not".split())
_PARTS = re.compile(r"[^a-z0-9]+")
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def _noisy(attributes: str, own: bool) -> tuple[bool, bool]:
    """Whether an element's names mark it as no main text; whether they declare the main text.

    own: of an article, whose classes often describe the page; only a class that is or begins with such a name counts.
    """
    noisy = main = False
    for name, value in _NAMED.findall(attributes):
        name, value = name.lower(), value.strip("\"'").lower()
        if name == "hidden" or name == "aria-hidden" and value == "true":
            noisy = True
        elif name == "role":
            main |= value == "main"
            noisy |= value in ROLES
        elif name in ("class", "id"):
            for word in value.split():
                parts = [x for x in _PARTS.split(word) if x]
                if parts and parts[0] not in ABOUT:
                    noisy |= parts[0] in NOISE if own else not NOISE.isdisjoint(parts)
    return noisy, main


def _tags(page: str) -> list[tuple[int, int, str, bool, str]]:
    """(start, end, name, closing, attributes) in order; what raw elements hold is part of their tag, comments have no name."""
    out, at = [], 0
    while m := _TAG.search(page, at):
        name, closing = (m[2] or m[5] or "").lower(), bool(m[1] or m[4])
        at = m.end()
        if name in RAW and not closing:
            end = re.compile(rf"</{name}\b[^>]*>", re.I).search(page, at)
            at = end.end() if end else len(page)
        out.append((m.start(), at, name, closing, m[3] or m[6] or ""))
    return out


def _ends(tags: list) -> dict[int, int]:
    """For each tag that opens an element the tag that closes it, where there is one."""
    open_: dict[str, list[int]] = {}
    out = {}
    for i, (_, _, name, closing, _) in enumerate(tags):
        if closing:
            if open_.get(name):
                out[open_[name].pop()] = i
        elif name and name not in VOID and name not in RAW:
            open_.setdefault(name, []).append(i)
    return out


def blocks(page: str) -> tuple[list[str], list[bool]]:
    """Blocks that no markup rules out, in order, and whether each stands in a declared article.

    An element whose names rule it out (not its kind) is heeded only if something is left without it: first an
    article inside such an element counts, then names count for nothing.
    """
    tags = _tags(page)
    ends = _ends(tags)
    found = _walk(page, tags, ends, True, False)
    if not any(found[1]) and any(x[2] in ARTICLE and not x[3] for x in tags):
        rescued = _walk(page, tags, ends, True, True)
        if any(rescued[1]):
            return rescued
    return found if found[0] else _walk(page, tags, ends, False, False)


def _walk(page: str, tags: list, ends: dict[int, int], named: bool, rescue: bool) -> tuple[list[str], list[bool]]:
    out: list[str] = []
    inside: list[bool] = []
    text: list[str] = []
    openers: list[str] = []  # elements that declare the article
    at, until, lost = 0, -1, False  # tags up to `until` are left out; lost: in an element that is never closed

    def flush() -> None:
        if text:
            block = " ".join(html.unescape("".join(text)).split())
            if block:
                out.append(block)
                inside.append(bool(openers))
            text.clear()

    for i, (start, end, name, closing, attributes) in enumerate(tags):
        hidden = lost or i <= until
        if not hidden and start > at:
            text.append(page[at:start])
        at = end
        if not name or i < until:
            continue
        if i == until:
            continue
        if closing:
            if lost:
                lost = name != "body"
                continue
            if name in BLOCK:
                flush()
            if openers and name == openers[-1]:
                openers.pop()
            elif name in ("body", "html"):
                openers.clear()
            continue
        if name in BLOCK and not lost:
            flush()
        elif name == "br" and not lost:
            text.append(" ")
        if name in RAW or name in VOID or attributes.endswith("/"):
            continue
        noisy, main = _noisy(attributes, name in ARTICLE) if attributes else (False, False)
        article = name in ARTICLE or main
        if article and not noisy:
            openers.append(name)
            lost = False  # an element that was never closed doesn't hide the article
        elif not lost and (name in DROPPED or noisy and named and name not in ("html", "body") and not (rescue and _holds_article(tags, ends, i))):
            flush()
            until, lost = ends.get(i, -1), i not in ends
    if not lost and at < len(page):
        text.append(page[at:])
    flush()
    return out, inside


def _holds_article(tags: list, ends: dict[int, int], at: int) -> bool:
    return any(x[2] in ARTICLE and not x[3] and not _noisy(x[4], True)[0] for x in tags[at + 1 : ends.get(at, len(tags))])


def parse(pages: DataFrame) -> DataFrame:
    """(page_id, url, host, declared, size, body), a row for each row: the blocks of the declared article, or all that are left, joined by line feeds.

    body is compressed, since it is shuffled, and `size` are its bytes before.
    """
    kind = pages.schema["page_id"].dataType.simpleString()

    def run(batches):
        codec = pa.Codec("zstd", compression_level=LEVEL)
        for batch in batches:
            for part in chunked(batch, "html"):
                body, declared = [], []
                for page in part.column("html").to_pylist():
                    found, inside = blocks(page or "")
                    declared.append(any(inside))
                    body.append("\n".join(x for x, y in zip(found, inside) if y or not declared[-1]))
                body = [x.encode() for x in body]
                packed = pa.array([codec.compress(x, asbytes=True) for x in body], pa.binary())
                yield pa.RecordBatch.from_arrays([part.column("page_id"), part.column("url"), part.column("host"), pa.array(declared), pa.array([len(x) for x in body], pa.int64()), packed], ["page_id", "url", "host", "declared", "size", "body"])

    host = F.coalesce(F.lower(F.regexp_extract("url", r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", 1)), F.lit(""))
    return pages.select("page_id", "url", F.xxhash64(host).alias("host"), "html").mapInArrow(run, f"page_id {kind}, url string, host long, declared boolean, size long, body binary")


def anchors(words: Words, run: int, winnow: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and hashes of the anchors of each stream."""
    at = words.starts_of(run)
    keys = np.full(len(words.doc), np.iinfo(np.uint64).max, np.uint64)
    keys[at] = span_hashes(words.hashes(), WORD_BASE, at, at + run)
    ends = words.first[1:][words.doc[at]] - run  # the last start of the stream
    least = least_in_windows(keys, winnow)[at]
    full = at + winnow - 1 <= ends
    # a stream of less than `winnow` starts has the least of them
    short = (np.diff(np.concatenate(([-1], words.doc[at]))) > 0) & ~full
    place = np.unique(least[full | short])
    return place, keys[place]


def block_edges(words: Words) -> np.ndarray:
    """Whether a block begins at each token, and at the end of all."""
    n = len(words.doc)
    line = np.cumsum(words.body == 10)[words.start]
    edge = np.ones(n + 1, bool)
    edge[1:n] = (line[1:] != line[:-1]) | (words.doc[1:] != words.doc[:-1])
    return edge if n else np.zeros(1, bool)


def covered(words: Words, place: np.ndarray, shared: np.ndarray, run: int, longest: int = LONGEST) -> np.ndarray:
    """Tokens under a shared anchor, without stretches over `longest`.

    Anchors may leave a few tokens at the ends of a repeat: less than `run` of them, up to a block's end, are covered too.
    """
    n = len(words.doc)
    hit = place[shared]
    depth = np.zeros(n + 1, np.int32)
    np.add.at(depth, hit, 1)
    np.add.at(depth, hit + run, -1)
    under = np.cumsum(depth[:n]) > 0
    if not len(hit):
        return under
    edge = block_edges(words)
    change = edge.copy()
    change[1:n] |= under[1:] != under[:-1]
    at = np.flatnonzero(change)
    first, last = at[:-1], at[1:]
    beside = ~edge[first] | ~edge[last]
    for a, b in zip(*(x[(last - first < run) & beside & ~under[first]].tolist() for x in (first, last))):
        under[a:b] = True
    return without_copies(words, under, run, longest)


def without_copies(words: Words, under: np.ndarray, run: int, longest: int = LONGEST) -> np.ndarray:
    """What is covered, without stretches (gaps of up to twice `run` closed) of more than `longest` tokens."""
    at = np.flatnonzero(under)
    if not len(at):
        return under
    far = (np.diff(at) > 2 * run + 1) | (words.doc[at[1:]] != words.doc[at[:-1]])
    stretch = np.concatenate(([0], np.cumsum(far)))
    first, last = at[np.concatenate(([True], far))], at[np.concatenate((far, [True]))]
    out = under.copy()
    out[at[(last - first + 1 > longest)[stretch]]] = False
    return out


def best_stretch(weight: np.ndarray) -> tuple[int, int]:
    """The stretch of the greatest sum, the longest of equals that start first; (0, 0) if no token weighs anything."""
    upto = np.concatenate(([0], np.cumsum(weight)))
    low = np.minimum.accumulate(upto)
    end = len(upto) - 1 - int(np.argmax((upto - low)[::-1]))
    if upto[end] <= low[end]:
        return 0, 0
    return int(np.argmax(upto[: end + 1] == low[end])), end


def unique_text(body: str, declared: bool, under: np.ndarray, common: np.ndarray) -> str:
    """What stands of a page's blocks in its main stretch, without blocks of the host's template.

    under: which tokens are covered; common: which are in blocks that most streams of the host hold. A declared article
    of such blocks alone stays.
    """
    begin, end = best_stretch(np.where(under, -1, 1) + (PRIOR if declared else 0))
    own, template, n = [], [], 0
    for block in body.split("\n"):
        tokens = WORD.findall(block)
        kept = tokens[max(begin - n, 0) : max(end - n, 0)]
        if kept:
            (template if common[n : n + len(tokens)].all() else own).append(block if len(kept) == len(tokens) else " ".join(kept))
        n += len(tokens)
    return "\n\n".join(own or (template if declared else []))


def main_text(pages: DataFrame, run: int = RUN, winnow: int = WINNOW, group_rows: int = GROUP_ROWS) -> DataFrame:
    """(page_id, url, text, n_chars, declared, n_tokens, n_covered, n_common), a row for each row.

    declared: whether markup names the article; n_tokens, n_covered and n_common: tokens that markup leaves, those under a
    repeated substring, and those of blocks that most streams of the host hold. Null html and pages without main text
    give an empty text. A page without a usable host is compared with its like. Repeated rows and page_ids keep their
    rows; a page of any length is one value. Other columns of any name change nothing. An empty table gives an empty
    result.
    """
    kind = pages.schema["page_id"].dataType.simpleString()
    groups = max(1, -(-pages.count() // group_rows))
    parsed = parse(pages)
    dealt = parsed.withColumn("g", F.pmod(F.xxhash64("page_id", "url", F.monotonically_increasing_id()), F.lit(groups)))
    by_group = dealt.groupBy("g")

    def streams(members):
        bodies = pa.array([pa.decompress(x, n, "zstd", asbytes=True).decode() for x, n in zip(members.column("body").to_pylist(), members.column("size").to_pylist())], pa.large_string())
        for part in chunked(members.drop_columns(["body", "size"]).append_column("body", bodies), "body"):
            words = Words(strings(part.column("body")))
            place, keys = anchors(words, run, winnow)
            edges = np.flatnonzero(block_edges(words))
            wholes = span_hashes(words.hashes(), WORD_BASE, edges[:-1], edges[1:])
            hosts = mix(np.asarray(part.column("host")).view(np.uint64))
            full = np.flatnonzero(words.count)  # a page without tokens is no stream
            doc = np.concatenate((words.doc[place], words.doc[edges[:-1]], full))
            entries = np.zeros(len(doc), ENTRY)
            # anchors, whole blocks, and one for each page that tells how many streams its host has
            entries["h"] = mix(np.concatenate((keys, mix(wholes ^ WHOLE), np.full(len(full), HOST))) ^ hosts[doc])
            entries["v"] = _names(words)[doc] & REST
            entries["src"] = NOWHERE
            yield part, words, place, edges, entries

    def merged_of(members):
        found = list(streams(members))
        return found, Merged(np.concatenate([np.zeros(0, ENTRY), *[x[-1] for x in found]]))

    def finish(members, told):
        found, merged = merged_of(members)
        streams_with = told_to(merged.distinct, told, True)["kinds"].astype(np.int64)[merged.which]
        out, at = [], 0
        for part, words, place, edges, entries in found:
            anchored, whole, hosts = np.split(streams_with[at : at + len(entries)], [len(place), len(place) + len(edges) - 1])
            at += len(entries)
            of_host = np.zeros(part.num_rows, np.int64)
            of_host[words.count > 0] = hosts
            under = covered(words, place, anchored > 1, run)
            common = np.repeat((whole >= LEAST) & (whole >= SHARE * of_host[words.doc[edges[:-1]]]), np.diff(edges))
            common = without_copies(words, common, 0)
            bounds = zip(words.first[:-1].tolist(), words.first[1:].tolist())
            texts = [unique_text(b, d, under[f:t], common[f:t]) for b, d, (f, t) in zip(part.column("body").to_pylist(), part.column("declared").to_pylist(), bounds)]
            n, n_common = (np.bincount(words.doc[x], minlength=part.num_rows) for x in (under, common))
            out.append(pa.table({"page_id": part.column("page_id"), "url": part.column("url"), "text": pa.array(texts, pa.string()), "declared": part.column("declared"), "n_tokens": pa.array(words.count, pa.int64()), "n_covered": pa.array(n, pa.int64()), "n_common": pa.array(n_common, pa.int64())}))
        return pa.concat_tables(out)

    told = ask(lambda rows: by_group.applyInArrow(lambda key, members: rows(key[0].as_py(), merged_of(members)[1].distinct), "c int, s int, g long, items binary"), groups, counted=True)
    schema = f"page_id {kind}, url string, text string, declared boolean, n_tokens long, n_covered long, n_common long"
    answered = by_group.cogroup(told.groupBy("g")).applyInArrow(finish, schema)
    return answered.select("page_id", "url", "text", F.length("text").cast("long").alias("n_chars"), "declared", "n_tokens", "n_covered", "n_common")


def _names(words: Words) -> np.ndarray:
    """A number for each stream, equal for equal streams of tokens."""
    return span_hashes(words.hashes(), WORD_BASE, words.first[:-1], words.first[1:])


def op2_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text(table(spark, sf_dir, "pages"))
