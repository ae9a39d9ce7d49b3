"""Main text of web pages: structure first, then a suffix array over the pages of each host.

1. Markup is cut into blocks.  Zones that are never text (scripts, styles, forms) or never main text
   (navigation, page headers and footers, sidebars, notices, adverts, comments) are told by element,
   role and class words.  Where a page has an article (or main) element, its remaining blocks are
   the text: repetition never removes anything from them, as articles can share passages.
2. All other blocks of a host's pages - of pages without such an element, and as a context what
   lies outside it on the others - form token streams.  A suffix array over the concatenated
   streams, sorted by prefix doubling to MIN_TOKENS tokens, shows the substrings that stand on
   several distinct pages; the tokens they cover are boilerplate, and the unique runs stay.
   Pages with equal streams count as one page there, or copies would wipe each other out.

A host's pages are dealt to groups of about GROUP_PAGES by a hash, so a host with a third of all
pages spreads over tasks.  A host of several groups first tells in which groups and pages each
substring of MIN_TOKENS tokens stands (by 64-bit hashes), so a repeat counts in the whole host and
the groups change no text.

Defined results: null html is an empty page with empty text; a page without a host has the empty
host; repeated rows are extracted each on their own, alike; columns other than page_id, url and
html are ignored; a page of any length is read as a whole; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
import html
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.stages import written
from bitsort.llm.text import chunks

MIN_TOKENS, MIN_PAGES, GROUP_PAGES = 6, 2, 20_000

_QUOTED = r"""[^>"']*(?:(?:"[^"]*"|'[^']*')[^>"']*)*"""
_TAG = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)"
    r"|<(?P<raw>script|style|noscript|template|textarea|select|svg|math|iframe|object|canvas|button|option)\b[^>]*>.*?(?:</(?P=raw)\s*>|\Z)"
    rf"|<(?P<close>/?)(?P<name>[a-zA-Z][a-zA-Z0-9:-]*)(?P<attrs>{_QUOTED})>|<(?P<shut>/?)(?P<plain>[a-zA-Z][a-zA-Z0-9:-]*)[^>]*>|<[!?][^>]*>",
    re.S | re.I,
)
#: Elements that part blocks, those among them that can hold others, and those that hold no main text.
BLOCK = frozenset(
    "address article aside blockquote body center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol p pre section summary table tbody tfoot thead title tr ul caption".split()
)
OPEN = frozenset("article aside blockquote body center details dialog div dl fieldset figure footer form head header html main menu nav ol section table ul".split())
NEVER = frozenset("head nav footer aside form dialog menu fieldset".split())
SPACE = frozenset("br td th wbr".split())
VOID = frozenset("area base br col embed hr img input link meta param source track wbr".split())
#: Words in class, id or role that name something else than main text.
OTHER = frozenset(
    "ad ads adv advert adverts advertisement advertising adsense banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices notification alert popup modal overlay newsletter subscribe subscription signup sidebar widget widgets related recommended recommendations share sharing social nav navbar navigation menu breadcrumb breadcrumbs pagination pager footer contentinfo complementary comment comments commentlist reply replies disqus respond login search toolbar copyright outbrain taboola".split()
)
PAGE_ONLY = frozenset("header masthead topbar".split())
_ATTR = re.compile(r"""\b(class|id|role|hidden|style|aria-hidden|itemprop)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s"'>]+))?""", re.I)
_WORD = re.compile(r"[a-z0-9]+")
ARTICLE, MAIN, LOOSE, OUTSIDE = range(4)


def _attributes(attrs: str) -> tuple[set[str], bool, bool]:
    """(words of class, id and role; hidden; marked as the main part)."""
    words, hidden, main = set(), False, False
    for name, value in _ATTR.findall(attrs):
        name, value = name.lower(), value.strip("\"'").lower()
        if name in ("class", "id", "role"):
            words.update(_WORD.findall(value))
            main |= name == "role" and value == "main"
        elif name == "itemprop":
            main |= value == "articlebody"
        else:
            hidden |= name == "hidden" or value == "true" or "display:none" in value.replace(" ", "")
    return words, hidden, main


def blocks(page: str) -> list[tuple[int, str]]:
    """(zone, text) of the blocks of a page, in order; references decoded, white space single."""
    out: list[tuple[int, str]] = []
    stack: list[tuple[str, int]] = []  # open elements with the zone inside them
    zone, pieces, at = LOOSE, [], 0

    def flush() -> None:
        if pieces:
            text = " ".join(html.unescape("".join(pieces)).split())
            if text:
                out.append((zone, text))
            pieces.clear()

    for m in _TAG.finditer(page):
        if m.start() > at:
            pieces.append(page[at : m.start()])
        at = m.end()
        name = (m["name"] or m["plain"] or "").lower()
        if not name:
            continue
        if m["close"] or m["shut"]:
            if name in BLOCK:
                flush()
            for k in range(len(stack) - 1, -1, -1):
                if stack[k][0] == name:
                    flush()
                    del stack[k:]
                    zone = stack[-1][1] if stack else LOOSE
                    break
            continue
        if name in SPACE:
            pieces.append(" ")
            continue
        if name in BLOCK:
            flush()
            if stack and stack[-1][0] not in OPEN and stack[-1][0] in BLOCK:  # an open paragraph ends here
                stack.pop()
                zone = stack[-1][1] if stack else LOOSE
        new = zone
        words, hidden, main = _attributes(m["attrs"]) if m["attrs"] and "=" in m["attrs"] or "hidden" in (m["attrs"] or "") else (set(), False, False)
        if zone != OUTSIDE and name not in ("html", "body"):
            inside = zone in (ARTICLE, MAIN)
            if name in NEVER or hidden or (name == "header" and not inside):
                new = OUTSIDE
            elif name != "main" and (words & OTHER or (not inside and words & PAGE_ONLY)):
                new = OUTSIDE
            elif name == "article" or main and zone == LOOSE:
                new = ARTICLE
            elif name == "main" and zone == LOOSE:
                new = MAIN
        if name in VOID or m.group().endswith("/>") and name not in OPEN:
            continue
        if name in OPEN or new != zone:
            if new != zone:
                flush()
            stack.append((name, new))
            zone = new
    if at < len(page):
        pieces.append(page[at:])
    flush()
    return out


def _chosen(found: list[tuple[int, str]]) -> tuple[list[str] | None, list[str], list[str]]:
    """(text blocks if the page's structure decides, undecided blocks, context)."""
    zones = {z for z, _ in found}
    outside = [t for z, t in found if z == OUTSIDE]
    for zone in (ARTICLE, MAIN):
        if zone in zones:
            return [t for z, t in found if z == zone], [], outside + [t for z, t in found if z == LOOSE]
    return None, [t for z, t in found if z == LOOSE], outside


PARSED = "page_id long, url string, text string, loose array<string>, context array<string>"


def _parse(texts: bool):
    """Pages as texts where structure decides (``texts``), or what the hosts' suffix arrays need of them."""
    kinds = (pa.int64(), pa.string(), pa.string(), pa.list_(pa.string()), pa.list_(pa.string()))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in (batch.slice(i, 256) for i in range(0, batch.num_rows, 256)):
                rows = []
                for page_id, url, page in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    text, loose, context = _chosen(blocks(page or ""))
                    if not texts:
                        rows.append((page_id, url, None if text is None else "", loose, context))
                    elif text is not None:
                        rows.append((page_id, url, "\n\n".join(text), None, None))
                cols = list(zip(*rows, strict=True)) or [[]] * 5
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["page_id", "url", "text", "loose", "context"])

    return run


def prefix_ranks(tokens: np.ndarray, depth: int) -> np.ndarray:
    """Rank of every suffix by its first ``depth`` tokens (a suffix array cut at that depth).

    Prefix doubling: the rank by 2d tokens is that of the pair of ranks by d tokens at i and i + d.
    """
    rank = np.unique(tokens, return_inverse=True)[1].astype(np.int64) + 1
    d = 1
    while d < depth:
        step = min(d, depth - d)
        later = np.zeros_like(rank)
        later[: max(0, len(rank) - step)] = rank[step:]
        rank = np.unique(rank * (int(rank.max()) + 1) + later, return_inverse=True)[1].astype(np.int64) + 1 if len(rank) else rank
        d += step
    return rank


def repeated_tokens(tokens: np.ndarray, page: np.ndarray, depth: int = MIN_TOKENS, pages: int = MIN_PAGES) -> np.ndarray:
    """Which tokens lie in a substring of at least ``depth`` tokens that stands on ``pages`` pages or more.

    ``page``: the number of each token's page; substrings do not cross pages.
    """
    n = len(tokens)
    if n < depth:
        return np.zeros(n, dtype=bool)
    ranks = prefix_ranks(tokens, depth)[: n - depth + 1]
    whole = page[: n - depth + 1] == page[depth - 1 :]
    at = np.flatnonzero(whole)
    order = at[np.lexsort([page[at], ranks[at]])]  # the suffix array: equal prefixes side by side
    r, p = ranks[order], page[order]
    first = np.concatenate([[True], r[1:] != r[:-1]]) if len(order) else np.zeros(0, dtype=bool)
    group = np.cumsum(first) - 1
    new_page = first | np.concatenate([[True], p[1:] != p[:-1]]) if len(order) else first
    hit = order[np.bincount(group, weights=new_page)[group] >= pages] if len(order) else order
    step = np.zeros(n + 1, dtype=np.int64)
    np.add.at(step, hit, 1)
    np.add.at(step, hit + depth, -1)
    return np.cumsum(step[:-1]) > 0


def _kept_runs(rows: list[dict], covered: list[bool]) -> pa.Table:
    """Texts of the undecided pages: what is not covered; ``covered`` holds the tokens of all pages, one after the other."""
    at, out = 0, []
    for r in rows:
        kept = []
        for block in r["loose"] or []:
            words = block.split()
            run = [w for w, c in zip(words, covered[at : at + len(words)], strict=True) if not c]
            at += len(words)
            if run:
                kept.append(" ".join(run))
        at += sum(len(t.split()) for t in (r["context"] or []))
        if r["text"] is None:
            out.append((r["page_id"], r["url"], "\n\n".join(kept)))
    cols = list(zip(*out, strict=True)) or [[]] * 3
    return pa.table([pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.string()), pa.array(cols[2], pa.string())], ["page_id", "url", "text"])


def _without_boilerplate(table: pa.Table) -> pa.Table:
    """Pages of a host that is one group: unique runs of the undecided blocks of each."""
    rows = table.to_pylist()
    words: list[str] = []
    page: list[int] = []
    known: dict[tuple, int] = {}
    for k, r in enumerate(rows):
        # equal pages are one page; a page's context is part of it
        number = known.setdefault((tuple(r["loose"] or []), tuple(r["context"] or [])), k)
        for block in [*(r["loose"] or []), *(r["context"] or [])]:
            own = block.split()
            words += own
            page += [number] * len(own)
    tokens = pa.array(words, pa.string()).dictionary_encode().indices.to_numpy().astype(np.int64) if words else np.zeros(0, dtype=np.int64)
    return _kept_runs(rows, repeated_tokens(tokens, np.array(page, dtype=np.int64)).tolist())


def _substrings(rows: list[dict]) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(first token, hash, page key) of every substring of MIN_TOKENS tokens, and the number of tokens."""
    streams = [" ".join(x for t in [*(r["loose"] or []), *(r["context"] or [])] for x in t.split()) for r in rows]
    keys = np.array([int.from_bytes(hashlib.blake2b(repr((r["loose"] or [], r["context"] or [])).encode("utf-8", "surrogatepass"), digest_size=8).digest(), "little", signed=True) for r in rows], dtype=np.int64)
    at, h, key, before = [], [], [], 0
    for chunk in chunks(pa.array(streams, pa.string()), SPACES):
        first, own = chunk.windows(MIN_TOKENS)
        at.append(first + before)
        h.append(own.view(np.int64))
        key.append(keys[chunk.first + np.searchsorted(chunk.ptr, first, side="right") - 1])
        before += int(chunk.ptr[-1])
    empty = np.zeros(0, dtype=np.int64)
    return (*(np.concatenate(x) if x else empty for x in (at, h, key)), before)


SPACES = np.zeros(256, dtype=bool)
SPACES[0x20] = True


def _places(table: pa.Table) -> pa.Table:
    """For a group's distinct substrings the smallest and largest key of the pages they stand on."""
    _, h, key, _ = _substrings(table.select(["loose", "context"]).to_pylist())
    order = np.lexsort([key, h])
    h, key = h[order], key[order]
    edge = np.flatnonzero(np.concatenate([[True], h[1:] != h[:-1], [True]])) if len(h) else np.zeros(1, dtype=np.int64)
    n = len(edge) - 1
    one = lambda c: pa.array([table[c][0].as_py()] * n, table[c].type)
    return pa.table([one("host"), one("grp"), pa.array(h[edge[:-1]]), pa.array(key[edge[:-1]]), pa.array(key[edge[1:] - 1])], ["host", "grp", "h", "lo", "hi"])


def _without_repeats(pages: pa.Table, repeats: pa.Table) -> pa.Table:
    """Pages of one of several groups of a host, given the substrings that are repeated in the host."""
    rows = pages.to_pylist()
    at, h, _, n = _substrings(rows)
    step = np.zeros(n + 1, dtype=np.int64)
    hit = at[np.isin(h, repeats["h"].to_numpy())]
    np.add.at(step, hit, 1)
    np.add.at(step, hit + MIN_TOKENS, -1)
    return _kept_runs(rows, (np.cumsum(step[:-1]) > 0).tolist())


def main_text(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row."""
    own = pages.select(F.col("page_id").cast("long"), F.col("url").cast("string"), F.col("html").cast("string"))
    host = F.coalesce(F.lower(F.regexp_extract("url", r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#:]*)", 1)), F.lit(""))
    # pages are parsed twice, once for the streams and once for the texts, so that no text is stored
    parsed = written(own.mapInArrow(_parse(False), PARSED).withColumn("host", host))
    decided = own.mapInArrow(_parse(True), PARSED).select("page_id", "url", "text")
    # hosts with an undecided page, dealt to groups of bounded size
    sizes = parsed.groupBy("host").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("text").isNull()).alias("open")).filter("open > 0").select("host", F.ceil(F.col("n") / GROUP_PAGES).alias("groups"))
    open_hosts = parsed.join(sizes, "host").withColumn("grp", F.pmod(F.xxhash64("page_id", "url"), F.col("groups")))
    open_hosts = open_hosts.select("host", "grp", "groups", "page_id", "url", "text", "loose", "context")
    schema = "page_id long, url string, text string"
    undecided = open_hosts.filter("groups = 1").groupBy("host", "grp").applyInArrow(_without_boilerplate, schema)
    if not sizes.filter("groups > 1").isEmpty():
        large = open_hosts.filter("groups > 1")
        places = large.groupBy("host", "grp").applyInArrow(_places, "host string, grp long, h long, lo long, hi long")
        repeats = places.groupBy("host", "h").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).filter("lo < hi").select("host", "h")
        told = places.select("host", "grp", "h").join(repeats, ["host", "h"])
        undecided = undecided.unionByName(large.groupBy("host", "grp").cogroup(told.groupBy("host", "grp")).applyInArrow(_without_repeats, schema))
    return decided.unionByName(undecided).withColumn("n_chars", F.length("text").cast("long"))


__all__ = ["blocks", "main_text", "prefix_ranks", "repeated_tokens"]
