"""Deduplication of long passages by a sparse suffix array.

Only suffixes at content-selected places are kept: a place is selected if the hash of its SEED
words is the smallest in some window of seeds.  Equal passages select the same places, and any
passage of at least MIN_WORDS words selects one.

1. Tasks select places; seed hashes are dealt to buckets and those of a single document drop out.
2. The documents of the rest give each place its context: MIN_WORDS - SEED words on either side of the seed.
   Of equal contexts of one home only the smallest document's go on.
3. In each bucket the suffixes are sorted and compared with their neighbours; runs of neighbours
   that share r words are extended to the left by the words that r leaves missing.  What the other
   documents of a class share with its smallest one are repeats, all pairs accounted for.
4. A document's repeats merge into maximal intervals.  Long passages select a place at least every
   MIN_WORDS - SEED + 1 words, so the stretches of neighbouring places overlap.

The words reported are exactly those in some run of MIN_WORDS words that a smaller document has too
(up to equal word hashes, cut to 32 bits where runs are compared).

Defined results: null texts have no words; a null doc_id counts as larger than all others; rows
with equal doc_id do not repeat each other; documents without repeats give no row; an empty table
gives no rows; other columns are ignored, whatever their names.  A text of any length is cut as a
whole, in one task.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.stages import by_bytes
from bitsort.llm.substring_dedup import (
    BUCKET_BYTES,
    HOME_BYTES,
    MESSAGE,
    NO_ID,
    _at_home,
    _Block,
    _count_bucket_of,
    _unpack_hits,
    intervals,
)
from bitsort.llm.text import U64, Chunk, chunks, mix, trim, window_hashes

MIN_WORDS, SEED = 50, 20
#: Suffixes compared at once; those of one seed stay together.
SLICE = 20_000
SUFFIX = "bucket int, seed binary, ids binary, text_hash binary, places binary, context binary, found binary"


def selected_places(seeds: np.ndarray, free: np.ndarray, window: int) -> np.ndarray:
    """Places whose seed hash is the smallest (the last of equal ones) of some ``window`` seeds.

    ``free``: how many seeds each document has; they lie back to back in ``seeds``.  A document
    with fewer seeds than a window has no passage that counts and selects none.
    """
    n = len(seeds)
    if n < window:
        return np.zeros(0, dtype=np.int64)
    # minima of all windows by doubling: a window is two overlapping halves
    best, span = np.arange(n), 1

    def smaller(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.where(seeds[b] <= seeds[a], b, a)

    while 2 * span <= window:
        best = smaller(best[: len(best) - span], best[span:])
        span *= 2
    if span < window:
        best = smaller(best[: n - window + 1], best[window - span : window - span + n - window + 1])
    ends = np.cumsum(free)
    first = np.repeat(ends - free, np.maximum(free - window + 1, 0))
    at = np.arange(len(first)) - np.repeat(np.cumsum(np.maximum(free - window + 1, 0)) - np.maximum(free - window + 1, 0), np.maximum(free - window + 1, 0)) + first
    return np.unique(best[at])


def chunk_suffixes(chunk: Chunk, min_words: int, seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(word hashes, selected words, their seed hashes) of a chunk."""
    words = chunk.hashes()
    at, h = chunk.windows(seed, words)
    own = selected_places(h, np.maximum(np.diff(chunk.ptr) - seed + 1, 0), min_words - seed + 1)
    return words, at[own], h[own]


class _SparseBlock(_Block):
    """As for all windows, but only the selected places travel."""

    def __init__(self, min_words: int, seed: int):
        super().__init__(seed)
        self.min_words, self.places, self.before = min_words, [], 0

    def add(self, ids: np.ndarray, text_hash: np.ndarray, chunk: Chunk) -> None:
        n = len(chunk.ptr) - 1
        self.ids.append(ids[chunk.first : chunk.first + n])
        self.text_hash.append(text_hash[chunk.first : chunk.first + n])
        self.words.append(np.diff(chunk.ptr))
        _, at, h = chunk_suffixes(chunk, self.min_words, self.width)
        self.places.append(at + self.before)
        self.hashes.append(h)
        self.before += int(chunk.ptr[-1])
        self.bytes += len(chunk.data)

    def window_places(self, ptr: np.ndarray) -> np.ndarray:
        return np.concatenate(self.places)

    def settled(self, ids: np.ndarray, least: np.ndarray) -> np.ndarray:
        return np.zeros(len(ids), dtype=bool)  # the first and the later ones are needed


def _sparse_messages(min_words: int, seed: int, buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = _SparseBlock(min_words, seed)
        for batch in batches:
            ids = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
            text_hash = batch.column(1).to_numpy(zero_copy_only=False)
            for chunk in chunks(batch.column(2)):
                block.add(ids, text_hash, chunk)
                if block.bytes >= 24 << 20:
                    yield block.messages(buckets)
                    block = _SparseBlock(min_words, seed)
                    trim()
        if block.ids:
            yield block.messages(buckets)

    return run


def _shared(doc: np.ndarray, least: np.ndarray, most: np.ndarray) -> np.ndarray:
    return most > least


def _merged(doc, text, start, end, source) -> tuple[np.ndarray, ...]:
    """Overlapping stretches of one document with one source as one."""
    order = np.lexsort([start, source, text, doc])
    doc, text, start, end, source = (x[order] for x in (doc, text, start, end, source))
    if not len(doc):
        return doc, text, start, end, source
    same = (doc[1:] == doc[:-1]) & (text[1:] == text[:-1]) & (source[1:] == source[:-1])
    run = np.concatenate([[0], np.cumsum(~same)]) << 40  # runs apart, so that ends of one do not reach the next
    first = np.flatnonzero(np.concatenate([[True], ~same | ((start + run)[1:] > np.maximum.accumulate(end + run)[:-1])]))
    return doc[first], text[first], start[first], np.maximum.reduceat(end, first), source[first]


def _context_hashes(context: np.ndarray) -> np.ndarray:
    total = np.zeros(len(context), dtype=U64)
    with np.errstate(over="ignore"):
        for k in range(context.shape[1]):
            total += mix(context[:, k].astype(U64) + U64(k << 33))
    return mix(total)


def _run_length(there: np.ndarray) -> np.ndarray:
    """How many leading entries of each row hold."""
    return np.where(there.all(axis=1), there.shape[1], there.argmin(axis=1))


def _valid(context: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How many words stand before and behind the seed, within the context."""
    side = context.shape[1] // 2
    return _run_length(context[:, side - 1 :: -1] != 0), _run_length(context[:, side:] != 0)


def _contexts(buckets: int, seed: int, min_words: int):
    """Suffixes of the documents of one home.

    Of suffixes with one context only those of the smallest document travel; for the others that
    one already shows all repeats that reach into the context.
    """

    side = min_words - seed
    around = np.concatenate([np.arange(side), np.arange(min_words, min_words + side)])  # in a text padded by ``side``

    def run(docs: pa.Table, hits: pa.Table) -> pa.Table:
        starts: dict[tuple[int, int], list] = {}
        for packed in hits["hits"].to_pylist():
            for key, places in _unpack_hits(packed):
                starts.setdefault(key, []).append(places)
        seeds, ids, text_hashes, places, contexts, out = [], [], [], [], [], []
        docs = docs.combine_chunks()
        if starts and docs.num_rows:
            own_ids = docs["doc_id"].fill_null(NO_ID).to_numpy()
            own_hash = docs["text_hash"].to_numpy()
            for chunk in chunks(docs["text"].chunk(0)):
                words = chunk.hashes()
                for k in range(len(chunk.ptr) - 1):
                    row = chunk.first + k
                    found = starts.get((int(own_ids[row]), int(own_hash[row])))
                    if not found:
                        continue
                    own = words[chunk.ptr[k] : chunk.ptr[k + 1]]
                    at = np.unique(np.concatenate(found)).astype(np.int64)
                    padded = np.zeros(len(own) + 2 * side, dtype=np.uint32)
                    padded[side : side + len(own)] = (own >> U64(32)).astype(np.uint32) | np.uint32(1)  # 0: no word
                    contexts.append(padded[at[:, None] + around])
                    seeds.append(window_hashes(own, seed)[at])
                    ids.append(np.full(len(at), own_ids[row]))
                    text_hashes.append(np.full(len(at), own_hash[row], dtype=np.int64))
                    places.append(at)
        if seeds:
            s, i, t, p, c = (np.concatenate(x) for x in (seeds, ids, text_hashes, places, contexts))
            seeds = contexts = None
            h = _context_hashes(c)
            order = np.lexsort([i, h, s])
            new = np.concatenate([[True], (h[order][1:] != h[order][:-1]) | (s[order][1:] != s[order][:-1])])
            least = i[order[np.flatnonzero(new)]][np.cumsum(new) - 1]
            later = i[order] > least
            left, right = _valid(c)
            gone, source = order[later], least[later]
            right = right + seed
            whole = left[gone] + right[gone] >= min_words
            gone, source = gone[whole], source[whole]
            if len(gone):
                out.append((int(s[0] % U64(buckets)), None, None, None, None, None, _packed_rows(_merged(i[gone], t[gone], p[gone] - left[gone], p[gone] + right[gone], source))))
            stay = order[~later]
            bucket = ((s[stay] >> U64(32)) * U64(buckets) >> U64(32)).astype(np.int64)
            edges = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1], [True]]))  # seeds ascend, so do buckets
            for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                own = stay[a:b]
                out.append((int(bucket[a]), s[own].tobytes(), i[own].tobytes(), t[own].tobytes(), p[own].tobytes(), c[own].tobytes(), None))
            del c
        trim()
        cols = list(zip(*out, strict=True)) or [[]] * 7
        return pa.table([pa.array(cols[0], pa.int32()), *(pa.array(x, pa.binary()) for x in cols[1:])], ["bucket", "seed", "ids", "text_hash", "places", "context", "found"])

    return run


def _packed_rows(columns: tuple[np.ndarray, ...]) -> bytes:
    return np.stack([x.astype(np.int64) for x in columns]).tobytes()


def compared(seed: np.ndarray, ids: np.ndarray, context: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Stretches (suffix, smallest other document, words before and behind the seed) shared with smaller documents.

    ``context`` holds as many words on either side of the seed as a repeat has besides it.  Suffixes
    are sorted; those that share their first r words are a run of neighbours.  A repeat around the
    seed needs, for some r, r equal words behind it and the rest before it: inside every run of
    every depth r, suffixes with equal words on the left are one class, and all but those of its
    smallest document repeat that.  So every pair is accounted for and none is enumerated.
    """
    none = np.zeros(0, dtype=np.int64)
    if not len(seed):
        return none, none, none, none
    side = context.shape[1] // 2
    after = np.ascontiguousarray(context[:, side:].astype(">u4")).view(f"S{4 * side}").ravel()
    order = np.lexsort([after, seed])
    del after
    s, d, context = seed[order], ids[order], context[order]
    new = np.concatenate([[True], s[1:] != s[:-1]])
    shared = np.concatenate([[0], _run_length(context[1:, side:] == context[:-1, side:])])
    before = np.zeros((side + 1, len(s)), dtype=U64)  # hashes of 0, 1, .. words on the left
    with np.errstate(over="ignore"):
        for a in range(side):
            before[a + 1] = mix(before[a] * U64(0x9E3779B97F4A7C15) + context[:, side - 1 - a] + U64(1))
    left, right = _valid(context)
    rows: list[tuple[np.ndarray, ...]] = [(none, none, none, none)]
    for r in range(side + 1):
        a = side - r
        can = np.flatnonzero((right >= r) & (left >= a))
        run = np.cumsum(new | (shared < r))[can]
        at = np.lexsort([d[can], before[a][can], run])
        can, run = can[at], run[at]
        h, doc = before[a][can], d[can]
        first = np.concatenate([[True], (run[1:] != run[:-1]) | (h[1:] != h[:-1])])[: len(can)]
        least = doc[np.flatnonzero(first)][np.cumsum(first) - 1] if len(can) else doc
        hit = doc > least
        rows.append((can[hit], least[hit], np.full(int(hit.sum()), a), np.full(int(hit.sum()), r)))
    i, source, a, r = (np.concatenate([x[k] for x in rows]) for k in range(4))
    if not len(i):
        return none, none, none, none
    # the stretches of a suffix with one source overlap at its seed: one row
    by = np.lexsort([source, i])
    i, source, a, r = i[by], source[by], a[by], r[by]
    first = np.flatnonzero(np.concatenate([[True], (i[1:] != i[:-1]) | (source[1:] != source[:-1])]))
    return order[i[first]], source[first], np.maximum.reduceat(a, first), np.maximum.reduceat(r, first)


FOUND = "doc_id long, text_hash long, start long, end long, source_id long"


def _joined(table: pa.Table, column: str, kind) -> np.ndarray:
    parts = [np.frombuffer(x.as_buffer(), kind) for x in table[column] if x.is_valid]
    return np.concatenate(parts) if parts else np.zeros(0, dtype=kind)


def _compare_bucket(min_words: int, seed_words: int):
    def run(table: pa.Table) -> pa.Table:
        known = [np.frombuffer(x.as_buffer(), np.int64).reshape(5, -1) for x in table["found"] if x.is_valid]
        out = [tuple(x) for x in known]
        seed = _joined(table, "seed", U64)
        ids, text_hash, places = (_joined(table, c, np.int64) for c in ("ids", "text_hash", "places"))
        context = _joined(table, "context", np.uint32).reshape(-1, 2 * (min_words - seed_words))
        del table
        order = np.argsort(seed, kind="stable")
        ends = np.flatnonzero(np.concatenate([seed[order][1:] != seed[order][:-1], [True]])) + 1 if len(seed) else np.zeros(0, dtype=np.int64)
        at = 0
        while at < len(seed):
            to = int(ends[min(int(np.searchsorted(ends, at + SLICE)), len(ends) - 1)])
            own = order[at:to]
            i, source, left, right = compared(seed[own], ids[own], context[own])
            i = own[i]
            out.append(_merged(ids[i], text_hash[i], places[i] - left, places[i] + seed_words + right, source))
            at = to
        del context
        rows = _merged(*(np.concatenate([x[k] for x in out]) if out else np.zeros(0, dtype=np.int64) for k in range(5)))
        trim()
        return pa.table([pa.array(x) for x in rows], ["doc_id", "text_hash", "start", "end", "source_id"])

    return run


def repeated_passages(docs: DataFrame, min_words: int = MIN_WORDS, seed: int = SEED) -> DataFrame:
    """(doc_id, text_hash, start, end, source_id): passages, in words, that a smaller document has too."""
    homes = by_bytes(docs, HOME_BYTES)
    buckets = -(-homes * HOME_BYTES // BUCKET_BYTES)
    rows = docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_hash"), F.col("text").cast("string"))
    hits = rows.mapInArrow(_sparse_messages(min_words, seed, buckets), MESSAGE).groupBy("bucket").applyInArrow(_count_bucket_of(homes, _shared), "home int, hits binary")
    at_home = rows.mapInArrow(_at_home(homes), "home int, doc_id long, text_hash long, text string")
    suffixes = at_home.groupBy("home").cogroup(hits.groupBy("home")).applyInArrow(_contexts(homes, seed, min_words), SUFFIX)
    found = suffixes.groupBy("bucket").applyInArrow(_compare_bucket(min_words, seed), FOUND)
    return found.withColumn("doc_id", F.when(F.col("doc_id") != int(NO_ID), F.col("doc_id"))).withColumn("source_id", F.when(F.col("source_id") != int(NO_ID), F.col("source_id")))


def deduplication_report(docs: DataFrame, min_words: int = MIN_WORDS) -> DataFrame:
    """One row per document with repeats: doc_id, n_removed, spans (word intervals) and sources (doc_ids)."""
    found = repeated_passages(docs, min_words)
    # rows of one document and text: their number is bounded by the document's length
    by_doc = found.groupBy("doc_id", "text_hash").agg(F.array_sort(F.collect_set(F.struct("start", "end"))).alias("spans"), F.array_sort(F.collect_set("source_id")).alias("sources"))

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for doc, spans, sources in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                mask = np.zeros(max(s["end"] for s in spans), dtype=bool)
                for s in spans:
                    mask[s["start"] : s["end"]] = True
                out.append((doc, int(mask.sum()), [{"start": a, "end": b} for a, b in intervals(mask)], sources))
            cols = list(zip(*out, strict=True)) or [[]] * 4
            kinds = (pa.int64(), pa.int64(), pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])), pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], ["doc_id", "n_removed", "spans", "sources"])

    return by_doc.select("doc_id", "spans", "sources").mapInArrow(merge, "doc_id long, n_removed long, spans array<struct<start:long,end:long>>, sources array<long>")


__all__ = ["MIN_WORDS", "SEED", "compared", "deduplication_report", "repeated_passages", "selected_places"]
