"""Benchmark decontamination by spaced-seed hashing.

A seed is a fixed mask over SPAN consecutive words; its zeros are ignored, so a substituted word
under a zero does not change the hash.  Seed hashes of the benchmark items (small, checked, and
taken block by block if they are not) are looked up at every word of every document.  Each hit
names a diagonal - an alignment of item and document - along which all words are compared: the
stretch with the most matches over a match rate of RATE decides.

Words are lower-cased runs of letters and digits.  Items shorter than a seed are found by the hash
of all their words; those of fewer than SHORTEST words stand in too many texts by chance and count
only where they are a document's whole text.

Defined results: null texts have no words, items without words match nothing; repeated rows, of
either table, count each on their own; a null doc_id or item_id stays null; of several best
overlaps of a document and an item the first counts; other columns are ignored by ``leaks`` and
kept by ``clean_documents``; a text of any length is searched as a whole; empty tables give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.text import NOT_ALNUM, U64, chunks, mix, window_hashes, window_starts

#: Masks of weight 7 over 10 words; any 10 equal words in a row meet all of them.
MASKS = ("1101100111", "1110011011", "1011110101", "1111001101")
SPAN = len(MASKS[0])
#: An overlap counts from so many matching words on (or RATE of a shorter item's words).
LEAST, RATE = 13, 0.8
#: Items of fewer words than this count only as whole texts.
SHORTEST = 5
#: Words compared at once.
COMPARED = 1 << 21
#: Bytes of benchmark text that are looked up at once; a larger benchmark takes several passes.
BENCHMARK_BYTES = 8 << 20
PAIR = "doc_id long, item_id long, start long, end long, matched long, item_words long"
_FACTORS = mix(np.arange(1, SPAN + 1, dtype=U64)) | U64(1)


def seed_hashes(words: np.ndarray, mask: str) -> np.ndarray:
    """Hash of the words under the ones of ``mask``, for every place where the mask fits."""
    n = len(words) - len(mask) + 1
    if n <= 0:
        return words[:0]
    total = np.zeros(n, dtype=U64)
    with np.errstate(over="ignore"):
        for i, bit in enumerate(mask):
            if bit == "1":
                total += words[i : i + n] * _FACTORS[i]
        return mix(total + U64(int(mask, 2)))


@dataclass
class Seeds:
    """Hashes of a benchmark: sorted, with the item and the place each comes from."""

    ids: list
    words: list
    hashes: np.ndarray
    items: np.ndarray
    places: np.ndarray
    gate: np.ndarray
    short: list

    @staticmethod
    def of(rows: list[tuple[int, str | None]]) -> Seeds:
        texts = pa.array([t for _, t in rows], pa.string())
        words: list[np.ndarray] = []
        for chunk in chunks(texts, NOT_ALNUM, lower=True):
            h = chunk.hashes()
            words += [h[i:j] for i, j in zip(chunk.ptr[:-1], chunk.ptr[1:], strict=True)]
        hashes, items, places = [], [], []
        for k, w in enumerate(words):
            found = [seed_hashes(w, m) for m in MASKS] if len(w) >= SPAN else [window_hashes(w, len(w))] if len(w) else []
            for h in found:
                hashes.append(h)
                items.append(np.full(len(h), k))
                places.append(np.arange(len(h)))
        h = np.concatenate(hashes) if hashes else np.zeros(0, dtype=U64)
        order = np.argsort(h, kind="stable")
        item, place = (np.concatenate(x)[order] if hashes else np.zeros(0, dtype=np.int64) for x in (items, places))
        gate = np.zeros(1 << 20, dtype=bool)
        gate[(h >> U64(44)).astype(np.int64)] = True
        return Seeds([i for i, _ in rows], words, h[order], item, place, gate, sorted({len(w) for w in words if 0 < len(w) < SPAN}))

    def hits(self, hashes: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(word of the document chunk, item, place in the item) of equal hashes."""
        some = np.flatnonzero(self.gate[(hashes >> U64(44)).astype(np.int64)])
        left, right = np.searchsorted(self.hashes, hashes[some]), np.searchsorted(self.hashes, hashes[some], side="right")
        n = right - left
        entry = np.repeat(left - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        return np.repeat(at[some], n), self.items[entry], self.places[entry]


def best_stretches(equal: np.ndarray, edges: np.ndarray, rate: float = RATE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start, end, matches) of the stretch with the largest sum of match - rate, for each segment of ``equal``.

    Segment k is ``edges[k]:edges[k + 1]`` and has at least one entry; all are scanned together.
    """
    scale = 100
    step = np.where(equal, scale - round(rate * scale), -round(rate * scale)).astype(np.int64)
    total = np.concatenate([[0], np.cumsum(step)])
    size = np.diff(edges)
    owner = np.repeat(np.arange(len(size)), size + 1)
    at = np.arange(len(owner)) - owner  # position in ``equal``; every segment has one more border than entries
    own = total[at]
    span = 2 * scale * (len(equal) + 1)
    low = np.minimum.accumulate(own - owner * span) + owner * span  # minima never reach over a segment's begin
    gain = own - low
    first = np.concatenate([[0], np.cumsum(size + 1)[:-1]])
    best = np.maximum.reduceat(gain, first)
    end = np.minimum.reduceat(np.where(gain == best[owner], np.arange(len(gain)), len(gain)), first)
    start = np.minimum.reduceat(np.where((own == low[end][owner]) & (np.arange(len(own)) <= end[owner]), np.arange(len(own)), len(own)), first)
    matches = np.concatenate([[0], np.cumsum(equal)])
    return at[start] - edges[:-1], at[end] - edges[:-1], matches[at[end]] - matches[at[start]]


def overlaps(batch_texts: pa.Array, seeds: Seeds) -> Iterator[tuple[int, int, int, int, int]]:
    """(row, item, start, end, matches): verified overlaps, the best of each row and item."""
    flat = np.concatenate(seeds.words) if seeds.words else np.zeros(0, dtype=U64)
    n_words = np.array([len(w) for w in seeds.words], dtype=np.int64)
    item_at = np.cumsum(n_words) - n_words
    for chunk in chunks(batch_texts, NOT_ALNUM, lower=True):
        words = chunk.hashes()
        at = window_starts(chunk.ptr, SPAN)
        runs = [(seed_hashes(words, m)[at], at) for m in MASKS] if len(at) else []
        for k in seeds.short:
            own = window_starts(chunk.ptr, k) if k >= SHORTEST else chunk.ptr[:-1][np.diff(chunk.ptr) == k]
            runs += [(window_hashes(words, k)[own], own)] if len(own) else []
        found = [seeds.hits(h, places) for h, places in runs]
        word, item, place = (np.concatenate([f[k] for f in found]) if found else np.zeros(0, dtype=np.int64) for k in range(3))
        if not len(word):
            continue
        doc = np.searchsorted(chunk.ptr, word, side="right") - 1
        doc, item, diagonal = np.unique(np.stack([doc, item, word - place]), axis=1)
        lo = np.maximum(chunk.ptr[doc], diagonal)
        size = np.minimum(chunk.ptr[doc + 1], diagonal + n_words[item]) - lo
        done = np.concatenate([[0], np.cumsum(size)])
        best: dict[tuple[int, int], tuple] = {}
        i = 0
        while i < len(doc):
            j = max(i + 1, int(np.searchsorted(done, done[i] + COMPARED, side="right")) - 1)
            step = np.arange(int(done[j] - done[i])) - np.repeat(done[i:j] - done[i], size[i:j])
            here = np.repeat(lo[i:j], size[i:j]) + step
            there = here - np.repeat(diagonal[i:j], size[i:j]) + np.repeat(item_at[item[i:j]], size[i:j])
            start, end, n = best_stretches(words[here] == flat[there], done[i : j + 1] - done[i])
            good = np.flatnonzero(n >= np.minimum(LEAST, -(-round(RATE * 100) * n_words[item[i:j]] // 100)))
            first = chunk.ptr[doc[i:j]]
            for k in good.tolist():
                key, row = (int(doc[i + k]), int(item[i + k])), (int(lo[i + k] + start[k] - first[k]), int(lo[i + k] + end[k] - first[k]), int(n[k]))
                if row[2] > best.get(key, (0, 0, 0))[2]:
                    best[key] = row
            i = j
        for (d, k), (start, end, n) in best.items():
            yield chunk.first + d, k, start, end, n


def _blocks(benchmark: DataFrame) -> Iterator[list[tuple]]:
    """The benchmark's items, at most about BENCHMARK_BYTES of text at a time."""
    rows = benchmark.select(F.col("item_id").cast("long"), F.col("text").cast("string"))
    size = rows.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = -(-size // BENCHMARK_BYTES) or 1
    for k in range(n):
        block = rows if n == 1 else rows.filter(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k)
        yield [tuple(r) for r in block.collect()]


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id, start, end, matched, item_words): verified overlaps; start and end in words."""
    spark, out = docs.sparkSession, None
    for rows in _blocks(benchmark):
        seeds = spark.sparkContext.broadcast(Seeds.of(rows))

        def find(batches: Iterator[pa.RecordBatch], seeds=seeds) -> Iterator[pa.RecordBatch]:
            own = seeds.value
            for batch in batches:
                ids = batch.column(0).to_pylist()
                found = [(ids[r], own.ids[i], s, e, n, len(own.words[i])) for r, i, s, e, n in overlaps(batch.column(1), own)]
                cols = list(zip(*found, strict=True)) or [[]] * 6
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in cols], ["doc_id", "item_id", "start", "end", "matched", "item_words"])

        part = docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")).mapInArrow(find, PAIR)
        out = part if out is None else out.unionByName(part)
    return out


def clean_documents(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows of ``docs`` in which no item of ``benchmark`` is found."""
    out, at = docs, docs.columns.index("text")
    for rows in _blocks(benchmark):
        seeds = docs.sparkSession.sparkContext.broadcast(Seeds.of(rows))

        def keep(batches: Iterator[pa.RecordBatch], seeds=seeds) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                good = np.ones(batch.num_rows, dtype=bool)
                good[[r for r, *_ in overlaps(batch.column(at), seeds.value)]] = False
                yield batch.filter(pa.array(good))

        out = out.mapInArrow(keep, docs.schema)
    return out
