"""Substring deduplication by Rabin-Karp hashes of every window of ``width`` words.

A window is a repeat if the same words also start in a document with a smaller doc_id; every word
that some repeat covers is removed.  Windows are judged on the input.

1. Each task hashes the windows of its documents, block by block.  Inside a block only the
   windows of the smallest doc_id with a hash go on; the others are repeats already.  So a passage
   that a third of all documents share leaves a block once, not once a document.
2. The remaining (hash, place) pairs, packed and sorted, are dealt to buckets by hash, counted
   there, and the places of repeats come back by document.
3. Each document merges its repeats into maximal intervals and drops the covered words.

Windows count as equal if their 64-bit hashes are.  Over n distinct windows about n**2 / 2**65
pairs collide: 0.0005 for half a gigabyte.

Defined results: a null text has no words; a null doc_id counts as larger than all others, so its
windows never make others repeats; rows with equal doc_id are not smaller than each other; texts
shorter than a window lose nothing; an empty table gives an empty result; other columns are
ignored, whatever their names.  A text of any length is cut as a whole, in one task.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import compress

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.stages import by_bytes
from bitsort.llm.text import U64, Chunk, chunks, mix, trim, window_starts

WIDTH = 13
BLOCK_BYTES = 24 << 20
NO_ID = np.iinfo(np.int64).max
#: What travels: sorted hashes and places of one block in one bucket, and the block's documents.
MESSAGE = "bucket int, docs binary, hashes binary, places binary, hits binary"
HITS = "home int, hits binary"
#: One bucket takes the windows of so many bytes of text, one home so many bytes of documents.
BUCKET_BYTES, HOME_BYTES = 16 << 20, 4 << 20


def _squeeze(*arrays: np.ndarray) -> bytes:
    return zstandard.compress(b"".join(np.ascontiguousarray(a).tobytes() for a in arrays), 1)


def _low_bytes(values: np.ndarray, n: int) -> np.ndarray:
    return np.ascontiguousarray(values.astype("<u8")).view(np.uint8).reshape(-1, 8)[:, :n]


def _from_low_bytes(data: bytes, n: int) -> np.ndarray:
    raw = np.frombuffer(data, dtype=np.uint8).reshape(-1, n)
    out = np.zeros((len(raw), 8), dtype=np.uint8)
    out[:, :n] = raw
    return out.view("<u8").ravel()


def _pack_sorted(values: np.ndarray) -> bytes:
    """Ascending 64-bit values as gaps of as few whole bytes as the largest gap needs."""
    gaps = np.diff(values, prepend=values[:1])
    n = max(1, (int(gaps.max()).bit_length() + 7) // 8) if len(gaps) else 1
    return bytes([n]) + (int(values[0]) if len(values) else 0).to_bytes(8, "little") + _low_bytes(gaps, n).tobytes()


def _unpack_sorted(data: bytes) -> np.ndarray:
    gaps = _from_low_bytes(data[9:], data[0]).astype(U64)
    if len(gaps):
        gaps[0] = int.from_bytes(data[1:9], "little")
    with np.errstate(over="ignore"):
        return np.cumsum(gaps, dtype=U64)


def _pack_places(values: np.ndarray) -> bytes:
    top = int(values.max()) if len(values) else 0
    n = 2 if top < 1 << 16 else 3 if top < 1 << 24 else 5
    return bytes([n]) + _low_bytes(values, n).tobytes()


class _Block:
    """Documents of one task, with the hashes of their windows."""

    def __init__(self, width: int):
        self.width, self.bytes, self.ids, self.text_hash, self.words, self.hashes = width, 0, [], [], [], []

    def add(self, ids: np.ndarray, text_hash: np.ndarray, chunk: Chunk) -> None:
        n = len(chunk.ptr) - 1
        self.ids.append(ids[chunk.first : chunk.first + n])
        self.text_hash.append(text_hash[chunk.first : chunk.first + n])
        self.words.append(np.diff(chunk.ptr))
        self.hashes.append(chunk.windows(self.width)[1])
        self.bytes += len(chunk.data)

    def window_places(self, ptr: np.ndarray) -> np.ndarray:
        return window_starts(ptr, self.width)

    def settled(self, ids: np.ndarray, least: np.ndarray) -> np.ndarray:
        """Windows that are repeats for what this block shows; only the others go on."""
        return ids > least

    def messages(self, buckets: int) -> pa.RecordBatch:
        ids, text_hash, words = (np.concatenate(x) for x in (self.ids, self.text_hash, self.words))
        first = np.cumsum(words) - words
        ptr = np.concatenate([first, [int(words.sum())]])
        small = np.int32 if ptr[-1] < 1 << 31 else np.int64
        place, h = self.window_places(ptr).astype(small), np.concatenate(self.hashes)
        self.hashes = []
        order = np.argsort(h, kind="stable")
        h, place = h[order], place[order]
        del order
        doc = (np.searchsorted(first, place, side="right") - 1).astype(np.int32)
        new = np.concatenate([[True], h[1:] != h[:-1]]) if len(h) else np.zeros(0, dtype=bool)
        least = np.minimum.reduceat(ids[doc], np.flatnonzero(new)) if len(h) else ids[:0]
        hit = self.settled(ids[doc], least[np.cumsum(new, dtype=np.int32) - 1]) if len(h) else new
        del new, least

        def with_docs(places: np.ndarray, docs: np.ndarray) -> tuple[bytes, np.ndarray]:
            """The documents of some places, and these places counted in those documents alone."""
            used, at = np.unique(docs, return_inverse=True)
            begin = np.cumsum(words[used]) - words[used]
            return _squeeze(np.array([len(used)], dtype=np.int64), np.diff(ids[used], prepend=0), text_hash[used], words[used].astype(np.int64)), places.astype(np.int64) - first[docs] + begin[at]

        out = []
        keep_h, keep_at, keep_doc = h[~hit], place[~hit], doc[~hit]
        # high bits of a sorted list: a bucket's share is one slice
        cut = np.searchsorted(keep_h, np.array([(b << 64) // buckets for b in range(1, buckets)], dtype=U64)) if buckets > 1 else []
        edges = [0, *cut, len(keep_h)]
        for b, (i, j) in enumerate(zip(edges, edges[1:], strict=False)):
            if j > i:
                docs, at = with_docs(keep_at[i:j], keep_doc[i:j])
                out.append((b, docs, _pack_sorted(keep_h[i:j]), _pack_places(at), None))
        if hit.any():
            docs, at = with_docs(place[hit], doc[hit])
            out.append((int(text_hash[0]) % buckets, docs, None, None, _squeeze(np.diff(np.sort(at), prepend=0))))
        cols = list(zip(*out, strict=True)) or [[]] * 5
        return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), *(pa.array(c, pa.binary()) for c in cols[1:])], ["bucket", "docs", "hashes", "places", "hits"])


def _window_messages(width: int, buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = _Block(width)
        for batch in batches:
            ids = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
            text_hash = batch.column(1).to_numpy(zero_copy_only=False)
            for chunk in chunks(batch.column(2)):
                block.add(ids, text_hash, chunk)
                if block.bytes >= BLOCK_BYTES:
                    yield block.messages(buckets)
                    block = _Block(width)
                    trim()
        if block.ids:
            yield block.messages(buckets)

    return run


def _documents(data: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    raw = zstandard.decompress(data)
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    ids = np.cumsum(np.frombuffer(raw, np.int64, n, 8))
    return ids, np.frombuffer(raw, np.int64, n, 8 + 8 * n), np.frombuffer(raw, np.int64, n, 8 + 16 * n)


def home_of(ids: np.ndarray, text_hash: np.ndarray, homes: int) -> np.ndarray:
    return (mix(ids.astype(U64) ^ mix(text_hash.astype(U64))) % U64(homes)).astype(np.int32)


def _hits_by_home(ids, text_hash, first, places: np.ndarray, homes: int, out: dict[int, list]) -> None:
    """Note a block's repeats under the homes of their documents, as word positions."""
    doc = np.searchsorted(first, places, side="right") - 1
    home = home_of(ids, text_hash, homes)[doc]
    order = np.argsort(home, kind="stable")
    home, doc, places = home[order], doc[order], places[order]
    edges = np.flatnonzero(np.concatenate([[True], home[1:] != home[:-1], [True]]))
    for i, j in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        own = doc[i:j]
        out.setdefault(int(home[i]), []).append((ids[own], text_hash[own], places[i:j] - first[own]))


def _pack_hits(parts: list) -> bytes:
    ids, text_hash, places = (np.concatenate([p[k] for p in parts]) for k in range(3))
    order = np.lexsort([places, text_hash, ids])
    ids, text_hash, places = ids[order], text_hash[order], places[order]
    edges = np.flatnonzero(np.concatenate([[True], (ids[1:] != ids[:-1]) | (text_hash[1:] != text_hash[:-1]), [True]]))
    first = edges[:-1]
    return _squeeze(np.array([len(first)], dtype=np.int64), ids[first], np.diff(edges), text_hash[first], places.astype("<u4"))


def _unpack_hits(data: bytes) -> Iterator[tuple[tuple[int, int], np.ndarray]]:
    raw = zstandard.decompress(data)
    n = int(np.frombuffer(raw, np.int64, 1)[0])
    ids, counts, text_hash = np.frombuffer(raw, np.int64, n, 8), np.frombuffer(raw, np.int64, n, 8 + 8 * n), np.frombuffer(raw, np.int64, n, 8 + 16 * n)
    places, at = np.frombuffer(raw, "<u4", offset=8 + 24 * n), 0
    for key, k in zip(zip(ids.tolist(), text_hash.tolist(), strict=True), counts.tolist(), strict=True):
        yield key, places[at : at + k]
        at += k


def _count_bucket(homes: int):
    """Windows of one bucket: which places hold a hash that a smaller document has too."""
    return _count_bucket_of(homes, lambda doc, least, most: doc > least)


def _count_bucket_of(homes: int, wanted):
    """Places of one bucket for which ``wanted(doc_id, least, most doc_id with the hash)`` holds, by home."""

    def run(table: pa.Table) -> pa.Table:
        hashes, ids, blocks, places, known = [], [], [], [], []
        out: dict[int, list] = {}
        for docs, h, at, hits in zip(*(table[c].to_pylist() for c in ("docs", "hashes", "places", "hits")), strict=True):
            block = _documents(docs)
            first = np.cumsum(block[2]) - block[2]
            if hits is not None:
                _hits_by_home(block[0], block[1], first, np.cumsum(np.frombuffer(zstandard.decompress(hits), np.int64)), homes, out)
            if h is not None:
                at = _from_low_bytes(at[1:], at[0]).astype(np.int64)
                hashes.append(_unpack_sorted(h))
                places.append(at.astype(np.uint32) if first[-1] < 1 << 32 else at)
                ids.append(block[0][np.searchsorted(first, at, side="right") - 1])
                blocks.append(np.full(len(at), len(known), dtype=np.int32))
                known.append((block[0], block[1], first))
        if hashes:
            h, doc = np.concatenate(hashes), np.concatenate(ids)
            order = np.argsort(h, kind="stable")
            h = h[order]
            new = np.concatenate([[True], h[1:] != h[:-1]])
            doc = doc[order]
            first, group = np.flatnonzero(new), np.cumsum(new) - 1
            order = order[wanted(doc, np.minimum.reduceat(doc, first)[group], np.maximum.reduceat(doc, first)[group])]
            blocks, places = np.concatenate(blocks)[order], np.concatenate(places)[order].astype(np.int64)
            order = np.lexsort([places, blocks])
            blocks, places = blocks[order], places[order]
            for b, (i, j) in enumerate(zip(np.searchsorted(blocks, range(len(known))), np.searchsorted(blocks, range(len(known)), side="right"), strict=True)):
                if j > i:
                    _hits_by_home(*known[b], places[i:j], homes, out)
        trim()
        return pa.table([pa.array(list(out), pa.int32()), pa.array([_pack_hits(x) for x in out.values()], pa.binary())], ["home", "hits"])

    return run


def covered(n_words: int, places: np.ndarray, width: int) -> np.ndarray:
    """Which words some window that starts at one of ``places`` covers (maximal intervals)."""
    step = np.zeros(n_words + 1, dtype=np.int32)
    np.add.at(step, places, 1)
    np.add.at(step, np.minimum(places + width, n_words), -1)
    return np.cumsum(step[:-1]) > 0


def intervals(mask: np.ndarray) -> list[tuple[int, int]]:
    edge = np.diff(np.concatenate([[0], mask.astype(np.int8), [0]]))
    return list(zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True))


def repeated_places(docs: DataFrame, width: int = WIDTH, buckets: int = 64, homes: int = 64) -> DataFrame:
    """Rows (home, hits): the starts of repeated windows of the documents of one home, packed.

    ``buckets``: how many ways to deal the hashes; ``homes``: how many groups the documents form.
    """
    rows = docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_hash"), F.col("text").cast("string"))
    return rows.mapInArrow(_window_messages(width, buckets), MESSAGE).groupBy("bucket").applyInArrow(_count_bucket(homes), HITS)


def _at_home(homes: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).fill_null(NO_ID).to_numpy(zero_copy_only=False)
            home = home_of(ids, batch.column(1).to_numpy(zero_copy_only=False), homes)
            yield pa.RecordBatch.from_arrays([pa.array(home), *batch.columns], ["home", "doc_id", "text_hash", "text"])

    return run


def _without_repeats(width: int):
    def run(docs: pa.Table, hits: pa.Table) -> pa.Table:
        starts: dict[tuple[int, int], list] = {}
        for packed in hits["hits"].to_pylist():
            for key, places in _unpack_hits(packed):
                starts.setdefault(key, []).append(places)
        out = []
        for batch in docs.select(["doc_id", "text_hash", "text"]).to_batches(max_chunksize=256):
            rows: list[tuple] = []
            for doc, text_hash, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).cast(pa.binary()).to_pylist(), strict=True):
                words = (text or b"").split()
                n, gone = len(words), []
                if places := starts.get((NO_ID if doc is None else doc, text_hash)):
                    mask = covered(n, np.concatenate(places).astype(np.int64), width)
                    gone, words = intervals(mask), list(compress(words, (~mask).tolist()))
                rows.append((doc, b" ".join(words), n, n - len(words), [{"start": i, "end": j} for i, j in gone]))
            out.append(_output(rows))
        trim()
        return pa.Table.from_batches(out or [_output([])])

    return run


def deduplicated(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """Every row with its kept text: doc_id, text (kept words joined by one space), n_words, n_removed, removed (word intervals)."""
    homes = by_bytes(docs, HOME_BYTES)
    hits = repeated_places(docs, width, -(-homes * HOME_BYTES // BUCKET_BYTES), homes)
    rows = docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("text_hash"), F.col("text").cast("string"))
    rows = rows.mapInArrow(_at_home(homes), "home int, doc_id long, text_hash long, text string")
    kept = rows.groupBy("home").cogroup(hits.groupBy("home"))
    return kept.applyInArrow(_without_repeats(width), "doc_id long, text string, n_words long, n_removed long, removed array<struct<start:long,end:long>>")


_SPANS = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))


def _output(rows: list[tuple]) -> pa.RecordBatch:
    cols = list(zip(*rows, strict=True)) or [[]] * 5
    kinds = (pa.int64(), pa.binary(), pa.int64(), pa.int64(), _SPANS)
    arrays = [pa.array(c, t) for c, t in zip(cols, kinds, strict=True)]
    arrays[1] = arrays[1].cast(pa.string())
    return pa.RecordBatch.from_arrays(arrays, ["doc_id", "text", "n_words", "n_removed", "removed"])


def digest(result: DataFrame) -> DataFrame:
    """doc_id, n_words, n_removed and the SHA-256 of what is kept."""
    return result.select("doc_id", "n_words", "n_removed", F.sha2("text", 256).alias("kept_sha256"))


__all__ = ["WIDTH", "covered", "deduplicated", "digest", "intervals", "repeated_places"]
