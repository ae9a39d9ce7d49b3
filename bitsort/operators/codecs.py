"""Bitmap codecs: words to payload bytes and back, all on numpy arrays.

A bitmap is an array of unsigned words (the last one may be partial; ``rows`` tells).  Every codec
has encode, decode and a size that equals the closed form of ``measure``.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.operators.measure import HYBRID31, Codec


def pack_bits(bits: np.ndarray, w: int) -> np.ndarray:
    """0/1 array -> words of w bits, the first row in the lowest bit."""
    n = -(-len(bits) // w) * w
    padded = np.zeros(n, dtype=np.uint64)
    padded[: len(bits)] = bits
    return (padded.reshape(-1, w) << np.arange(w, dtype=np.uint64)).sum(axis=1, dtype=np.uint64)


def unpack_bits(words: np.ndarray, w: int, rows: int) -> np.ndarray:
    return ((words.astype(np.uint64)[:, None] >> np.arange(w, dtype=np.uint64)) & np.uint64(1)).ravel()[:rows].astype(np.int8)


def full_words(n: int, w: int, rows: int) -> np.ndarray:
    """The word with all rows set, for each word."""
    full = np.full(n, (1 << w) - 1, dtype=np.uint64)
    if n and rows % w:
        full[-1] = (1 << (rows % w)) - 1
    return full


def segments(words: np.ndarray, w: int, rows: int) -> Iterator[tuple[int, int, int, int]]:
    """(clean bit, clean words, start, end of the dirty words after them)."""
    n = len(words)
    kind = np.where(words == 0, 0, np.where(words == full_words(n, w, rows), 1, 2))
    edge = np.flatnonzero(np.concatenate([[True], kind[1:] != kind[:-1], [True]])) if n else np.zeros(1, dtype=int)
    pending: tuple[int, int] | None = None
    for i, j in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
        k = int(kind[i])
        if k == 2:
            yield (*(pending or (0, 0)), i, j)
            pending = None
        else:
            if pending:
                yield (*pending, i, i)
            pending = (k, j - i)
    if pending:
        yield (*pending, n, n)


def encode_marker(words: np.ndarray, rows: int, codec: Codec) -> np.ndarray:
    """Markers - fill bit, clean count, dirty count from the low bits up - and verbatim words."""
    out: list[np.ndarray] = []
    for bit, clean, i, j in segments(words, codec.w, rows):
        dirty, first = j - i, True
        while first or clean > 0 or dirty > 0:
            c = min(clean, codec.clean_max)
            rest = 0
            if codec.extend and c == codec.clean_max:
                rest, clean = clean - c, c
            clean -= c
            d = min(dirty, codec.dirty_max) if clean == 0 else 0
            marker = bit | (c << 1) | (d << (1 + codec.clean_bits))
            out.append(np.array([marker, rest] if codec.extend and c == codec.clean_max else [marker], dtype=np.uint64))
            out.append(words[i : i + d].astype(np.uint64))
            i, dirty, first = i + d, dirty - d, False
    return np.concatenate(out) if out else np.zeros(0, dtype=np.uint64)


def decode_marker(stream: np.ndarray, rows: int, codec: Codec) -> np.ndarray:
    n = -(-rows // codec.w)
    out, at, i, full = np.zeros(n, dtype=np.uint64), 0, 0, full_words(n, codec.w, rows)
    while i < len(stream):
        m = int(stream[i])
        c, d = (m >> 1) & codec.clean_max, (m >> (1 + codec.clean_bits)) & codec.dirty_max
        i += 1
        if codec.extend and c == codec.clean_max:
            c += int(stream[i])
            i += 1
        if m & 1:
            out[at : at + c] = full[at : at + c]
        at += c
        out[at : at + d] = stream[i : i + d]
        at, i = at + d, i + d
    return out


def encode_hybrid(words: np.ndarray, rows: int, codec: Codec = HYBRID31) -> np.ndarray:
    """Flagged words: the top bit tells clean runs (fill bit, count) from literals of 31 rows."""
    top, out = 1 << codec.w, []
    for bit, clean, i, j in segments(words, codec.w, rows):
        while clean > 0:
            c = min(clean, codec.clean_max)
            out.append(np.array([top | (bit << (codec.w - 1)) | c], dtype=np.uint64))
            clean -= c
        out.append(words[i:j].astype(np.uint64))
    return np.concatenate(out) if out else np.zeros(0, dtype=np.uint64)


def decode_hybrid(stream: np.ndarray, rows: int, codec: Codec = HYBRID31) -> np.ndarray:
    n, out, at = -(-rows // codec.w), [], 0
    full = full_words(n, codec.w, rows)
    for x in stream.tolist():
        if x >> codec.w:
            c = x & codec.clean_max
            out.append(full[at : at + c] if (x >> (codec.w - 1)) & 1 else np.zeros(c, dtype=np.uint64))
            at += c
        else:
            out.append(np.array([x], dtype=np.uint64))
            at += 1
    return np.concatenate(out) if out else np.zeros(0, dtype=np.uint64)


def encode_bytewise(bits: np.ndarray) -> bytes:
    """Byte-granular runs: a head byte (fill bit, 3 bits of fill bytes, 4 bits of literal bytes), long fills as a
    varint after it, then the literal bytes.  A documented variant of byte-aligned run-length coding."""
    data = np.packbits(bits.astype(np.uint8), bitorder="little")
    kind = np.where(data == 0, 0, np.where(data == 255, 1, 2))
    out, i, n = bytearray(), 0, len(data)
    while i < n:
        bit = int(kind[i]) if kind[i] < 2 else 0
        j = i
        while j < n and kind[j] == bit:
            j += 1
        k = j
        while k < n and kind[k] == 2 and k - j < 15:
            k += 1
        fill = j - i
        out.append(bit << 7 | min(fill, 7) << 4 | (k - j))
        if fill >= 7:
            x = fill - 7
            while True:
                out.append((x & 127) | (128 if x > 127 else 0))
                x >>= 7
                if not x:
                    break
        out += data[j:k].tobytes()
        i = k
    return bytes(out)


def decode_bytewise(stream: bytes, rows: int) -> np.ndarray:
    out, i = bytearray(), 0
    while i < len(stream):
        head = stream[i]
        fill, i = (head >> 4) & 7, i + 1
        if fill == 7:
            shift = 0
            while True:
                fill += (stream[i] & 127) << shift
                shift, i = shift + 7, i + 1
                if stream[i - 1] < 128:
                    break
        out += (b"\xff" if head >> 7 else b"\x00") * fill + stream[i : i + (head & 15)]
        i += head & 15
    return np.unpackbits(np.frombuffer(bytes(out), dtype=np.uint8), bitorder="little")[:rows].astype(np.int8)


def bit_runs(bits: np.ndarray) -> list[tuple[int, int]]:
    """(bit, length) of plain run-length coding."""
    edge = np.flatnonzero(np.concatenate([[True], bits[1:] != bits[:-1], [True]])) if len(bits) else []
    return [(int(bits[i]), int(j - i)) for i, j in zip(edge[:-1], edge[1:], strict=True)] if len(bits) else []


def run_length_text(bits: np.ndarray) -> str:
    """Counts and symbols in turn."""
    return "".join(f"{n}{b}" for b, n in bit_runs(bits))


def escaped_text(symbols: str) -> str:
    """Single symbols bare; a symbol written twice announces its count.  Inverse: ``unescaped_text``."""
    out, i = "", 0
    while i < len(symbols):
        j = i
        while j < len(symbols) and symbols[j] == symbols[i]:
            j += 1
        out += symbols[i] if j - i == 1 else f"{symbols[i] * 2}{j - i}"
        i = j
    return out


def gamma_bits(x: int) -> int:
    return 2 * (x.bit_length() - 1) + 1


def delta_bits(x: int) -> int:
    return x.bit_length() - 1 + gamma_bits(x.bit_length())


def run_length_bits(bits: np.ndarray, counter: str = "fixed") -> int:
    """Size in bits: fixed 32-bit counters and a bit each, or gamma or delta counters and one first bit."""
    lengths = [n for _, n in bit_runs(bits)]
    if counter == "fixed":
        return 33 * len(lengths)
    return 1 + sum(gamma_bits(n) if counter == "gamma" else delta_bits(n) for n in lengths)


def dictionary_bytes(words: np.ndarray, w: int) -> int:
    """Size under a general dictionary compressor."""
    return len(zlib.compress(words.astype(f"<u{w // 8}").tobytes(), 6))


def words_touched_and(dirty_only: np.ndarray, sparse: np.ndarray, rows: int, w: int, skipping: bool) -> int:
    """Words a reader looks at to AND a dirty-only bitmap with a sparse one: it can skip dirty runs or not."""
    own = int((sparse != 0).sum())
    return 2 * own + 1 if skipping else len(dirty_only) + own


#: Words that are gathered before bitmaps are encoded together.
GATHERED = 1 << 18
#: Words of streams that are made at once: few words of long bitmaps can have very many markers.
STREAMED = 1 << 23


def stream_cuts(first: np.ndarray, n: int, total: np.ndarray, codec: Codec) -> np.ndarray:
    """Where to cut bitmaps that begin at the places ``first`` of ``n`` words, so that the streams between two cuts have
    STREAMED words at most; a longer stream is alone.  ``total``: all words of each bitmap."""
    own = np.diff(np.append(first, n))
    # a non-zero word ends at most one run of zeros and begins one of its own; the last one has zeros after it
    most = np.cumsum(total // codec.clean_max + 4 * own + 2)
    cuts, done = [0], 0
    while cuts[-1] < len(first):
        cuts.append(max(cuts[-1] + 1, int(np.searchsorted(most, done + STREAMED, "right"))))
        done = int(most[cuts[-1] - 1])
    return np.array(cuts)


def encode_sparse(group: np.ndarray, at: np.ndarray, bits: np.ndarray, total: np.ndarray, last_rows: np.ndarray, codec: Codec, dtype: str = "<u8") -> tuple[np.ndarray, np.ndarray]:
    """The streams of many bitmaps, one after the other, and the length of each, from their non-zero words alone.

    ``group`` numbers the bitmap of each word from 0 on, ``total`` and ``last_rows`` are its bitmap's
    words and the rows in the last one.  Nothing but the streams, of numbers of type ``dtype``, is longer than
    the words: full counters of zeros are filled in first, then all other words are set.
    """
    n, w = len(group), codec.w
    if codec.extend:  # counters that go on in a word of their own are written bitmap by bitmap
        cut, streams = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1], [True]])), []
        for i, j in zip(cut[:-1].tolist(), cut[1:].tolist(), strict=True):
            dense = np.zeros(int(total[i]), dtype=np.uint64)
            dense[at[i:j]] = bits[i:j]
            streams.append(encode_marker(dense, (int(total[i]) - 1) * w + int(last_rows[i]), codec))
        return np.concatenate(streams).astype(dtype), np.array([len(x) for x in streams], dtype=np.int64)
    whole = np.uint64((1 << w) - 1)
    end = np.where(last_rows >= w, whole, (np.uint64(1) << (last_rows % w).astype(np.uint64)) - np.uint64(1))
    full = bits == np.where(at == total - 1, end, whole)
    new = np.concatenate([[True], group[1:] != group[:-1]])
    gap = at - np.concatenate([[-1], at[:-1]]) - 1
    gap[new] = at[new]
    # runs of words of one kind, then pieces: zeros before a run, the run, zeros after the last one
    start = np.flatnonzero(new | (gap > 0) | np.concatenate([[True], full[1:] != full[:-1]]))
    size = np.diff(np.append(start, n))
    own, zeros, kind = group[start], gap[start], np.where(full[start], 1, 2)
    tail = np.where(np.append(own[1:] != own[:-1], True), total[start] - at[start] - size, 0)
    piece = np.stack([np.where(zeros > 0, zeros, 0), size, tail], axis=1).ravel()
    kinds = np.stack([np.zeros_like(kind), kind, np.zeros_like(kind)], axis=1).ravel()
    owner, there = np.repeat(own, 3), piece > 0
    piece, kinds, owner = piece[there], kinds[there], owner[there]
    # a dirty piece shares the marker of the clean one before it
    joins = np.concatenate([[False], (kinds[1:] == 2) & (kinds[:-1] < 2) & (owner[1:] == owner[:-1])])
    head = np.flatnonzero(~joins)
    followed = np.append(joins[1:], False)[head]
    clean = np.where(kinds[head] < 2, piece[head], 0)
    dirty = np.where(kinds[head] == 2, piece[head], np.where(followed, np.append(piece[1:], 0)[head], 0))
    bit, owner = (kinds[head] == 1).astype(np.uint64), owner[head]
    firsts = -(-clean // codec.clean_max)
    if codec.markers:
        firsts = np.maximum(firsts, 1)
        more = np.maximum(-(-dirty // codec.dirty_max) - 1, 0)
    else:
        more = np.zeros_like(dirty)
    length = firsts + more + dirty
    begin = np.cumsum(length) - length
    zero = (codec.clean_max << 1) if codec.markers else (1 << w) | codec.clean_max
    stream = np.full(int(length.sum()), zero, dtype=dtype)
    # the markers that differ: of ones all, of zeros the last one, which counts dirty words too, and those after it
    skipped = np.where(bit == 1, 0, np.maximum(firsts - 1, 0))
    markers = firsts + more - skipped
    seg = np.repeat(np.arange(len(head)), markers)
    nth = np.arange(len(seg)) - np.repeat(np.cumsum(markers) - markers, markers) + skipped[seg]
    later = nth - firsts[seg] + 1  # from 0 on for the last marker of the clean words
    count = np.where(later < 0, codec.clean_max, np.where(later == 0, clean[seg] - (firsts[seg] - 1) * codec.clean_max, 0)).astype(np.uint64)
    if codec.markers:
        words = np.where(later < 0, 0, np.minimum(dirty[seg] - later * codec.dirty_max, codec.dirty_max)).astype(np.uint64)
        value = bit[seg] | (count << np.uint64(1)) | (words << np.uint64(1 + codec.clean_bits))
        place = begin[seg] + nth + np.maximum(later, 0) * codec.dirty_max
    else:
        value = np.uint64(1 << w) | (bit[seg] << np.uint64(w - 1)) | count
        place = begin[seg] + nth
    stream[place] = value
    nth = np.arange(int(dirty.sum())) - np.repeat(np.cumsum(dirty) - dirty, dirty)
    stream[np.repeat(begin + firsts, dirty) + nth + (nth // codec.dirty_max if codec.markers else 0)] = bits[~full]
    return stream, np.bincount(owner, weights=length, minlength=int(group[-1]) + 1).astype(np.int64)


def encode_payloads(words: DataFrame, blocks: DataFrame, codec: Codec) -> DataFrame:
    """(block, attr, bitmap, n_words, payload) from sparse words, many bitmaps a batch.

    Words are dealt by bitmap and sorted, so a bitmap is one stretch of rows; the last of a batch
    is carried over.  Block sizes come to the words after they have been dealt.
    """
    laid = words.select("block", "attr", "bitmap", "word_no", "bits").filter("bits <> 0").repartition("block", "attr", "bitmap")
    laid = laid.join(F.broadcast(blocks), "block").select("block", "attr", "bitmap", (F.col("word_no") - F.col("first_word")).alias("at"), "bits", F.col("words").cast("long").alias("words"), F.col("last_rows").cast("long").alias("last_rows")).sortWithinPartitions("block", "attr", "bitmap", "at")
    kind = "<u8" if codec.w > 32 else "<u4" if codec.w > 16 else "<u2"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:

        def whole(table: pa.Table, last: bool) -> int:
            """How many words belong to bitmaps that are there to their ends."""
            key = [table[c].to_numpy() for c in ("block", "attr", "bitmap")]
            new = np.concatenate([[True], np.any([k[1:] != k[:-1] for k in key], axis=0)])
            return len(new) if last else int(np.flatnonzero(new)[-1])

        def emit(table: pa.Table) -> Iterator[pa.RecordBatch]:
            key = [table[c].to_numpy() for c in ("block", "attr", "bitmap")]
            first = np.flatnonzero(np.concatenate([[True], np.any([k[1:] != k[:-1] for k in key], axis=0)]))
            at, bits, total, tail = (table[c].to_numpy() for c in ("at", "bits", "words", "last_rows"))
            cuts, edge = stream_cuts(first, len(at), total[first], codec), np.append(first, len(at))
            for x, y in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                own, some = slice(edge[x], edge[y]), first[x:y]
                data, lengths = encode_sparse(np.repeat(np.arange(y - x), np.diff(edge[x : y + 1])), at[own], bits[own].view(np.uint64), total[own], tail[own], codec, kind)
                ends = np.concatenate([[0], np.cumsum(lengths)]) * data.itemsize
                payload = pa.Array.from_buffers(pa.large_binary(), len(lengths), [None, pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(data)])
                columns = [pa.array(key[0][some], pa.int64()), pa.array(key[1][some], pa.int32()), pa.array(key[2][some], pa.int64()), pa.array(lengths, pa.int64()), payload.cast(pa.binary())]
                yield pa.RecordBatch.from_arrays(columns, ["block", "attr", "bitmap", "n_words", "payload"])

        held, n, full = [], 0, GATHERED
        for batch in batches:
            if batch.num_rows:
                held.append(pa.Table.from_batches([batch]))
                n += batch.num_rows
            if n >= full:
                table = pa.concat_tables(held)
                stop = whole(table, False)
                held, n = [table.slice(stop)], table.num_rows - stop
                full = max(GATHERED, 2 * n)  # one long bitmap is not looked through again for each batch
                if stop:
                    yield from emit(table.slice(0, stop))
        if n:
            yield from emit(pa.concat_tables(held))

    return laid.mapInArrow(run, "block long, attr int, bitmap long, n_words long, payload binary")
