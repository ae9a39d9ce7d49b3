"""Combining many bitmaps: several strategies, one answer, with work counters.

Kernels take bitmaps as runs (start, end, bit) or words on numpy; ``combine`` runs them block by
block on Spark, ``relational`` is the same as one aggregation of words.
"""

from __future__ import annotations

import heapq
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.operators.codecs import bit_runs, pack_bits, unpack_bits


@dataclass
class Work:
    steps: int = 0
    runs_read: int = 0
    heap_operations: int = 0
    words_touched: int = 0
    temporaries: int = 0
    temporary_sizes: list[int] = field(default_factory=list)


Runs = list[tuple[int, int, int]]


def to_runs(bits: np.ndarray) -> Runs:
    out, at = [], 0
    for b, n in bit_runs(bits):
        out.append((at, at + n, b))
        at += n
    return out


def from_runs(runs: Runs, rows: int) -> np.ndarray:
    out = np.zeros(rows, dtype=np.int8)
    for s, e, b in runs:
        out[s:e] = b
    return out


def _append(out: Runs, s: int, e: int, b: int) -> None:
    if out and out[-1][2] == b:
        out[-1] = (out[-1][0], e, b)
    else:
        out.append((s, e, b))


def symmetric_test(op: str, n: int, t: int = 0) -> Callable[[int], int]:
    """Result bit from the number of ones."""
    return {
        "and": lambda c: int(c == n),
        "or": lambda c: int(c > 0),
        "xor": lambda c: c & 1,
        "nand": lambda c: int(c < n),
        "nor": lambda c: int(c == 0),
        "xnor": lambda c: 1 - (c & 1),
        "at_least": lambda c: int(c >= t),
        "exactly": lambda c: int(c == t),
        "majority": lambda c: int(2 * c > n),
        "all_equal": lambda c: int(c in (0, n)),
    }[op]


def scan_runs(bitmaps: list[Runs], f: Callable[[list[int]], int], work: Work | None = None) -> Runs:
    """Any function of L inputs: go from one nearest run end to the next over all inputs."""
    work = work or Work()
    at, pos, out = 0, [0] * len(bitmaps), []
    rows = bitmaps[0][-1][1] if bitmaps and bitmaps[0] else 0
    while at < rows:
        values, nearest = [], rows
        for i, runs in enumerate(bitmaps):
            while runs[pos[i]][1] <= at:
                pos[i] += 1
                work.runs_read += 1
            values.append(runs[pos[i]][2])
            nearest = min(nearest, runs[pos[i]][1])
        _append(out, at, nearest, f(values))
        work.steps += 1
        at = nearest
    return out


def heap_runs(bitmaps: list[Runs], op: str, t: int = 0, inverted: list[bool] | None = None, work: Work | None = None) -> Runs:
    """Symmetric functions: a heap of run ends and a running count of ones; inputs can be inverted."""
    work = work or Work()
    flip = inverted or [False] * len(bitmaps)
    test, out, at = symmetric_test(op, len(bitmaps), t), [], 0
    heap = [(runs[0][1], i, 0) for i, runs in enumerate(bitmaps) if runs]
    heapq.heapify(heap)
    ones = sum(runs[0][2] ^ flip[i] for i, runs in enumerate(bitmaps) if runs)
    while heap:
        end = heap[0][0]
        if end > at:
            _append(out, at, end, test(ones))
            work.steps += 1
            at = end
        _, i, k = heapq.heappop(heap)
        work.heap_operations += 1
        if k + 1 < len(bitmaps[i]):
            ones += (bitmaps[i][k + 1][2] ^ flip[i]) - (bitmaps[i][k][2] ^ flip[i])
            heapq.heappush(heap, (bitmaps[i][k + 1][1], i, k + 1))
            work.heap_operations += 1
            work.runs_read += 1
    return out


def pairwise(bitmaps: list[Runs], op: str, by_size: bool = False, work: Work | None = None) -> Runs:
    """Two at a time, left to right or from the smallest up."""
    work = work or Work()
    order = sorted(bitmaps, key=len) if by_size else list(bitmaps)
    out = order[0]
    for other in order[1:]:
        out = heap_runs([out, other], op, work=work)
        work.temporaries += 1
        work.temporary_sizes.append(len(out))
    return out


def smallest_first(bitmaps: list[Runs], op: str, work: Work | None = None) -> Runs:
    """Combine the two smallest again and again."""
    work = work or Work()
    heap = [(len(r), i, r) for i, r in enumerate(bitmaps)]
    heapq.heapify(heap)
    n = len(heap)
    while len(heap) > 1:
        (_, _, a), (_, _, b) = heapq.heappop(heap), heapq.heappop(heap)
        merged = heap_runs([a, b], op, work=work)
        heapq.heappush(heap, (len(merged), n, merged))
        n, work.temporaries = n + 1, work.temporaries + 1
        work.temporary_sizes.append(len(merged))
        work.heap_operations += 3
    return heap[0][2]


def in_place(bitmaps: list[Runs], op: str, rows: int, work: Work | None = None) -> Runs:
    """An uncompressed accumulator; runs that change nothing are skipped."""
    work = work or Work()
    acc = np.full(rows, int(op == "and"), dtype=np.int8)
    for runs in bitmaps:
        for s, e, b in runs:
            work.runs_read += 1
            if op == "and" and not b:
                acc[s:e] = 0
            elif op == "or" and b:
                acc[s:e] = 1
            elif op == "xor" and b:
                acc[s:e] ^= 1
            else:
                continue
            work.words_touched += -(-(e - s) // 32)
    return to_runs(acc)


def choose_strategy(op: str, sizes: list[int], rows: int, density: float) -> str:
    """In place for OR of sparse and AND of dense inputs, pairwise for few, else the heap."""
    if (op == "or" and density < 0.05) or (op == "and" and density > 0.95):
        return "in_place"
    return "pairwise" if len(sizes) <= 3 else "heap"


STRATEGIES = ("scan", "heap", "pairwise", "pairwise_sorted", "smallest_first", "in_place")


def combine_runs(bitmaps: list[Runs], op: str, strategy: str, rows: int, work: Work | None = None) -> Runs:
    if not bitmaps:
        return [(0, rows, 0)] if rows else []
    if strategy == "scan":
        test = symmetric_test(op, len(bitmaps))
        return scan_runs(bitmaps, lambda v: test(sum(v)), work)
    if strategy == "heap":
        return heap_runs(bitmaps, op, work=work)
    if strategy in ("pairwise", "pairwise_sorted"):
        return pairwise(bitmaps, op, strategy == "pairwise_sorted", work)
    if strategy == "smallest_first":
        return smallest_first(bitmaps, op, work)
    return in_place(bitmaps, op, rows, work)


#: Words of a block that one task combines at once; any cut is right, as combining goes word by word.
CHUNK_WORDS = 1 << 16
#: What ``combine`` counts beside its answer, chunk by chunk.
COUNTERS = ("steps", "runs_read", "heap_operations", "words_touched", "temporaries", "largest_temporary")


def combine(words: DataFrame, blocks: DataFrame, op: str, strategy: str, w: int = 32) -> DataFrame:
    """(block, word_no, bits, COUNTERS) of the combination of all bitmaps in ``words``.

    Work goes chunk by chunk of a block's words, which bounds a task's memory.  Bitmaps without a
    word in a chunk are zero there and still count.
    """
    total = words.select("attr", "bitmap").distinct().count()
    own = blocks.select("block", "first_word", "words", "last_rows", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("words") - 1) / CHUNK_WORDS).cast("long"))).alias("chunk"))
    sized = words.join(blocks.select("block", "first_word"), "block").withColumn("chunk", F.floor((F.col("word_no") - F.col("first_word")) / CHUNK_WORDS)).drop("first_word")
    sized = own.join(sized, ["block", "chunk"], "left").select("block", "chunk", "attr", "bitmap", "word_no", "bits", "first_word", "words", "last_rows")

    def run(table: pa.Table) -> pa.Table:
        block, chunk, first, n, tail = (int(table[c][0].as_py()) for c in ("block", "chunk", "first_word", "words", "last_rows"))
        first, n, ends = first + chunk * CHUNK_WORDS, min(CHUNK_WORDS, n - chunk * CHUNK_WORDS), (chunk + 1) * CHUNK_WORDS >= n
        rows = (n - 1) * w + (tail if ends else w)
        table = table.filter(pc.is_valid(table["bitmap"]))
        key = table["attr"].to_numpy().astype(np.int64) * (1 << 40) + table["bitmap"].to_numpy()
        order = np.lexsort([table["word_no"].to_numpy(), key])
        key, at, bits = key[order], table["word_no"].to_numpy()[order] - first, table["bits"].to_numpy()[order].astype(np.uint64)
        edges = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1], [True]])) if len(key) else np.zeros(1, dtype=np.int64)
        bitmaps = [sparse_runs(at[i:j], bits[i:j], w, rows) for i, j in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)]
        bitmaps += [[(0, rows, 0)]] * (total - len(bitmaps))
        work = Work()
        packed = pack_bits(from_runs(combine_runs(bitmaps, op, strategy, rows, work), rows), w)
        hit = np.flatnonzero(packed)
        counted = [work.steps, work.runs_read, work.heap_operations, work.words_touched, work.temporaries, max(work.temporary_sizes, default=0)]
        return pa.table(
            [pa.array([block] * len(hit), pa.int64()), pa.array(hit + first, pa.int64()), pa.array(packed[hit].astype(np.int64)), *(pa.array([c] * len(hit), pa.int64()) for c in counted)],
            ["block", "word_no", "bits", *COUNTERS],
        )

    return sized.groupBy("block", "chunk").applyInArrow(run, "block long, word_no long, bits long, " + ", ".join(f"{c} long" for c in COUNTERS))


def sparse_runs(at: np.ndarray, bits: np.ndarray, w: int, rows: int) -> Runs:
    """Runs (start, end, bit) of a bitmap from its non-zero words alone: what lies between them is not unpacked."""
    if not len(at):
        return [(0, rows, 0)]
    flat = ((bits[:, None] >> np.arange(w, dtype=np.uint64)) & np.uint64(1)).astype(np.int8)
    row = (at[:, None] * w + np.arange(w)).ravel()[flat.ravel() == 1]
    starts = row[np.concatenate([[True], row[1:] != row[:-1] + 1])]
    stops = row[np.concatenate([row[1:] != row[:-1] + 1, [True]])] + 1
    out, here = [], 0
    for i, j in zip(starts.tolist(), stops.tolist(), strict=True):
        if i > here:
            out.append((here, i, 0))
        out.append((i, j, 1))
        here = j
    if here < rows:
        out.append((here, rows, 0))
    return out


def relational(words: DataFrame, op: str) -> DataFrame:
    """The same for AND, OR and XOR as one aggregation of words, merged before the shuffle."""
    total = words.select("attr", "bitmap").distinct().count()
    agg = {"and": F.bit_and, "or": F.bit_or, "xor": F.bit_xor}[op]
    out = words.groupBy("block", "word_no").agg(agg("bits").alias("bits"), F.count(F.lit(1)).alias("n"))
    out = out.filter(F.col("n") == total) if op == "and" else out
    return out.filter("bits <> 0").select("block", "word_no", "bits")
