"""k-of-N codes: how many bitmaps, which code order, and codes from ranks without enumeration.

A code is a sorted array of k positions, 1 being the leftmost bit.  All orders are ascending:
``numeric`` reads the code as a binary number, ``reflected`` is the order in which the sense flips
at every one, so that neighbours differ in two bits.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: From so many distinct values on a column may use k = 2, 3, 4.
CAPS = ((5, 1), (21, 2), (85, 3))
ALLOCATIONS = ("numeric", "reflected", "random", "reflected_alternating", "freq_reflected")


def sufficient_bitmaps(n: int, k: int) -> int:
    """ceil(k * n**(1/k)): enough bitmaps for n values, by integer arithmetic."""
    lo = round(k * n ** (1 / k))
    lo = max(k, lo - 2)
    while lo**k < n * k**k:
        lo += 1
    return lo


def min_bitmaps(n: int, k: int) -> int:
    """The smallest N with C(N, k) >= n."""
    lo, hi = k, max(k, sufficient_bitmaps(max(n, 1), k))
    while lo < hi:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if math.comb(mid, k) >= n else (mid + 1, hi)
    return lo


def cap_k(n: int, k: int) -> int:
    """k, or less for a column of few distinct values."""
    for below, most in CAPS:
        if n < below:
            return min(k, most)
    return k


def padded_bitmaps(n: int, k: int) -> tuple[int, int]:
    """(N, constant ones): never more varying bitmaps than k = 1 needs, by fixing leading ones."""
    best = min(range(1, k + 1), key=lambda j: (min_bitmaps(n, j), j))
    return min_bitmaps(n, best) + k - best, k - best


def balanced_radices(n: int, kappa: int) -> list[int]:
    """kappa near-equal factors with a product of at least n, their sum as small as can be."""
    low = max(1, int(n ** (1 / kappa)))
    while (low + 1) ** kappa <= n:
        low += 1
    for more in range(kappa + 1):
        if (low + 1) ** more * low ** (kappa - more) >= n:
            return [low + 1] * more + [low] * (kappa - more)
    return [low + 1] * kappa


def compare_bitmap_counts(n: int, kappa: int) -> dict[str, int]:
    """Bitmaps of k-of-N against kappa-component encoding of n values."""
    return {"k_of_n": min_bitmaps(n, kappa), "components": sum(balanced_radices(n, kappa))}


def zipf_frequency(n: int, distinct: int, s: float, rank: int) -> float:
    return n / rank**s / sum(j**-s for j in range(1, distinct + 1))


def zipf_cardinality_bound(n: int, s: float) -> float:
    return n ** (1 / s)


def unrank(ranks: np.ndarray, n_bits: int, k: int, scheme: str) -> np.ndarray:
    """Codes (one row of k positions each) of ranks, by cumulative binomials."""
    rest = np.asarray(ranks, dtype=np.int64).copy()
    out = np.empty((len(rest), k), dtype=np.int64)
    for step, j in enumerate(range(k, 0, -1)):
        table = np.array([min(math.comb(m, j), 2**62) for m in range(n_bits + 1)], dtype=np.int64)
        right = np.searchsorted(table, rest, side="right") - 1  # bits to the right of this one
        out[:, step] = n_bits - right
        rest = rest - table[right]
        if scheme == "reflected" and j > 1:
            inner = np.array([math.comb(m, j - 1) for m in range(n_bits + 1)], dtype=np.int64)
            rest = inner[right] - 1 - rest
    return out


def code_list(n_bits: int, k: int, count: int | None = None, scheme: str = "reflected", seed: int = 0, descending: bool = False, permute: list[int] | None = None, invert: list[int] | None = None) -> list[tuple[int, ...]]:
    """The first ``count`` codes of a scheme on the driver (small tables, tests, code studies).

    permute: new position of each bit; invert: bits whose meaning flips (dense codes of any weight).
    """
    total = math.comb(n_bits, k)
    count = total if count is None else count
    if scheme in ("numeric", "reflected"):
        ranks = np.arange(total - 1, total - 1 - count, -1) if descending else np.arange(count)
        codes = [tuple(int(x) for x in row) for row in unrank(ranks, n_bits, k, scheme)]
    elif scheme == "random":
        order = keyed_permutation(np.arange(count), total, seed)
        codes = [tuple(int(x) for x in row) for row in unrank(order, n_bits, k, "numeric")]
    elif scheme == "weight_adjacent":
        codes = [c for c in _level_walk(n_bits) if len(c) == k][:count]
    elif scheme == "long_run":
        codes = [c for c in _long_run_walk(n_bits) if len(c) == k][:count]
    else:
        raise ValueError(scheme)
    if permute:
        codes = [tuple(sorted(permute[p - 1] for p in c)) for c in codes]
    if invert:
        codes = [tuple(sorted(set(c) ^ set(invert))) for c in codes]
    return codes


def _level_path(n_bits: int, level: int) -> list[tuple[int, ...]]:
    """A path through all vectors of n_bits between two weights, level and level + 1, each visited once over all paths.

    The vectors with a leading one follow a path of the shorter vectors one level down, their bits
    exchanged so that the ends meet; the others follow the path of the same level.
    """
    if n_bits == 1:
        return [(0,), (1,)] if level == 0 else []
    if not 0 <= level < n_bits:
        return []
    turn = _level_exchange(n_bits - 1)
    return [(1, *(x[i] for i in turn)) for x in _level_path(n_bits - 1, level - 1)] + [(0, *x) for x in _level_path(n_bits - 1, level)]


def _level_exchange(n_bits: int) -> tuple[int, ...]:
    if n_bits <= 1:
        return (0,)
    longer = (*_level_exchange(n_bits - 1), n_bits - 1)
    twice = tuple(longer[i] for i in longer)
    return (twice[-1], *twice[:-1])


def _level_walk(n_bits: int) -> Iterator[tuple[int, ...]]:
    """All bit vectors in a Gray code that leaves a weight for good once it has passed it by two.

    Vectors of one weight, taken out of it, differ from their neighbours in two bits.
    """
    for level in range(n_bits):
        path = _level_path(n_bits, level)
        for x in path[::-1] if level % 2 else path:
            yield tuple(i + 1 for i, bit in enumerate(x) if bit)


def _long_run_walk(n_bits: int) -> Iterator[tuple[int, ...]]:
    """A cyclic Gray code with long runs, made from the cycles of its two halves.

    Steps go through one half or the other in a fixed pattern of one period of the shorter half, an
    odd number of them through it, as evenly mixed as can be; so every pair of places is met once.
    """
    half = n_bits // 2
    low, high = _binary_reflected(half), _binary_reflected(n_bits - half)
    period = len(low)
    odd = period // 2 - 1 if period > 2 else 1
    pattern = [(i + 1) * odd // period > i * odd // period for i in range(period)]
    i = j = 0
    for step in range(len(low) * len(high)):
        yield tuple(sorted([*low[i], *(p + half for p in high[j])]))
        if pattern[step % period]:
            i = (i + 1) % len(low)
        else:
            j = (j + 1) % len(high)


def _binary_reflected(n_bits: int) -> list[tuple[int, ...]]:
    return [tuple(p + 1 for p in range(n_bits) if (g >> (n_bits - 1 - p)) & 1) for g in (i ^ (i >> 1) for i in range(2**n_bits))]


def reflected_less(a: list[int], b: list[int]) -> bool:
    """Dense bit vectors: at the first difference the vector whose bit is the parity of what precedes is smaller."""
    ones = 0
    for x, y in zip(a, b, strict=True):
        if x != y:
            return x == ones % 2
        ones += x
    return False


def reflected_less_sparse(a: tuple[int, ...], b: tuple[int, ...]) -> bool:
    """The same order on sorted positions of ones, of any weights."""
    for i, (x, y) in enumerate(zip(a, b, strict=False)):
        if x != y:
            # the one with the earlier next one has a 1 at the first difference
            return (x < y) == (i % 2 == 1)
    i = min(len(a), len(b))
    return len(a) != len(b) and (len(a) > len(b)) == (i % 2 == 1)


def reflected_key(code: Column, n_bits: int | None = None) -> Column:
    """An array whose plain order is the reflected order; n_bits is needed where weights vary."""
    padded = code if n_bits is None else F.array_append(code, F.lit(n_bits + 1))
    return F.transform(padded, lambda p, i: F.when(i % 2 == 0, -p).otherwise(p))


def unrank_column(n_bits: int, k: int, scheme: str):
    """An Arrow function: codes of a column of ranks."""

    @F.pandas_udf("array<long>")
    def codes(rank: pd.Series) -> pd.Series:
        return pd.Series(list(unrank(rank.to_numpy(), n_bits, k, scheme)))

    return codes


def keyed_permutation(ranks: np.ndarray, total: int, seed: int = 0) -> np.ndarray:
    """A random-looking bijection of 0 .. total-1: a Feistel network, walked until it is back in range."""
    half = max(1, ((total - 1).bit_length() + 1) // 2)
    low = (1 << half) - 1

    def once(x: np.ndarray) -> np.ndarray:
        left, right = x >> half, x & low
        for turn in range(6):
            mixed = (right.astype(np.uint64) + np.uint64((seed * 8 + turn + 1) * 0x9E3779B97F4A7C15 % 2**64)) * np.uint64(0xBF58476D1CE4E5B9)
            mixed ^= mixed >> np.uint64(29)
            mixed *= np.uint64(0x94D049BB133111EB)
            left, right = right, left ^ ((mixed >> np.uint64(32)).astype(np.int64) & low)
        return (left << half) | right

    with np.errstate(over="ignore"):
        out = once(np.asarray(ranks, dtype=np.int64))
        while (out >= total).any():
            out = np.where(out >= total, once(out), out)
    return out


def permuted_column(total: int, seed: int):
    """An Arrow function: the permuted ranks of a column of ranks."""

    @F.pandas_udf("long")
    def permuted(rank: pd.Series) -> pd.Series:
        return pd.Series(keyed_permutation(rank.to_numpy(), total, seed))

    return permuted


def coded(df: DataFrame, rank: str, n_values: int, k: int, scheme: str = "reflected", seed: int = 0, n_bits: int | None = None, prefix_ones: int = 0, permute: list[int] | None = None) -> DataFrame:
    """Add ``code`` for ranks 0 .. n_values-1.  k = 1 stays native.  ``permute``: new position of each bit."""
    n_bits = n_bits or min_bitmaps(n_values, k)
    r = F.col(rank).cast("long")
    if scheme == "random":
        r, scheme = permuted_column(math.comb(n_bits, k), seed)(r), "numeric"
    if k == 1:
        code = F.array((F.lit(n_bits) - r).cast("long"))
    else:
        code = unrank_column(n_bits, k, scheme)(r)
    if prefix_ones:
        code = F.concat(F.array(*[F.lit(i + 1).cast("long") for i in range(prefix_ones)]), F.transform(code, lambda p: p + prefix_ones))
    if permute:
        table = F.array(*[F.lit(p).cast("long") for p in permute])
        code = F.array_sort(F.transform(code, lambda p: F.element_at(table, p.cast("int"))))
    return df.withColumn("code", code)


def values_per_bitmap(codes: DataFrame) -> DataFrame:
    """(attr, bitmap, values): how many values each bitmap serves; at most C(N-1, k-1)."""
    return codes.select("attr", F.explode("code").alias("bitmap")).groupBy("attr", "bitmap").agg(F.count(F.lit(1)).alias("values"))


def code_frame(spark: SparkSession, codes: list[tuple[int, ...]], n_bits: int, name: str) -> DataFrame:
    """(name, rank, bit, value): a code list as dense bits, for the code studies."""
    rows = [(name, r, p, int(p in c)) for r, c in enumerate(map(set, codes)) for p in range(1, n_bits + 1)]
    return spark.createDataFrame(rows, "name string, rank long, bit long, value long")
