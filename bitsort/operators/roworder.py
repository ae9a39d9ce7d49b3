"""Row orders and global row numbers.

An order is a list of sort keys; rows are range-partitioned on them, sorted within partitions,
stored (range bounds are sampled, so they must not be computed twice) and numbered by the counts of
their files and their places in them.
"""

from __future__ import annotations

import re
from itertools import permutations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bitsort.operators.codes import reflected_key
from bitsort.operators.dictionary import BROADCAST_VALUES, attribute_counts, histograms
from bitsort.plans.recovery import partitions, stored, stored_at

#: A prime and multipliers of the portable shuffle: h = sum(c_i * m_i) mod p, any SQL can compute it.
SHUFFLE_PRIME = 2_147_483_647
SHUFFLE_FACTORS = (48_271, 69_621, 16_807, 39_373, 40_014, 40_692, 53_668, 12_211, 37_791, 24_851)


def shuffle_key(cols: list[str], seed: int = 0) -> Column:
    total = F.lit(seed).cast("long")
    for i, c in enumerate(cols):
        total = total + F.pmod(F.col(c).cast("long") * F.lit(SHUFFLE_FACTORS[i % 10] + i // 10), F.lit(SHUFFLE_PRIME)) * F.lit(SHUFFLE_FACTORS[(i + 3) % 10])
    return F.pmod(F.pmod(total, F.lit(SHUFFLE_PRIME)) * F.lit(48_271) + F.pmod(total, F.lit(65_521)) * F.lit(69_621), F.lit(SHUFFLE_PRIME))


def _counted(df: DataFrame, cols: list[str]) -> DataFrame:
    """Add _f<i>, the frequency of each column's value."""
    every = stored(histograms(df, cols))
    sizes = attribute_counts(every)
    for i, c in enumerate(cols):
        h = every.filter(F.col("attr") == i).select(F.col("value").alias(f"_v{i}"), F.col("cnt").alias(f"_f{i}"))
        h = F.broadcast(h) if sizes.get(i, 0) <= BROADCAST_VALUES else h
        df = df.join(h, F.col(c).cast("long").eqNullSafe(F.col(f"_v{i}"))).drop(f"_v{i}")
    return df


def order_keys(df: DataFrame, how: str, cols: list[str], seed: int = 0, blocks: int = 1, rows: int | None = None, codes: dict[str, str] | None = None, n_bits: dict[str, int] | None = None, natural: list[str] | None = None, ties: str = "freq_vector", sort_positions: bool = False) -> tuple[DataFrame, list[Column | str]]:
    """The frame (with helper columns) and the keys of an order; plain columns by their names.

    how: shuffle, natural, lex, cluster, blocks, reflected, freq_lex, rarest_first.
    """
    plain = list(cols)
    if how == "shuffle":
        return df, [shuffle_key(cols, seed), *plain]
    if how == "natural":
        return df, [*(natural or []), *plain]
    if how == "lex":
        return df, plain
    if how == "cluster":
        return df, [F.xxhash64(*plain), *plain]
    if how == "blocks":
        # the row's place in the shuffled input says which block it is in
        numbered = number_rows(df, *order_keys(df, "shuffle", cols, seed), row_id="_in")
        n = rows or numbered.count()
        return numbered.withColumn("_b", F.floor(F.col("_in") * blocks / n)).drop("_in", "block"), ["_b", *plain]
    if how == "reflected":
        # concatenated code positions, columns one after the other, as one array key
        shifted, before = [], 0
        for c in cols:
            shifted.append(F.transform(F.col((codes or {}).get(c, f"{c}_code")), _shift(before)))
            before += (n_bits or {})[c]
        key = F.concat(*shifted)
        key = F.array_sort(key) if sort_positions else key
        return df, [reflected_key(key), *plain]
    if how == "freq_lex":
        return _counted(df, cols), [x for i, c in enumerate(cols) for x in (f"_f{i}", c)]
    if how == "rarest_first":
        df = _counted(df, cols)
        pairs = F.array_sort(F.array(*[F.struct(F.col(f"_f{i}").alias("f"), F.lit(i).alias("c"), F.col(c).cast("long").alias("v")) for i, c in enumerate(cols)]))
        if ties == "pairwise":
            return df, [pairs]
        return df, [F.transform(pairs, lambda s: s["f"]), pairs]
    raise ValueError(how)


def _shift(by: int):
    return lambda p: p + by


def layout(bits: list[int]) -> list[tuple[int, int]]:
    """(which long, by how many places shifted) for numbers of so many bits, packed in order into few longs."""
    longs: list[list[int]] = []
    for b in bits:
        if not longs or sum(longs[-1]) + b > 63:
            longs.append([])
        longs[-1].append(b)
    return [(i, sum(own[j + 1 :])) for i, own in enumerate(longs) for j in range(len(own))]


def packed(numbers: list[Column], bits: list[int]) -> list[Column]:
    """Longs that sort as the numbers do, the first one first."""
    out: list[Column] = []
    for x, (i, shift) in zip(numbers, layout(bits), strict=True):
        x = F.call_function("shiftleft", x.cast("long"), F.lit(shift))
        out = [*out, x] if i == len(out) else [*out[:-1], out[-1].bitwiseOR(x)]
    return out


def unpacked(longs: list[Column], bits: list[int]) -> list[Column]:
    return [F.shiftrightunsigned(longs[i], shift).bitwiseAND(F.lit((1 << b) - 1)) for b, (i, shift) in zip(bits, layout(bits), strict=True)]


def packed_reflected_keys(key: Column, length: int, bits: int) -> list[Column]:
    """The same order as ``reflected_key`` of arrays of one length, positions of so many bits, in few longs."""
    at = [F.element_at(key, i + 1).cast("long") for i in range(length)]
    return packed([p if i % 2 else F.lit((1 << bits) - 1) - p for i, p in enumerate(at)], [bits] * length)


def number_rows(df: DataFrame, _frame: DataFrame, keys: list[Column | str], row_id: str = "row_id", block_rows: int | None = None) -> DataFrame:
    """Sort by keys and add row_id (0-based, gapless) and block.  The sorted table is the recovery point."""
    return counted_rows(df, _frame, keys, row_id, block_rows)[0]


def counted_rows(df: DataFrame, _frame: DataFrame, keys: list[Column | str], row_id: str = "row_id", block_rows: int | None = None) -> tuple[DataFrame, int]:
    """The numbered rows, and how many they are."""
    # only computed keys travel beside the row
    computed = {f"_o{i}": k for i, k in enumerate(keys) if not isinstance(k, str)}
    names = [k if isinstance(k, str) else f"_o{i}" for i, k in enumerate(keys)]
    named = _frame.withColumns(computed).select(*dict.fromkeys([*df.columns, *names]))
    own = named.repartitionByRange(partitions(df), *names).sortWithinPartitions(*names).select(*df.columns)
    read = df.sparkSession.read.schema(own.schema).parquet(stored_at(own))
    placed = read.select("*", F.col("_metadata.file_name").alias("_file"), F.col("_metadata.row_index").alias("_at"))
    counts = {r["_file"]: r["n"] for r in placed.groupBy("_file").agg(F.count(F.lit(1)).alias("n")).collect()}  # one row a partition
    offsets, total = {}, 0
    for f in sorted(counts, key=_file_place):
        offsets[f] = total
        total += counts[f]
    table = df.sparkSession.createDataFrame(pa.table({"_file": pa.array(list(offsets), pa.string()), "_before": pa.array(list(offsets.values()), pa.int64())}))
    out = placed.join(F.broadcast(table), "_file").withColumn(row_id, F.col("_before") + F.col("_at")).drop("_file", "_at", "_before")
    # computed for a single block too: a constant would turn joins by block into nested loops
    return out.withColumn("block", F.floor(F.col(row_id) / (block_rows or max(total, 1))).cast("long")), total


def _file_place(name: str) -> tuple[int, int]:
    """Partition and, where a setting splits its rows, the file's number within it, from the name of a file that Spark wrote."""
    part, piece = re.match(r"part-(\d+)-.*?(?:-c(\d+))?\.", name).groups()
    return int(part), int(piece or 0)


def order_rows(df: DataFrame, how: str, cols: list[str], block_rows: int | None = None, **options) -> DataFrame:
    """Rows in an order, with row_id and block."""
    return ordered_rows(df, how, cols, block_rows, **options)[0]


def ordered_rows(df: DataFrame, how: str, cols: list[str], block_rows: int | None = None, **options) -> tuple[DataFrame, int]:
    """Rows in an order, with row_id and block, and how many they are."""
    return counted_rows(df, *order_keys(df, how, cols, **options), block_rows=block_rows)


def bitmap_positions(dictionary: DataFrame, words: DataFrame | None, n_rows: int, how: str, w: int = 32) -> DataFrame:
    """(attr, bitmap, position): all bitmaps of an index in one order, for the reflected row order.

    Without ``words`` the dictionary's counts tell how many rows each bitmap has: as many as the
    values whose codes it is in.

    IF incompressible first, MSF moderately sparse first, SF sparse first, set_bits, interleaved (the
    first bitmap of every column, then the second ones), natural (column after column).
    """
    named = dictionary.select("attr", "cnt", F.explode("code").alias("bitmap"))
    if words is None:
        every = named.groupBy("attr", "bitmap").agg(F.sum("cnt").cast("double").alias("_ones"))
    else:
        ones = words.groupBy("attr", "bitmap").agg(F.sum(F.bit_count("bits")).cast("double").alias("_ones"))
        every = named.select("attr", "bitmap").distinct().join(ones, ["attr", "bitmap"], "left")
    d = F.coalesce("_ones", F.lit(0.0)) / F.lit(float(max(n_rows, 1)))
    key = {"IF": F.abs(d - 0.5), "MSF": -F.least(d, (1 - d) / (4 * w - 1)), "SF": d, "set_bits": d, "interleaved": F.col("bitmap").cast("double"), "natural": F.col("attr").cast("double")}[how]
    every = every.withColumn("_key", key).select("attr", "bitmap", "_key")
    if words is None and dictionary.agg(F.sum("k")).first()[0] <= BROADCAST_VALUES:  # at most so many bitmaps
        one = Window.partitionBy(F.col("bitmap") < 0).orderBy("_key", "attr", "bitmap")
        return every.select("attr", "bitmap", F.row_number().over(one).cast("long").alias("position"))
    placed = number_rows(every, every, ["_key", "attr", "bitmap"], "position")
    return placed.select("attr", "bitmap", (F.col("position") + 1).alias("position"))


# --- driver-side orders of a few rows, for comparison and tests ---------------------------------


def hamming(rows: np.ndarray) -> int:
    return int((rows[1:] != rows[:-1]).sum()) if len(rows) else 0


def best_order_exhaustive(rows: np.ndarray) -> tuple[int, tuple[int, ...]]:
    """The order of at most 8 distinct rows with the fewest bit changes (equal rows stay together)."""
    distinct = np.unique(rows, axis=0)
    if len(distinct) > 8:
        raise ValueError("at most 8 distinct rows")
    return min((hamming(distinct[list(p)]), p) for p in permutations(range(len(distinct))))


def tour_order(rows: np.ndarray) -> np.ndarray:
    """A tour of at most 500 distinct rows by a minimum spanning tree in preorder (within twice the best)."""
    distinct, where = np.unique(rows, axis=0, return_inverse=True)
    n = len(distinct)
    if n > 500:
        raise ValueError("at most 500 distinct rows")
    d = (distinct[:, None] != distinct[None]).sum(axis=2)
    inside, parent, near = np.zeros(n, bool), np.zeros(n, int), np.full(n, 1 << 30)
    near[0], children = 0, {i: [] for i in range(n)}
    for step in range(n):
        u = int(np.argmin(np.where(inside, 1 << 30, near)))
        inside[u] = True
        if step:
            children[int(parent[u])].append(u)
        closer = d[u] < near
        parent[closer & ~inside], near[closer & ~inside] = u, d[u][closer & ~inside]
    walk, stack = [], [0]
    while stack:
        u = stack.pop()
        walk.append(u)
        stack += children[u][::-1]
    return np.argsort(np.argsort(walk)[where.ravel()], kind="stable")


def two_switch(rows: np.ndarray, iterations: int = 1000, seed: int = 0) -> np.ndarray:
    """Swap random pairs of rows while that lowers the number of bit changes."""
    rng, order = np.random.default_rng(seed), np.arange(len(rows))
    cost = hamming(rows[order])
    for _ in range(iterations):
        i, j = rng.integers(0, len(rows), 2)
        order[[i, j]] = order[[j, i]]
        new = hamming(rows[order])
        if new > cost:
            order[[i, j]] = order[[j, i]]
        else:
            cost = new
    return order


def uncompressed_reorder(dense: np.ndarray) -> np.ndarray:
    """Order of the rows of a small uncompressed index by the reflected order of its bit vectors."""
    flips = np.cumsum(dense, axis=1) - dense
    return np.lexsort((dense ^ (flips & 1))[:, ::-1].T)
