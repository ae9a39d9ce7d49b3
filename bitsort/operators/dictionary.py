"""Histograms, dictionaries (value -> rank -> code), binning and mixed-radix components."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bitsort.operators import codes as C
from bitsort.plans.recovery import partitions, stored

#: Dictionaries of at most so many rows are broadcast to the rows they encode.
BROADCAST_VALUES = 200_000


#: Types whose values are their own numbers; columns of all other types are numbered through ``typed_values``.
NUMBERS = ("tinyint", "smallint", "int", "bigint", "boolean")


def typed_values(df: DataFrame, cols: list[str]) -> dict[str, DataFrame]:
    """For each column that holds no integers: (value in its own type, number), numbers in value order, null first.

    Numbers come from a range sort and counts by partition, as all ranks do.
    """
    kinds, out = dict(df.dtypes), {}
    for c in cols:
        if kinds[c] not in NUMBERS:
            hist = df.groupBy(F.col(c).alias("value")).agg(F.count(F.lit(1)).alias("cnt")).withColumn("attr", F.lit(0))
            out[c] = stored(ranked(hist).select("value", F.col("rank").alias("number")))
    return out


def numbered_values(df: DataFrame, cols: list[str], typed: dict[str, DataFrame], keep: tuple[str, ...] = ()) -> DataFrame:
    """``cols`` of ``df`` as integers: columns of other types by their numbers, null where a value has none; ``keep`` as they are."""
    for c, values in typed.items():
        part = values.select(F.col("value").alias("_v"), F.col("number").alias("_n"))
        part = F.broadcast(part) if values.count() <= BROADCAST_VALUES else part
        df = df.join(part, F.col(c).eqNullSafe(F.col("_v")), "left").drop("_v", c).withColumnRenamed("_n", c)
    return df.select(*[F.col(c).cast("long").alias(c) for c in cols], *[c for c in keep if c not in cols])


def melted(df: DataFrame, cols: list[str]) -> DataFrame:
    """(attr, value): one row for each row and column, as strings keep no order values stay typed by column."""
    return df.select(F.explode(F.array(*[F.struct(F.lit(i).alias("attr"), F.col(c).cast("long").alias("value")) for i, c in enumerate(cols)])).alias("s")).select("s.attr", "s.value")


def histograms(df: DataFrame, cols: list[str]) -> DataFrame:
    """(attr, value, cnt) of all columns in one pass, combined before the shuffle."""
    return melted(df, cols).groupBy("attr", "value").agg(F.count(F.lit(1)).alias("cnt"))


def cardinalities(df: DataFrame, cols: list[str], approximate: bool = False) -> list[int]:
    """Distinct values of each column; approximate ones serve planning only."""
    agg = F.approx_count_distinct if approximate else F.count_distinct
    row = df.agg(*[agg(F.col(c)).alias(f"c{i}") for i, c in enumerate(cols)]).first()
    return [int(x) for x in row]


def ranked(hist: DataFrame, order: str = "value", frequency_desc: bool = False, seed: int = 0) -> DataFrame:
    """Add rank (from 0, within each attribute) in value, frequency or random order.

    Attributes of at most BROADCAST_VALUES values are ranked by a window each.  Beyond that ranks come
    from a global range sort and row numbers, so no window covers a whole attribute: rank = number of
    the row - rows of the attributes before.
    """
    return _ranked(hist, order, frequency_desc, seed)[0]


def attribute_counts(hist: DataFrame) -> dict[int, int]:
    """Values of each attribute; one row a column."""
    return {r["attr"]: int(r["n"]) for r in hist.groupBy("attr").agg(F.count(F.lit(1)).alias("n")).collect()}


def _ranked(hist: DataFrame, order: str = "value", frequency_desc: bool = False, seed: int = 0) -> tuple[DataFrame, dict[int, int]]:
    """The ranks, and how many values each attribute has.  The histogram is read by several jobs, so it is written first."""
    hist = stored(hist)
    sizes = attribute_counts(hist)
    cnt = -F.col("cnt") if frequency_desc else F.col("cnt")
    keys = {"value": [F.col("value")], "frequency": [cnt, F.col("value")], "random": [F.xxhash64("value", F.lit(seed)), F.col("value")]}[order]
    if max(sizes.values(), default=0) <= BROADCAST_VALUES:
        return hist.withColumn("rank", (F.row_number().over(Window.partitionBy("attr").orderBy(*keys)) - 1).cast("long")), sizes
    from bitsort.operators.roworder import counted_rows  # it needs this module

    # files read again come in any order, so rows are numbered by the files' names
    names = {"_k%d" % i: x for i, x in enumerate(keys)}
    numbered, _ = counted_rows(hist, hist.withColumns(names), ["attr", *names], "_row")
    attrs = sorted(sizes)
    first = F.create_map(*[F.lit(x) for i, a in enumerate(attrs) for x in (a, sum(sizes[b] for b in attrs[:i]))])
    return numbered.withColumn("rank", (F.col("_row") - F.element_at(first, F.col("attr"))).cast("long")).drop("_row", "block"), sizes


def build_dictionary(df: DataFrame, cols: list[str], k: int = 1, allocation: str = "reflected", seed: int = 0, frequency_desc: bool = False, n_policy: str = "minimal", nulls: str = "value", permute: dict[int, list[int]] | None = None, hist: DataFrame | None = None, known_ranks: bool = False) -> DataFrame:
    """(attr, value, cnt, rank, n_bits, k, code) of every column; ``hist``: its histograms where they are known,
    with ranks in value order where ``known_ranks`` says so and the allocation needs no others.

    allocation: numeric, reflected, random, reflected_alternating (an attribute is reversed when the
    ones before it are odd in number) or freq_reflected (codes along (count, value)).  n_policy
    "padded": never more varying bitmaps than k = 1 needs.  nulls "skip": nulls get no code.
    permute: for an attribute, the new position of each of its bits.
    """
    if n_policy not in ("minimal", "padded") or nulls not in ("value", "skip"):
        raise ValueError(f"n_policy {n_policy}, nulls {nulls}")
    if known_ranks:
        ranks = hist.select("attr", "value", "cnt", "rank")
        sizes = attribute_counts(ranks)
    else:
        hist = histograms(df, cols) if hist is None else hist.select("attr", "value", "cnt")
        hist = hist.filter("value is not null") if nulls == "skip" else hist
        ranks, sizes = _ranked(hist, "frequency" if allocation == "freq_reflected" else "value", frequency_desc, seed)
        ranks = stored(ranks)
    out, ones = None, 0
    for i in range(len(cols)):
        n = sizes.get(i, 0)
        own_k = C.cap_k(n, k)
        n_bits, prefix = (C.padded_bitmaps(max(n, 1), own_k)) if n_policy == "padded" else (C.min_bitmaps(max(n, 1), own_k), 0)
        part = ranks.filter(F.col("attr") == i)
        code_rank = F.lit(n - 1) - F.col("rank") if allocation == "reflected_alternating" and ones % 2 else F.col("rank")
        scheme = {"numeric": "numeric", "random": "random"}.get(allocation, "reflected")
        part = C.coded(part.withColumn("_r", code_rank), "_r", max(n, 1), own_k - prefix, scheme, seed, n_bits - prefix, prefix, (permute or {}).get(i)).drop("_r")
        part = part.withColumn("n_bits", F.lit(n_bits)).withColumn("k", F.lit(own_k))
        ones += own_k
        out = part if out is None else out.unionByName(part)
    return out.select("attr", "value", "cnt", "rank", "n_bits", "k", "code")


def attach(rows: DataFrame, cols: list[str], dictionary: DataFrame, what: str = "code", dealt: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Replace every column by its ``what`` (code or rank); values without one (skipped nulls) get null.

    Large dictionaries are joined by shuffle; then ``dealt`` may lay the rows out, and small ones are broadcast.
    """
    sizes = attribute_counts(dictionary)
    small = [sizes.get(i, 0) <= BROADCAST_VALUES for i in range(len(cols))]
    for i, c in sorted(enumerate(cols), key=lambda x: small[x[0]]):
        if dealt and small[i]:
            rows, dealt = dealt(rows), None
        part = dictionary.filter(F.col("attr") == i).select(F.col("value").alias(f"_v{i}"), F.col(what).alias(f"_w{i}"))
        part = F.broadcast(part) if small[i] else part
        rows = rows.join(part, F.col(c).cast("long").eqNullSafe(F.col(f"_v{i}")), "left").drop(f"_v{i}", c).withColumnRenamed(f"_w{i}", c)
    return dealt(rows) if dealt else rows


@dataclass
class Ranked:
    """Rows whose columns hold the places of their values in value order, from 0 on, null first: what all indexes of a study share."""

    cols: list[str]
    rows: DataFrame
    #: (attr, value, cnt) of the places, and how many each column has.
    hist: DataFrame
    cards: list[int]


def ranked_rows(df: DataFrame, cols: list[str]) -> Ranked:
    """Every value is looked up once; codes of one bitmap then follow from the rows alone."""
    ranks, sizes = _ranked(histograms(df, cols))
    ranks, cards = stored(ranks), [sizes.get(i, 0) for i in range(len(cols))]
    kinds = ["int" if n < 1 << 31 else "long" for n in cards]
    rows = attach(df.select(*cols), cols, ranks, "rank").select(*[F.col(c).cast(t) for c, t in zip(cols, kinds, strict=True)])
    if rows.rdd.getNumPartitions() < partitions(df):  # one file of one row group would keep one core busy
        rows = rows.repartition(partitions(df))
    rows = stored(rows)
    return Ranked(cols, rows, ranks.select("attr", F.col("rank").alias("value"), "cnt"), cards)


def ranked_dictionary(ranked: Ranked, k: int = 1, allocation: str = "reflected") -> DataFrame:
    """The dictionary of ranked rows, for every order of their columns: only for allocations that do not look at other columns."""
    return stored(build_dictionary(ranked.rows, ranked.cols, k, allocation, hist=ranked.hist))


def bin_attribute(df: DataFrame, col: str, bins: int, how: str = "width") -> DataFrame:
    """Add ``<col>_bin`` from 0: equal width, or equal depth by approximate quantiles.  Queries recheck candidates."""
    if how == "width":
        lo, hi = df.agg(F.min(col), F.max(col)).first()
        step = (hi - lo) / bins or 1
        return df.withColumn(f"{col}_bin", F.least(F.floor((F.col(col) - lo) / step), F.lit(bins - 1)).cast("long"))
    cuts = df.agg(F.percentile_approx(col, [i / bins for i in range(1, bins)], 10000)).first()[0] if bins > 1 else []
    return df.withColumn(f"{col}_bin", sum((F.when(F.col(col) > c, 1).otherwise(0) for c in cuts), F.lit(0)).cast("long"))


def hierarchical_bins(ranks: DataFrame, fanout: int, levels: int) -> DataFrame:
    """Add bin_1 .. bin_levels, each ``fanout`` times coarser than the one before."""
    for level in range(1, levels + 1):
        ranks = ranks.withColumn(f"bin_{level}", F.floor(F.col("rank") / fanout**level).cast("long"))
    return ranks


def range_cover(lo: int, hi: int, fanout: int, levels: int) -> list[tuple[int, int]]:
    """(level, bin) nodes that exactly cover ranks lo .. hi, few of them."""
    out: list[tuple[int, int]] = []
    while lo <= hi:
        level = 0
        while level < levels and lo % fanout ** (level + 1) == 0 and lo + fanout ** (level + 1) - 1 <= hi:
            level += 1
        out.append((level, lo // fanout**level))
        lo += fanout**level
    return out


def components_of(rank, radices: list[int]):
    """Mixed-radix digits of a rank column, least significant first: one unary attribute each."""
    out, scale = [], 1
    for q in radices:
        out.append(F.pmod(F.floor(rank / scale), F.lit(q)).cast("long"))
        scale *= q
    return out


def encode_components(df: DataFrame, col: str, radices: list[int]) -> DataFrame:
    """Add <col>_d0, <col>_d1, ...: the digits of the column's value rank."""
    d = ranked(histograms(df, [col])).select(F.col("value").alias("_v"), F.col("rank").alias("_r"))
    out = df.join(d, F.col(col).cast("long").eqNullSafe(F.col("_v"))).drop("_v")
    for i, digit in enumerate(components_of(F.col("_r"), radices)):
        out = out.withColumn(f"{col}_d{i}", digit)
    return out.drop("_r")
