"""Index construction: sparse words, naive baseline, writing, appending, timing.

The index before compression is a table of non-zero words: (block, attr, bitmap, word_no, bits).
Rows are dealt by spans of row numbers, once; words, runs and sizes are made inside a span without a
further shuffle, and only what lies at the borders of spans travels.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace
from functools import cache, reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from bitsort.operators import roworder
from bitsort.operators.codes import cap_k, min_bitmaps
from bitsort.operators.dictionary import BROADCAST_VALUES, Ranked, attach, build_dictionary, histograms, numbered_values, ranked, typed_values
from bitsort.plans.recovery import partitions, passing, stored

KEY = ["block", "attr", "bitmap"]
#: Words of a span at least; a table of one span is not dealt.
SPAN_WORDS = 1 << 11
#: Spans for each shuffle partition.  A bitmap leaves a row for every span it is in, so there are no more than needed.
SPANS_A_PARTITION = 1


def word_mask(rows_in_word: Column, w: int) -> Column:
    """A word with its first ``rows_in_word`` bits set; all 64 are -1."""
    full = F.lit(-1) if w == 64 else F.lit((1 << w) - 1)
    return F.when(rows_in_word >= w, full).otherwise(F.call_function("shiftleft", F.lit(1).cast("long"), rows_in_word.cast("int")) - 1).cast("long")


def numbered_bitmap() -> Column:
    """The column and the bitmap as one number: words are grouped and sorted by few numbers."""
    return F.shiftleft(F.col("attr").cast("long"), 48).bitwiseOR(F.col("bitmap"))


def named_bitmap(number: str = "_bitmap") -> dict[str, Column]:
    """The column and the bitmap from that number."""
    return {"attr": F.shiftright(number, 48).cast("int"), "bitmap": F.col(number).bitwiseAND(F.lit((1 << 48) - 1))}


def sparse_words(rows: DataFrame, cols: list[str], w: int = 32) -> DataFrame:
    """(block, attr, bitmap, word_no, bits) from rows whose columns hold codes (arrays) or unary ranks.

    w: bits a word takes rows of - 16, 32, 64, or 31 for the hybrid codec.
    """
    arrays = {n for n, t in rows.dtypes if t.startswith("array")}
    parts = [F.struct(F.lit(i).alias("attr"), (F.col(c) if c in arrays else F.array(F.col(c).cast("long"))).alias("code")) for i, c in enumerate(cols)]
    span = [c for c in ("span",) if c in rows.columns]
    bits = rows.select(*span, "block", F.expr(f"row_id div {w}").alias("word_no"), F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod("row_id", F.lit(w)).cast("int")).alias("bit"), F.explode(F.array(*parts)).alias("s"))
    bits = bits.select(*span, "block", "word_no", "bit", "s.attr", F.explode("s.code").alias("bitmap"))
    cut = bits.select(*span, "block", numbered_bitmap().alias("_bitmap"), "word_no", "bit").groupBy(*span, "block", "_bitmap", "word_no").agg(F.bit_or("bit").alias("bits"))
    return cut.withColumns(named_bitmap()).select(*span, *KEY, "word_no", "bits")


@cache
def even_names(spans: int, p: int) -> list[int]:
    """Integers whose hashes deal them to the partitions 0 .. p-1 in turn: so few spans fill partitions evenly."""
    out: dict[int, list[int]] = {i: [] for i in range(p)}
    need, x = -(-spans // p), 0
    while min(map(len, out.values())) < need:
        out[_hashed(x) % p].append(x)
        x += 1
    return [out[i % p][i // p] for i in range(spans)]


def _hashed(x: int) -> int:
    """The hash that rows are dealt by, of an integer (32-bit Murmur3 with seed 42), as a signed number."""
    low = 0xFFFFFFFF
    turned = lambda v, by: ((v << by) | (v >> (32 - by))) & low
    h = 42 ^ (turned(x * 0xCC9E2D51 & low, 15) * 0x1B873593 & low)
    h = (turned(h, 13) * 5 + 0xE6546B64 & low) ^ 4
    h = (h ^ (h >> 16)) * 0x85EBCA6B & low
    h = (h ^ (h >> 13)) * 0xC2B2AE35 & low
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


def dealer(rows: DataFrame, n_rows: int, w: int) -> Callable[[DataFrame], DataFrame] | None:
    """What deals numbered rows by spans of whole words; none where one span holds them all."""
    p = partitions(rows)
    words = max(SPAN_WORDS, -(-n_rows // (w * SPANS_A_PARTITION * p)))
    names = F.array(*[F.lit(x) for x in even_names(SPANS_A_PARTITION * p, p)])

    def dealt(own: DataFrame) -> DataFrame:
        return own.withColumn("span", F.element_at(names, F.floor(F.col("row_id") / (words * w)).cast("int") + 1)).repartition(p, "span")

    return dealt if n_rows > words * w else None


def spanned_words(rows: DataFrame, cols: list[str], dictionary: DataFrame, n_rows: int, w: int = 32) -> DataFrame:
    """The words of numbered rows; ``span`` beside them where there are several: whole words, dealt by it."""
    return sparse_words(attach(rows, cols, dictionary, dealt=dealer(rows, n_rows, w)), cols, w)


def block_sizes(rows: DataFrame, w: int = 32) -> DataFrame:
    """(block, first_word, words, last_rows): where each block's words begin, how many, rows in the last one."""
    b = rows.groupBy("block").agg(F.min("row_id").alias("lo"), F.max("row_id").alias("hi"))
    first, last = F.floor(F.col("lo") / w), F.floor(F.col("hi") / w)
    return b.select("block", first.alias("first_word"), (last - first + 1).alias("words"), (F.col("hi") - last * w + 1).alias("last_rows"))


def even_blocks(spark: SparkSession, n_rows: int, block_rows: int | None, w: int = 32, block: int = 0, first_row: int = 0) -> DataFrame:
    """The same for rows numbered without gaps from ``first_row`` on, from their number alone: no job reads them."""
    size = block_rows or max(n_rows, 1)
    lo = F.col("id") * size + first_row
    hi = F.least(lo + size, F.lit(first_row + n_rows)) - 1
    first, last = F.floor(lo / w), F.floor(hi / w)
    return spark.range(0, -(-n_rows // size), 1, 1).select((F.col("id") + block).alias("block"), first.alias("first_word"), (last - first + 1).alias("words"), (hi - last * w + 1).alias("last_rows"))


def naive_words(rows: DataFrame, cols: list[str], dictionary: DataFrame, w: int = 32) -> DataFrame:
    """Baseline: every bitmap gets every word, zero or not.  Small inputs only; joins all words with all bitmaps."""
    words = rows.select("block", F.floor(F.col("row_id") / w).alias("word_no")).distinct()
    bitmaps = dictionary.select("attr", F.explode("code").alias("bitmap")).distinct()
    every = words.crossJoin(bitmaps)
    return every.join(sparse_words(rows, cols, w), ["block", "attr", "bitmap", "word_no"], "left").withColumn("bits", F.coalesce("bits", F.lit(0).cast("long")))


@dataclass
class Index:
    """A built index: columns, words, dictionary, block sizes and the rows they describe."""

    cols: list[str]
    words: DataFrame
    dictionary: DataFrame
    blocks: DataFrame
    rows: DataFrame
    w: int
    k: int
    allocation: str
    #: Columns of other types than integers: their values and the numbers that stand for them.
    typed: dict[str, DataFrame] = field(default_factory=dict)
    timings: dict[str, float] = field(default_factory=dict)
    n_rows: int = 0


def build_index(df: DataFrame, cols: list[str], k: int = 1, allocation: str = "reflected", row_order: str = "lex", w: int = 32, block_rows: int | None = None, timed: bool = False, **options) -> Index:
    """Sort, number, encode and cut into words.  ``timed`` materialises each phase and notes its seconds.

    Columns may have any ordered type.  Options of the dictionary: seed, frequency_desc, n_policy,
    nulls, permute; all others go to the row order.
    """
    if block_rows and block_rows % w:
        raise ValueError("block_rows must be a multiple of the word length")
    clock = time.perf_counter
    t0 = clock()
    typed = typed_values(df, cols)
    df = numbered_values(df, cols, typed, tuple(options.get("natural") or ()))
    of_dictionary = {n: options.pop(n) for n in ("seed", "frequency_desc", "n_policy", "permute") if n in options}
    nulls = options.pop("nulls", "value")
    if nulls == "skip" and typed:
        for c, values in typed.items():  # the number of null stands for no value
            none = values.filter("value is null").first()
            df = df.withColumn(c, F.when(F.col(c) != F.lit(none["number"]), F.col(c))) if none else df
    dictionary = stored(build_dictionary(df, cols, k, allocation, nulls=nulls, **of_dictionary))
    t1 = clock()
    if row_order == "reflected":
        n_bits = {c: int(r["n"]) for c, r in zip(cols, sorted(dictionary.groupBy("attr").agg(F.max("n_bits").alias("n")).collect()), strict=True)}
        coded, placed = df, positions(dictionary, options.pop("bitmap_order", None))
        for i, c in enumerate(cols):
            part = placed.filter(F.col("attr") == i).select(F.col("value").alias("_v"), F.col("code").alias(f"{c}_code"))
            coded = coded.join(part, F.col(c).eqNullSafe(F.col("_v")), "left").drop("_v").withColumn(f"{c}_code", F.coalesce(f"{c}_code", F.array().cast("array<long>")))
        if "position" in placed.columns:
            n_bits = dict.fromkeys(cols, 0)  # positions count through all columns already
        rows, n_rows = roworder.ordered_rows(coded, "reflected", cols, block_rows, n_bits=n_bits, sort_positions="position" in placed.columns, **options)
    else:
        rows, n_rows = roworder.ordered_rows(df, row_order, cols, block_rows, **options)
    rows = rows.select(*cols, "row_id", "block")
    t2 = clock()
    words = spanned_words(rows, cols, dictionary, n_rows, w)
    if timed:
        words = stored(words)
    t3 = clock()
    return Index(cols, words, dictionary, even_blocks(df.sparkSession, n_rows, block_rows, w), rows, w, k, allocation, typed, {"dictionary_s": t1 - t0, "sort_s": t2 - t1, "index_s": t3 - t2, "total_s": t3 - t0}, n_rows)


def build_orders(ranked: Ranked, orders: list[list[str] | DataFrame], dictionary: DataFrame, k: int = 1, w: int = 32) -> Index:
    """One index of ranked rows in several orders, each of them a block: sorted once, with the number of the order before the keys.

    An order is a list of all columns, for rows sorted by value, or an order of all bitmaps, (attr, bitmap,
    position), for rows sorted by reflected codes.  Rows travel as few packed longs; ``dictionary`` is that
    of ``ranked``, numeric or reflected, and where a value has one bitmap nothing is joined to them.
    """
    cols, cards, spark = ranked.cols, ranked.cards, ranked.rows.sparkSession
    bits = {c: max(1, (n - 1).bit_length()) for c, n in zip(cols, cards, strict=True)}
    longs = {f"_p{i}": x for i, x in enumerate(roworder.packed([F.col(c) for c in cols], list(bits.values())))}
    names, rows, keyed = list(longs), ranked.rows.withColumns(longs), []
    by_value = {m: roworder.packed([F.col(c) for c in o], [bits[c] for c in o]) for m, o in enumerate(orders) if isinstance(o, list)}
    by_code = [m for m in range(len(orders)) if m not in by_value]
    ones = sum(cap_k(n, k) for n in cards)
    position = sum(min_bitmaps(max(n, 1), cap_k(n, k)) for n in cards).bit_length()
    longest = max([len(x) for x in by_value.values()] + ([1 + roworder.layout([position] * ones)[-1][0]] if by_code else []))
    keys = [f"_o{i}" for i in range(longest)]
    padded = lambda own: [x.alias(n) for n, x in zip(keys, [*own, *[F.lit(0).cast("long")] * (longest - len(own))], strict=True)]
    if by_value:
        every = F.array(*[F.struct(F.lit(m).alias("_m"), *padded(x)) for m, x in by_value.items()])
        keyed.append(rows.select(*names, F.explode(every).alias("s")).select("s.*", *names))
    if by_code:
        placed = stored(reduce(DataFrame.unionByName, [positions(dictionary, orders[m]).withColumn("_n", F.lit(m)) for m in by_code]))
        coded = rows.select(*cols, *names, F.explode(F.array(*[F.lit(m) for m in by_code])).alias("_m"))
        for i, c in enumerate(cols):
            part = placed.filter(F.col("attr") == i).select("_n", F.col("value").alias("_v"), F.col("code").alias(f"{c}_code"))
            part = F.broadcast(part) if cards[i] * len(by_code) <= BROADCAST_VALUES else part
            coded = coded.join(part, (F.col("_m") == F.col("_n")) & (F.col(c) == F.col("_v"))).drop("_n", "_v")
        coded = coded.select("_m", F.sort_array(F.concat(*[f"{c}_code" for c in cols])).alias("_key"), *names)
        keyed.append(coded.select("_m", *padded(roworder.packed_reflected_keys(F.col("_key"), ones, position)), *names))
    frame = reduce(DataFrame.unionByName, keyed)
    numbered, total = roworder.counted_rows(frame.select(*names), frame, ["_m", *keys])
    n = max(1, total // len(orders))
    words = -(-n // w)
    own = numbered.select(*names, (F.floor(F.col("row_id") / n) * (words * w) + F.pmod("row_id", F.lit(n))).alias("row_id"))

    def plain(df: DataFrame) -> DataFrame:
        values = dict(zip(cols, roworder.unpacked([F.col(p) for p in names], list(bits.values())), strict=True))
        return df.withColumns({**values, "block": F.floor(F.col("row_id") / (words * w))}).drop(*names)

    dealt = dealer(own, words * w * len(orders), w)
    if k == 1:
        unary = {c: F.lit(x) - F.col(c) for c, x in zip(cols, cards, strict=True)}
        cut = sparse_words(plain(dealt(own) if dealt else own).withColumns(unary), cols, w)
    elif max(cards) <= BROADCAST_VALUES:
        cut = sparse_words(attach(plain(dealt(own) if dealt else own), cols, dictionary), cols, w)
    else:
        cut = sparse_words(attach(plain(own), cols, dictionary, dealt=dealt), cols, w)
    id_ = F.col("id")
    blocks = spark.range(0, len(orders) if total else 0, 1, 1).select(id_.alias("block"), (id_ * words).alias("first_word"), F.lit(words).cast("long").alias("words"), F.lit(n - (words - 1) * w).cast("long").alias("last_rows"))
    return Index(cols, cut, dictionary, blocks, plain(own), w, k, "reflected", n_rows=total)


def recoded(index: Index, k: int = 1, w: int = 32, allocation: str = "reflected") -> Index:
    """The same rows in the same order with other codes or words; nothing is read or sorted again.  For row orders that no code decides."""
    by_value = "freq_reflected" not in (allocation, index.allocation)  # then codes follow the same ranks
    dictionary = stored(build_dictionary(index.rows, index.cols, k, allocation, hist=index.dictionary, known_ranks=by_value))
    return replace(index, words=spanned_words(index.rows, index.cols, dictionary, index.n_rows, w), dictionary=dictionary, blocks=even_blocks(index.rows.sparkSession, index.n_rows, None, w), w=w, k=k, allocation=allocation)


def positions(dictionary: DataFrame, order: DataFrame | None) -> DataFrame:
    """(attr, value, code): codes as places of an order of all bitmaps, (attr, bitmap, position), where one is given."""
    if order is None:
        return dictionary.select("attr", "value", "code")
    own = dictionary.select("attr", "value", F.explode("code").alias("bitmap")).join(order, ["attr", "bitmap"])
    return own.groupBy("attr", "value").agg(F.array_sort(F.collect_list("position")).alias("code")).withColumn("position", F.lit(True))


def write_index(index: Index, path: str, rows: bool = True) -> None:
    """Words, dictionary and block sizes as Parquet: one folder a column, sorted by bitmap and block,
    so that a query reads one folder and the row groups whose statistics hold its bitmaps.

    The range partitioner samples its input: words are stored first, so that they are cut once."""
    spark = index.words.sparkSession
    with passing(spark):
        laid = stored(index.words.drop("span")).repartitionByRange(partitions(index.words), "attr", "bitmap", "block").sortWithinPartitions("attr", "bitmap", "block", "word_no")
        laid.write.mode("overwrite").partitionBy("attr").parquet(f"{path}/words")
    index.dictionary.write.mode("overwrite").partitionBy("attr").parquet(f"{path}/dictionary")
    index.blocks.write.mode("overwrite").parquet(f"{path}/blocks")
    if rows:
        index.rows.write.mode("overwrite").parquet(f"{path}/rows")
    for c, values in index.typed.items():
        values.write.mode("overwrite").parquet(f"{path}/values_{c}")


def read_index(spark, path: str, cols: list[str], w: int = 32, k: int = 1, allocation: str = "reflected", typed: tuple[str, ...] = (), rows: DataFrame | None = None) -> Index:
    """``typed``: the columns that hold no integers; ``rows``: the rows where they were not written."""
    values = {c: spark.read.parquet(f"{path}/values_{c}") for c in typed}
    return Index(cols, spark.read.parquet(f"{path}/words"), spark.read.parquet(f"{path}/dictionary"), spark.read.parquet(f"{path}/blocks"), spark.read.parquet(f"{path}/rows") if rows is None else rows, w, k, allocation, values)


def append_blocks(index: Index, more: DataFrame, row_order: str = "lex") -> Index:
    """Sort new rows on their own and add them as a further block.

    Unseen values extend the dictionary: each gets a bitmap of its own beside the k - 1 first ones,
    so no code changes and none is used twice.
    """
    typed = dict(index.typed)
    for c, values in index.typed.items():
        new = more.select(F.col(c).alias("value")).distinct().join(values.select(F.col("value").alias("_v")), F.col("value").eqNullSafe(F.col("_v")), "left_anti")
        last = values.agg(F.max("number")).first()[0]
        extra = ranked(new.select(F.lit(0).alias("attr"), "value", F.lit(1).alias("cnt"))).select("value", (F.col("rank") + F.lit(last + 1 if last is not None else 0)).alias("number"))
        typed[c] = stored(values.unionByName(extra))
    more = numbered_values(more, index.cols, typed)
    known = index.dictionary.groupBy("attr").agg(F.max("rank").alias("_last"), F.max("n_bits").alias("_bits"), F.max("k").alias("_k"))
    unseen = histograms(more, index.cols).join(index.dictionary.select("attr", F.col("value").alias("_v")).withColumnRenamed("attr", "_a"), (F.col("attr") == F.col("_a")) & F.col("value").eqNullSafe(F.col("_v")), "left_anti")
    extra = ranked(unseen).join(known, "attr").withColumn("_new", F.col("_bits") + F.col("rank") + 1)
    ones = F.when(F.col("_k") > 1, F.sequence(F.lit(1).cast("long"), (F.col("_k") - 1).cast("long"))).otherwise(F.array().cast("array<long>"))
    extra = extra.select("attr", "value", "cnt", (F.col("_last") + F.col("rank") + 1).alias("rank"), F.col("_new").cast("int").alias("n_bits"), F.col("_k").alias("k"), F.concat(ones, F.array(F.col("_new").cast("long"))).alias("code"))
    dictionary = stored(index.dictionary.select("attr", "value", "cnt", "rank", "n_bits", "k", "code").unionByName(extra))
    last = index.blocks.agg(F.max("block").alias("b"), F.max((F.col("first_word") + F.col("words")) * index.w).alias("r")).first()
    rows, n_rows = roworder.ordered_rows(more, row_order, index.cols)
    rows = (rows.withColumn("row_id", F.col("row_id") + F.lit(last["r"])).withColumn("block", F.lit(last["b"] + 1).cast("long")))
    words = index.words.drop("span").unionByName(sparse_words(attach(rows, index.cols, dictionary), index.cols, index.w))
    return Index(index.cols, words, dictionary, index.blocks.unionByName(even_blocks(more.sparkSession, n_rows, None, index.w, last["b"] + 1, last["r"])), index.rows.select(*index.cols, "row_id", "block").unionByName(rows.select(*index.cols, "row_id", "block")), index.w, index.k, index.allocation, typed)
