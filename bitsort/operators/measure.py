"""Exact sizes and costs of an index, from its non-zero words alone.

Between two non-zero words lie zero words; runs of full words and of dirty words follow from
neighbours.  A stream is cut into segments of one clean run and one dirty run; a segment costs its
dirty words and as many markers as its counters need.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from bitsort.operators.build import KEY, Index, named_bitmap, numbered_bitmap, word_mask


@dataclass(frozen=True)
class Codec:
    """Word length and counter widths.  ``markers`` codecs have marker words; the hybrid flags every word."""

    w: int
    clean_bits: int
    dirty_bits: int
    markers: bool = True
    extend: bool = False  # a full clean counter means: the next word holds the rest

    @property
    def clean_max(self) -> int:
        return (1 << self.clean_bits) - 1

    @property
    def dirty_max(self) -> int:
        return (1 << self.dirty_bits) - 1


#: Half the bits of a marker count clean words, all but one of the others dirty ones.
MARKER = {16: Codec(16, 8, 7), 32: Codec(32, 16, 15), 64: Codec(64, 32, 31)}
HYBRID31 = Codec(31, 30, 0, markers=False)


def marker_codec(w: int, clean_bits: int | None = None, extend: bool = False) -> Codec:
    clean_bits = clean_bits or w // 2
    return Codec(w, clean_bits, w - 1 - clean_bits, True, extend)


#: Words that one window takes; runs over the borders of such chunks are put together afterwards.
CHUNK_WORDS = 1 << 16
#: Block sizes are one row a block; so many are broadcast.
BROADCAST_BLOCKS = 100_000


def _ceil(x: Column, y: int) -> Column:
    return F.ceil(x / F.lit(y)).cast("long")


def clean_words(length: Column, codec: Codec) -> Column:
    """Words that a clean run of this length takes."""
    if codec.extend:
        return F.when(length >= codec.clean_max, 2).otherwise(1)
    return _ceil(length, codec.clean_max)


COSTS = ("dirty", "clean_runs", "markers", "overruns")


def run_costs(full: Column, length: Column, first_at: Column, zeros: Column, tail: Column, codec: Codec) -> dict[str, Column]:
    """What a run of equal non-zero words costs, with the zero words before it and those that end the bitmap after it."""
    clean = zeros > 0
    return {
        "dirty": F.when(~full, length).otherwise(0),
        "clean_runs": clean.cast("long") + full.cast("long") + (tail > 0).cast("long"),
        "markers": F.when(clean, clean_words(zeros, codec)).otherwise(0)
        + F.when(full, clean_words(length, codec)).otherwise(0)
        + F.when(tail > 0, clean_words(tail, codec)).otherwise(0)
        + (
            # a dirty run shares the marker of the clean run before it; one that starts the stream has its own
            F.when(~full, F.greatest(_ceil(length, codec.dirty_max) - 1, F.lit(0)) + (first_at == 0).cast("long")).otherwise(0)
            if codec.markers
            else F.lit(0)
        ),
        "overruns": F.floor(zeros / codec.clean_max) + F.when(full, F.floor(length / codec.clean_max)).otherwise(F.floor(length / codec.dirty_max) if codec.markers else F.lit(0)) + F.floor(tail / codec.clean_max),
    }


def chunk_runs(words: DataFrame, blocks: DataFrame, codec: Codec) -> tuple[DataFrame, bool]:
    """One row for each chunk of a bitmap, and whether a bitmap can have several: its inner runs' costs and its first and last run.

    A chunk is what one window takes: CHUNK_WORDS of a bitmap at most, and never more than a span
    where words are dealt by spans; then all of this happens where the words are made.
    """
    w, span = codec.w, [c for c in ("span",) if c in words.columns]
    shape = blocks.agg(F.count(F.lit(1)).alias("n"), F.max("words").alias("words")).first()
    sizes = F.broadcast(blocks) if shape["n"] <= BROADCAST_BLOCKS else blocks
    sized = words.join(sizes, "block")
    at = F.col("word_no") - F.col("first_word")
    rows_in = F.when(at == F.col("words") - 1, F.col("last_rows")).otherwise(F.lit(w))
    sized = sized.filter(F.col("bits") != 0).select(numbered_bitmap().alias("_bitmap"), "block", *span, at.alias("at"), (F.col("bits") == word_mask(rows_in, w)).alias("full")).withColumn("chunk", F.floor(F.col("at") / CHUNK_WORDS))
    # sorted by the bitmap first, as it tells most words apart; a filter leaves them sorted
    part = ["_bitmap", "block", *span, "chunk"]
    order = Window.partitionBy(*part).orderBy("at")
    whole = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    marked = sized.withColumns({"before": F.lag("at").over(order), "kind": F.lag("full").over(order), "until": F.max("at").over(whole)})
    marked = marked.withColumn("gap", F.col("at") - F.col("before") - 1)
    # words of a run follow each other, so that the word before the next run's first one is its last
    starts = marked.filter(F.col("before").isNull() | (F.col("gap") > 0) | (F.col("full") != F.col("kind"))).withColumn("_next", F.lead("before").over(order))
    found = starts.select(*part, "full", (F.coalesce("_next", "until") - F.col("at") + 1).alias("len"), F.col("at").alias("first_at"), F.coalesce("gap", F.lit(0)).alias("zeros"), F.col("before").isNull().alias("begins"), F.col("_next").isNull().alias("ends"))
    costs = run_costs(F.col("full"), F.col("len"), F.col("first_at"), F.col("zeros"), F.lit(0), codec)
    inner = ~F.col("begins") & ~F.col("ends")
    own = found.withColumns(costs).groupBy(*part).agg(
        *[F.coalesce(F.sum(F.when(inner, F.col(c))), F.lit(0)).cast("long").alias(c) for c in COSTS],
        *[F.max(F.when(F.col(edge), F.col(c))).alias(f"{edge}_{c}") for edge in ("begins", "ends") for c in ("full", "len", "first_at", "zeros")],
        F.max(F.col("begins") & F.col("ends")).alias("single"),
    )
    own = own.withColumns(named_bitmap()).join(sizes.select("block", "words"), "block")
    return own, bool(span) or (shape["words"] or 0) > CHUNK_WORDS


def bitmap_sizes(words: DataFrame, blocks: DataFrame, codec: Codec) -> DataFrame:
    """Per (block, attr, bitmap): dirty, clean_runs, storage_cost, markers, words (compressed), overruns, ones-runs.

    Runs are found chunk by chunk; only the first and the last run of each chunk meet those of its
    neighbours.  Where every bitmap is one chunk there are no neighbours.
    """
    own, several = chunk_runs(words, blocks, codec)
    edge = lambda e, inner: F.struct(*[F.col(f"{e}_{c}").alias(c) for c in ("full", "len", "first_at", "zeros")], F.lit(e == "begins").alias("begins"), *[(F.col(c) if inner else F.lit(0).cast("long")).alias(c) for c in COSTS])
    both = F.when(F.col("single"), F.array(edge("begins", True))).otherwise(F.array(edge("begins", True), edge("ends", False)))
    border = own.select(*KEY, "words", F.explode(both).alias("s")).select(*KEY, "words", "s.*")
    order = Window.partitionBy(*KEY).orderBy("first_at")
    gap = F.col("first_at") - F.coalesce(F.lag(F.col("first_at") + F.col("len")).over(order), F.lit(0))
    border = border.withColumn("zeros", F.when(F.col("begins"), gap).otherwise(F.col("zeros"))).withColumn("_kind", F.lag("full").over(order)).withColumn("_last", F.lead("first_at").over(order).isNull())
    if several:
        joined = F.col("begins") & (F.col("zeros") == 0) & (F.col("full") == F.col("_kind"))
        border = border.withColumn("_run", F.sum(F.when(F.coalesce(joined, F.lit(False)), 0).otherwise(1)).over(order))
        border = border.groupBy(*KEY, "_run", "full").agg(F.sum("len").alias("len"), F.min("first_at").alias("first_at"), F.max("zeros").alias("zeros"), F.max("words").alias("words"), F.max("_last").alias("_last"), *[F.sum(c).alias(c) for c in COSTS])
    tail = F.when(F.col("_last"), F.col("words") - F.col("first_at") - F.col("len")).otherwise(0)
    costs = run_costs(F.col("full"), F.col("len"), F.col("first_at"), F.col("zeros"), tail, codec)
    out = border.groupBy(*KEY).agg(*[F.sum(F.col(c) + costs[c]).cast("long").alias(c) for c in COSTS])
    return out.withColumn("storage_cost", F.col("dirty") + F.col("clean_runs")).withColumn("compressed", F.col("dirty") + F.col("markers"))


def attribute_sizes(index: Index, codec: Codec | None = None) -> DataFrame:
    """Per attribute: bitmaps, dirty, clean_runs, storage_cost, markers, compressed, overruns."""
    sizes = bitmap_sizes(index.words, index.blocks, codec or MARKER[index.w])
    return sizes.groupBy("attr").agg(F.countDistinct("bitmap").alias("bitmaps"), *[F.sum(c).cast("long").alias(c) for c in ("dirty", "clean_runs", "storage_cost", "markers", "compressed", "overruns")])


def total_sizes(index: Index, codec: Codec | None = None) -> DataFrame:
    """One row: the sums over all attributes, the share of clean runs and of full counters."""
    t = attribute_sizes(index, codec).agg(*[F.sum(c).cast("long").alias(c) for c in ("bitmaps", "dirty", "clean_runs", "storage_cost", "markers", "compressed", "overruns")])
    return t.withColumn("clean_share", F.round(F.col("markers") / F.col("compressed"), 6)).withColumn("overrun_share", F.round(F.col("overruns") / F.col("markers"), 6))


def block_totals(index: Index, codec: Codec | None = None) -> DataFrame:
    """(block, compressed): the size of each block by itself."""
    return bitmap_sizes(index.words, index.blocks, codec or MARKER[index.w]).groupBy("block").agg(F.sum("compressed").cast("long").alias("compressed"))


def size_ratio(sizes: DataFrame, base: str, key: list[str], method: str = "method", size: str = "compressed") -> DataFrame:
    """Add ``ratio``: every size over that of the method ``base`` with the same key."""
    own = sizes.filter(F.col(method) == base).select(*key, F.col(size).alias("_base"))
    return sizes.join(own, key, "left").withColumn("ratio", F.round(F.col(size) / F.col("_base"), 6)).drop("_base")


def uncompressed_words(index: Index) -> DataFrame:
    """(attr, words): words of the index without compression, every bitmap whole."""
    every = index.blocks.agg(F.sum("words").alias("_n"))
    bitmaps = index.dictionary.groupBy("attr").agg(F.max("n_bits").cast("long").alias("bitmaps"))
    return bitmaps.join(F.broadcast(every)).select("attr", "bitmaps", (F.col("bitmaps") * F.col("_n")).alias("words"))


def code_hamming_cost(index: Index) -> DataFrame:
    """(attr, changes): bits that change between neighbouring rows, from the words alone.

    A bitmap changes within its words and where one word's last bit differs from the next one's
    first; words that are not there are zero.
    """
    first, top = F.col("bits").bitwiseAND(F.lit(1)), F.shiftrightunsigned("bits", index.w - 1).bitwiseAND(F.lit(1).cast("long"))
    shifted = F.shiftrightunsigned("bits", 1)
    low = F.lit((1 << (index.w - 1)) - 1).cast("long")
    sized = index.words.filter("bits <> 0").join(index.blocks, "block")
    at = F.col("word_no") - F.col("first_word")
    inside_rows = F.when(at == F.col("words") - 1, F.col("last_rows")).otherwise(F.lit(index.w))
    mask = F.when(inside_rows >= index.w, low).otherwise(F.call_function("shiftleft", F.lit(1).cast("long"), (inside_rows - 1).cast("int")) - 1).cast("long")
    inner = F.bit_count(F.col("bits").bitwiseXOR(shifted).bitwiseAND(mask))
    own = sized.select(*KEY, at.alias("at"), first.alias("head"), F.when(at == F.col("words") - 1, F.lit(0)).otherwise(top).cast("long").alias("tail"), inner.alias("inner"), (at == F.col("words") - 1).alias("ends"))
    ahead = own.select(*KEY, (F.col("at") + 1).alias("at"), F.col("tail").alias("_tail"))
    met = own.join(ahead, [*KEY, "at"], "full_outer")
    border = F.when(F.col("at") == 0, 0).otherwise(F.coalesce("head", F.lit(0)).bitwiseXOR(F.coalesce("_tail", F.lit(0))))
    return met.groupBy("attr").agg((F.sum(F.coalesce("inner", F.lit(0))) + F.sum(border)).cast("long").alias("changes"))


def density(words: DataFrame, n_rows: int) -> DataFrame:
    """(attr, bitmap, ones, density) and so the order of bitmaps by weight."""
    return words.groupBy("attr", "bitmap").agg(F.sum(F.bit_count("bits")).cast("long").alias("ones")).withColumn("density", F.col("ones") / F.lit(n_rows))


def hamming_cost(rows: DataFrame, cols: list[str]) -> DataFrame:
    """(attr, changes, runs): changes of value between neighbouring rows, without a global window.

    Rows are cut into chunks of row numbers; a chunk's first row meets the last of the one before
    through a join of chunk borders.
    """
    chunk = 1 << 16
    keyed = rows.withColumn("_c", F.floor(F.col("row_id") / chunk))
    order = Window.partitionBy("_c").orderBy("row_id")
    borders = rows.filter(F.pmod("row_id", F.lit(chunk)) == chunk - 1).select((F.floor(F.col("row_id") / chunk) + 1).alias("_c"), *[F.col(c).alias(f"_p{i}") for i, c in enumerate(cols)])
    joined = keyed.join(borders, "_c", "left")
    changes = []
    for i, c in enumerate(cols):
        before = F.coalesce(F.lag(c).over(order), F.col(f"_p{i}"))
        changes.append((~before.eqNullSafe(F.col(c)) & (F.col("row_id") > 0)).cast("long").alias(f"d{i}"))
    sums = joined.select(*changes).agg(*[F.sum(f"d{i}").alias(f"d{i}") for i in range(len(cols))])
    parts = F.array(*[F.struct(F.lit(i).alias("attr"), F.col(f"d{i}").alias("changes"), (F.col(f"d{i}") + 1).alias("runs")) for i in range(len(cols))])
    return sums.select(F.explode(parts).alias("s")).select("s.*")


def data_examined(index: Index, codec: Codec | None = None) -> DataFrame:
    """(attr, words): compressed words of the k bitmaps of an equality query, averaged over the values."""
    sizes = bitmap_sizes(index.words, index.blocks, codec or MARKER[index.w]).groupBy("attr", "bitmap").agg(F.sum("compressed").alias("size"))
    per_value = index.dictionary.select("attr", "value", F.explode("code").alias("bitmap")).join(sizes, ["attr", "bitmap"]).groupBy("attr", "value").agg(F.sum("size").alias("size"))
    return per_value.groupBy("attr").agg(F.round(F.avg("size"), 6).alias("words"))


def sorted_bounds(sizes: DataFrame, cardinalities: list[int], k: int = 1) -> DataFrame:
    """Check of the bounds for lexicographically sorted rows: (attr, dirty, bound, holds).

    The i-th column has at most twice the product of the first i cardinalities of dirty words times k.
    """
    bounds, product = [], 1
    for n in cardinalities:
        product *= n
        bounds.append(2 * k * product)
    table = F.array(*[F.lit(min(b, 2**62)).cast("long") for b in bounds])
    return sizes.select("attr", "dirty", F.element_at(table, F.col("attr") + 1).alias("bound")).withColumn("holds", F.col("dirty") <= F.col("bound"))


def run_histogram(codes: DataFrame) -> DataFrame:
    """(name, len, count): lengths of runs of equal bits down each bit position of a code list."""
    order = Window.partitionBy("name", "bit").orderBy("rank")
    new = F.when(F.col("value") == F.lag("value").over(order), 0).otherwise(1)
    return codes.withColumn("run", F.sum(new).over(order)).groupBy("name", "bit", "run").agg(F.count(F.lit(1)).alias("len")).groupBy("name", "len").agg(F.count(F.lit(1)).alias("count"))


def long_run_probability(codes: DataFrame) -> DataFrame:
    """(name, len, prob): probability that a bit lies in a run of at least len."""
    h = run_histogram(codes)
    down = Window.partitionBy("name").orderBy(F.desc("len")).rowsBetween(Window.unboundedPreceding, 0)
    every = Window.partitionBy("name")
    return h.withColumn("prob", F.round(F.sum(F.col("len") * F.col("count")).over(down) / F.sum(F.col("len") * F.col("count")).over(every), 9)).select("name", "len", "prob")


def dirty_probability(codes: list[tuple[int, ...]], n_bits: int, j: int, w: int = 32) -> float:
    """Probability that a word is dirty whose w rows hold j successive codes, each about w/j times."""
    bits = sum(len(set().union(*codes[i : i + j])) - len(set(codes[i]).intersection(*codes[i + 1 : i + j])) for i in range(len(codes) - j + 1))
    return bits / n_bits / max(1, len(codes) - j + 1)


def code_distances(codes: list[tuple[int, ...]], j: int = 2) -> dict[str, float]:
    """Neighbour, cyclic and collective (j successive codes) Hamming distances of a code list."""
    gaps = [len(set(a) ^ set(b)) for a, b in zip(codes, codes[1:], strict=False)]
    many = [len(set().union(*codes[i : i + j])) - len(set(codes[i]).intersection(*codes[i + 1 : i + j])) for i in range(len(codes) - j + 1)]
    return {"neighbour_max": max(gaps, default=0), "neighbour_sum": sum(gaps), "cyclic": len(set(codes[0]) ^ set(codes[-1])), "collective_mean": sum(many) / max(1, len(many))}
