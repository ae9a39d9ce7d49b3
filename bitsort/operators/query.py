"""Queries on an index: equality, membership, ranges, predicate trees; row ids, counts, rows.

A predicate becomes a table of answer words (block, word_no, bits).  OR within a column is one
aggregation over the words of its bitmaps, AND across columns keeps the words that all have; NOT
needs the words that no bitmap has, made from the block sizes.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bitsort.operators.build import Index, word_mask
from bitsort.operators.dictionary import BROADCAST_VALUES

WORD = ["block", "word_no"]


@dataclass(frozen=True)
class Pred:
    """col: ``op`` is eq, in or between with values; and, or, xor, not, andnot with children."""

    op: str
    col: str | None = None
    values: tuple = ()
    children: tuple[Pred, ...] = ()

    def __and__(self, other: Pred) -> Pred:
        return Pred("and", children=(self, other))

    def __or__(self, other: Pred) -> Pred:
        return Pred("or", children=(self, other))

    def __xor__(self, other: Pred) -> Pred:
        return Pred("xor", children=(self, other))

    def __invert__(self) -> Pred:
        return Pred("not", children=(self,))


def eq(col: str, value: int) -> Pred:
    return Pred("in", col, (value,))


def isin(col: str, values) -> Pred:
    return Pred("in", col, tuple(values))


def between(col: str, lo: int, hi: int) -> Pred:
    return Pred("between", col, (lo, hi))


#: Up to so many bitmaps of a predicate are named in the scan's filter, so that row groups are skipped.
NAMED_BITMAPS = 2_000


def selected(index: Index, p: Pred) -> DataFrame:
    """The dictionary rows of a predicate's values, compared in the column's own type."""
    d = index.dictionary.filter(F.col("attr") == index.cols.index(p.col))
    test = lambda c: F.col(c).between(*p.values) if p.op == "between" else F.col(c).isin(list(p.values))
    if p.col not in index.typed:
        return d.filter(test("value"))
    return d.join(index.typed[p.col].filter(test("value")).select(F.col("number").alias("value")), "value", "left_semi")


def column_words(index: Index, p: Pred, codes: DataFrame) -> DataFrame:
    """The words of a column, of few bitmaps only where the predicate has few."""
    words = index.words.filter(F.col("attr") == index.cols.index(p.col)).select("block", "bitmap", "word_no", "bits")
    named = named_bitmaps(codes)
    return words.filter(F.col("bitmap").isin(named)) if named is not None else words


def named_bitmaps(codes: DataFrame) -> list[int] | None:
    """The bitmaps of ``codes`` where they are few."""
    named = [r[0] for r in codes.select("bitmap").distinct().limit(NAMED_BITMAPS + 1).collect()]
    return named if len(named) <= NAMED_BITMAPS else None


def coded_bits(words: DataFrame, k: int, w: int) -> DataFrame:
    """(attr, block, word_no, code, bits): what the words tell of whole codes of k bitmaps, from the words of one or some columns.

    One bitmap is a code itself.  With several every set bit is taken once, and the bitmaps of a row are its code,
    so the work grows with the rows and not with the values that share a bitmap.  A word may come in several pieces.
    Words that are dealt by spans keep theirs.
    """
    span = [c for c in ("span",) if c in words.columns]
    if k == 1:
        return words.select(*span, "attr", *WORD, F.array("bitmap").alias("code"), "bits")
    return coded_places(words, k, w).select(*span, "attr", *WORD, "code", F.call_function("shiftleft", F.lit(1).cast("long"), F.col("place")).alias("bits"))


def coded_places(words: DataFrame, k: int, w: int) -> DataFrame:
    """(attr, block, word_no, place, code): the same row by row."""
    span = [c for c in ("span",) if c in words.columns]
    place = words.select(*span, "attr", *WORD, "bitmap", F.explode(set_places(w, "bits")).alias("place"))
    if k == 1:
        return place.select(*span, "attr", *WORD, "place", F.array("bitmap").alias("code"))
    least, most = F.min("bitmap"), F.max("bitmap")
    code = {2: F.array(least, most), 3: F.array(least, F.sum("bitmap") - least - most, most)}.get(k, F.sort_array(F.collect_list("bitmap")))
    return place.groupBy(*span, "attr", *WORD, "place").agg(F.count(F.lit(1)).alias("n"), code.alias("code")).filter(F.col("n") == k).drop("n")


def value_words(index: Index, p: Pred) -> DataFrame:
    """Words of the rows whose column has one of the values: AND of k bitmaps, then OR of the values."""
    own = selected(index, p).select("code")
    k = (own.agg(F.max(F.size("code"))).first()[0] or 1) if index.k > 1 else 1
    codes = own.select(F.explode("code").alias("bitmap")).distinct()
    words = index.words.filter(F.col("attr") == index.cols.index(p.col))
    named = named_bitmaps(codes)
    words = words.filter(F.col("bitmap").isin(named)) if named is not None else words.join(codes, "bitmap", "left_semi")
    return coded_bits(words, k, index.w).join(own, "code", "left_semi").groupBy(*WORD).agg(F.bit_or("bits").alias("bits"))


def all_words(index: Index) -> DataFrame:
    """Every word of every block, all rows set."""
    b = index.blocks.select("block", "first_word", "words", "last_rows", F.explode(F.sequence(F.lit(0).cast("long"), F.col("words") - 1)).alias("at"))
    rows_in = F.when(F.col("at") == F.col("words") - 1, F.col("last_rows")).otherwise(F.lit(index.w))
    return b.select("block", (F.col("first_word") + F.col("at")).alias("word_no"), word_mask(rows_in, index.w).alias("bits"))


def combine_words(parts: list[DataFrame], op: str, index: Index) -> DataFrame:
    """AND, OR, XOR of answers; words that are zero are left out."""
    tagged = reduce(DataFrame.unionByName, [p.select(*WORD, "bits") for p in parts])
    agg = {"and": F.bit_and, "or": F.bit_or, "xor": F.bit_xor}[op]
    out = tagged.groupBy(*WORD).agg(agg("bits").alias("bits"), F.count(F.lit(1)).alias("n"))
    out = out.filter(F.col("n") == len(parts)) if op == "and" else out
    return out.filter("bits <> 0").select(*WORD, "bits")


def answer(index: Index, p: Pred) -> DataFrame:
    if p.op in ("in", "between"):
        return value_words(index, p)
    parts = [answer(index, c) for c in p.children]
    if p.op in ("and", "or", "xor"):
        return combine_words(parts, p.op, index)
    if p.op == "not":
        return combine_words([all_words(index), parts[0]], "xor", index)
    if p.op == "andnot":
        return combine_words([parts[0], combine_words([all_words(index), parts[1]], "xor", index)], "and", index)
    if p.op in ("nand", "nor", "xnor"):
        inner = combine_words(parts, {"nand": "and", "nor": "or", "xnor": "xor"}[p.op], index)
        return combine_words([all_words(index), inner], "xor", index)
    raise ValueError(p.op)


def symmetric_words(index: Index, preds: list[Pred], test: str, t: int = 0, inverted: list[bool] | None = None) -> DataFrame:
    """Answer words of the rows for which the number of true predicates passes a test: at_least, exactly, majority, parity, all_equal.

    The answers' words are added bit by bit into binary counters, one word a digit; no row is touched.
    """
    inverted = inverted or [False] * len(preds)
    parts = [answer(index, ~p if flip else p) for p, flip in zip(preds, inverted, strict=True)]
    n = len(parts)
    at_zero = test == "all_equal" or (test in ("exactly", "at_least") and t == 0)
    tagged = [p.select(*WORD, F.lit(i).alias("i"), "bits") for i, p in enumerate(parts)]
    # where no predicate holds at all there is no word; tests that pass at zero need every word
    tagged += [all_words(index).select(*WORD, F.lit(n).alias("i"), "bits")] if at_zero else []
    words = reduce(DataFrame.unionByName, tagged).groupBy(*WORD).agg(*[F.coalesce(F.max(F.when(F.col("i") == i, F.col("bits"))), F.lit(0).cast("long")).alias(f"_b{i}") for i in range(n + at_zero)])
    digits = n.bit_length()
    words = words.select("*", *[F.lit(0).cast("long").alias(f"_d{d}") for d in range(digits)])
    for i in range(n):  # add one answer: the carry ripples through the digits
        carry = F.col(f"_b{i}")
        summed = []
        for d in range(digits):
            summed.append(F.col(f"_d{d}").bitwiseXOR(carry).alias(f"_d{d}"))
            carry = F.col(f"_d{d}").bitwiseAND(carry)
        words = words.select(*[c for c in words.columns if not c.startswith("_d")], *summed)

    def counts(c: int):
        each = [F.col(f"_d{d}") if c >> d & 1 else F.bitwise_not(F.col(f"_d{d}")) for d in range(digits)]
        return reduce(lambda x, y: x.bitwiseAND(y), each)

    wanted = {"at_least": range(t, n + 1), "exactly": [t], "majority": range(n // 2 + 1, n + 1), "parity": range(1, n + 1, 2), "all_equal": [0, n]}[test]
    bits = reduce(lambda x, y: x.bitwiseOR(y), [counts(c) for c in wanted if 0 <= c <= n], F.lit(0).cast("long"))
    bits = bits.bitwiseAND(F.col(f"_b{n}")) if at_zero else bits
    return words.select(*WORD, bits.alias("bits")).filter("bits <> 0")


def symmetric(index: Index, preds: list[Pred], test: str, t: int = 0, inverted: list[bool] | None = None) -> DataFrame:
    """The same as row ids."""
    return symmetric_words(index, preds, test, t, inverted).select(F.explode(row_bits(index.w, "word_no", "bits")).alias("row_id"))


def row_bits(w: int, word_no: str, bits: str):
    """Row numbers of the set bits of a word."""
    return F.transform(set_places(w, bits), lambda i: F.col(word_no) * F.lit(w) + i)


def set_places(w: int, bits: str):
    """Places of the set bits of a word."""
    return F.array_compact(F.array(*[F.when(F.col(bits).bitwiseAND(_bit(i)) != 0, F.lit(i)) for i in range(w)]))


def _bit(i: int):
    return F.lit(-(1 << 63) if i == 63 else 1 << i).cast("long")


def row_ids(index: Index, p: Pred) -> DataFrame:
    return answer(index, p).select(F.explode(row_bits(index.w, "word_no", "bits")).alias("row_id"))


def count(index: Index, p: Pred) -> DataFrame:
    """One row: how many rows match, from the words alone."""
    return answer(index, p).agg(F.coalesce(F.sum(F.bit_count("bits")), F.lit(0)).cast("long").alias("rows"))


def matching_rows(index: Index, p: Pred) -> DataFrame:
    """The rows themselves, read by block and row number."""
    rows = index.rows.join(row_ids(index, p), "row_id", "left_semi")
    for c, values in index.typed.items():
        rows = rows.join(values.select(F.col("number").alias(c), F.col("value").alias("_v")), c, "left").drop(c).withColumnRenamed("_v", c)
    return rows


def load_only(index: Index, p: Pred) -> DataFrame:
    """Words and bytes that the bitmaps of a predicate's values have, without combining them."""
    leaves, todo = [], [p]
    while todo:
        q = todo.pop()
        leaves += [q] if q.col else []
        todo += q.children
    parts = []
    for q in leaves:
        codes = selected(index, q).select(F.explode("code").alias("bitmap")).distinct()
        parts.append(column_words(index, q, codes).join(codes, "bitmap", "left_semi").select("bits"))
    return reduce(DataFrame.unionByName, parts).agg(F.count(F.lit(1)).alias("words"))


def counts_by_value(index: Index, col: str) -> DataFrame:
    """(value, rows) straight from the bitmaps of a unary column."""
    attr = index.cols.index(col)
    sizes = index.words.filter(F.col("attr") == attr).groupBy("bitmap").agg(F.sum(F.bit_count("bits")).cast("long").alias("rows"))
    d = index.dictionary.filter((F.col("attr") == attr) & (F.size("code") == 1)).select("value", F.element_at("code", 1).alias("bitmap"))
    return d.join(sizes, "bitmap").select("value", "rows")


def _asked(index: Index, queries: DataFrame) -> DataFrame:
    """(qid, attr, value, k, bitmap): the bitmaps that queries (qid, attr, lo, hi) need."""
    values = index.dictionary.select("attr", "value", F.size("code").alias("k"), "code")
    return values.join(F.broadcast(queries), "attr").filter(F.col("value").between(F.col("lo"), F.col("hi"))).select("qid", "attr", "value", "k", F.explode("code").alias("bitmap"))


def batch_load(index: Index, queries: DataFrame) -> DataFrame:
    """(qid, words): how many words each query's bitmaps have; nothing is combined."""
    asked = _asked(index, queries).select("qid", "attr", "bitmap").distinct()
    return index.words.select("attr", "bitmap", "bits").join(asked, ["attr", "bitmap"]).groupBy("qid").agg(F.count("bits").alias("words"))


#: Queries that one long holds a bit each of.
MASK_BITS = 62


def masked_ranges(queries: DataFrame) -> tuple[DataFrame, dict[int, list[int]], dict[tuple[int, int], int]]:
    """(attr, lo, hi, part, mask): ranges that do not overlap, and the queries that hold in each as bits; the queries' numbers by part; what each part leaves free in a column.

    ``queries`` is small, and so is this table: twice as many ranges at most, for each part of MASK_BITS queries.
    """
    asked = queries.select("qid", "attr", "lo", "hi").collect()
    ids, attrs, rows, free = sorted({r["qid"] for r in asked}), sorted({r["attr"] for r in asked}), [], {}
    parts = {p // MASK_BITS: ids[p : p + MASK_BITS] for p in range(0, len(ids), MASK_BITS)}
    for p, own in parts.items():
        bit = {q: 1 << i for i, q in enumerate(own)}
        for a in attrs:
            mine = [(r["lo"], r["hi"], bit[r["qid"]]) for r in asked if r["attr"] == a and r["qid"] in bit]
            bound = {r["qid"] for r in asked if r["attr"] == a}
            free[(p, a)] = sum(bit[q] for q in own if q not in bound)
            cuts = sorted({x for lo, hi, _ in mine for x in (lo, hi + 1)})
            for lo, after in zip(cuts, cuts[1:], strict=False):
                mask = reduce(int.__or__, [m for x, y, m in mine if x <= lo < after <= y + 1], 0)
                rows += [(a, lo, after - 1, p, mask)] if mask else []
    table = queries.sparkSession.createDataFrame(rows, "attr int, lo long, hi long, part int, mask long")
    return table, parts, free


def masked_rows(entries: DataFrame, row: list[str], parts: dict[int, list[int]], free: dict[tuple[int, int], int]) -> DataFrame:
    """(row, part, mask) from entries (row, attr, part, mask): a row's masks meet by AND over the columns; rows of no query are left out."""
    attrs = sorted({a for _, a in free})
    least = F.create_map(*[x for (p, a), m in free.items() for x in (F.lit(p * len(attrs) + attrs.index(a)), F.lit(m).cast("long"))])
    own = entries.groupBy(*row, "part").agg(*[F.coalesce(F.bit_or(F.when(F.col("attr") == a, F.col("mask"))), F.lit(0).cast("long")).alias(f"_m{i}") for i, a in enumerate(attrs)])
    # a part in which every query asks all columns leaves nothing free
    masks = [F.col(f"_m{i}").bitwiseOR(F.element_at(least, F.col("part") * len(attrs) + i)) if any(free[(p, a)] for p in parts) else F.col(f"_m{i}") for i, a in enumerate(attrs)]
    return own.select(*row, "part", reduce(lambda x, y: x.bitwiseAND(y), masks).alias("mask")).filter("mask <> 0")


def query_bits(parts: dict[int, list[int]], queries: DataFrame) -> DataFrame:
    """(qid, part, bit): where the masks hold each query."""
    return queries.sparkSession.createDataFrame([(q, p, 1 << i) for p, own_ids in parts.items() for i, q in enumerate(own_ids)], "qid long, part int, bit long")


def masked_counts(met: DataFrame, parts: dict[int, list[int]], queries: DataFrame) -> DataFrame:
    """(qid, rows) from the masks of rows; equal ones are counted once."""
    names = query_bits(parts, queries)
    hits = met.groupBy("part", "mask").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(names), "part").filter(F.col("mask").bitwiseAND(F.col("bit")) != 0).groupBy("qid").agg(F.sum("n").alias("rows"))
    return names.select("qid").join(hits, "qid", "left").select("qid", F.coalesce("rows", F.lit(0).cast("long")).alias("rows"))


def masked_ids(met: DataFrame, row_id: Column, parts: dict[int, list[int]], queries: DataFrame) -> DataFrame:
    """(qid, row_id) from the masks of rows."""
    hits = met.join(F.broadcast(query_bits(parts, queries)), "part").filter(F.col("mask").bitwiseAND(F.col("bit")) != 0)
    return hits.select("qid", row_id.alias("row_id"))


def _batch(index: Index, queries: DataFrame, ids: bool) -> DataFrame:
    """The answers to queries (qid, attr, lo, hi) in one pass over the words they need: row ids or counts.

    Bitmaps and codes that they need are broadcast up to BROADCAST_VALUES, and words dealt by spans are answered where
    they are made.  With codes of several bitmaps a row carries all queries that its values answer as bits of a mask.
    """
    values = index.dictionary.select("attr", "value", "code")
    if index.k > 1:
        ranges, parts, free = masked_ranges(queries)
        wanted_codes = values.join(F.broadcast(ranges), "attr").filter(F.col("value").between(F.col("lo"), F.col("hi"))).select("attr", "code", "part", "mask")
    else:
        wanted_codes = values.join(F.broadcast(queries), "attr").filter(F.col("value").between(F.col("lo"), F.col("hi"))).select("qid", "attr", "code")
    bitmaps = wanted_codes.select("attr", F.explode("code").alias("bitmap")).distinct()
    # columns of few values have shorter codes
    shape = {r["attr"]: r for r in wanted_codes.groupBy("attr").agg(F.count(F.lit(1)).alias("n"), F.max(F.size("code")).alias("k")).collect()}
    if sum(r["n"] for r in shape.values()) <= BROADCAST_VALUES:
        bitmaps, wanted_codes = F.broadcast(bitmaps), F.broadcast(wanted_codes)
    words = index.words.join(bitmaps, ["attr", "bitmap"], "left_semi")
    span = [c for c in ("span",) if c in words.columns]
    if index.k > 1:
        lengths = {a: r["k"] for a, r in shape.items()} or {0: 1}
        places = [coded_places(words.filter(F.col("attr").isin([a for a, n in lengths.items() if n == k])), k, index.w) for k in sorted(set(lengths.values()))]
        met = masked_rows(reduce(DataFrame.unionByName, places).join(wanted_codes, ["attr", "code"]), [*span, *WORD, "place"], parts, free)
        return masked_ids(met, F.col("word_no") * F.lit(index.w) + F.col("place"), parts, queries) if ids else masked_counts(met, parts, queries)
    hit = coded_bits(words, 1, index.w).join(wanted_codes, ["attr", "code"])
    per_column = hit.groupBy(*span, "qid", "attr", *WORD).agg(F.bit_or("bits").alias("bits"))
    wanted = queries.groupBy("qid").agg(F.count_distinct("attr").alias("_all"))
    per_word = per_column.groupBy(*span, "qid", *WORD).agg(F.bit_and("bits").alias("bits"), F.count(F.lit(1)).alias("_n")).join(F.broadcast(wanted), "qid").filter("_n = _all")
    if ids:
        return per_word.filter("bits <> 0").select("qid", F.explode(row_bits(index.w, "word_no", "bits")).alias("row_id"))
    hits = per_word.groupBy("qid").agg(F.sum(F.bit_count("bits")).cast("long").alias("rows"))
    return wanted.select("qid").join(hits, "qid", "left").select("qid", F.coalesce("rows", F.lit(0).cast("long")).alias("rows"))


def batch_counts(index: Index, queries: DataFrame) -> DataFrame:
    """(qid, rows): conjunctions of ranges, (qid, attr, lo, hi), all answered at once.

    An equality is a range of one value.  ``queries`` is a small table; its size is the caller's.
    """
    return _batch(index, queries, False)


def batch_row_ids(index: Index, queries: DataFrame) -> DataFrame:
    """(qid, row_id): the same answers as row ids, taken from the set bits."""
    return _batch(index, queries, True)


def _batch_lists(lists: DataFrame, queries: DataFrame) -> tuple[DataFrame, dict[int, list[int]]]:
    ranges, parts, free = masked_ranges(queries)
    own = lists.join(F.broadcast(ranges), "attr").filter(F.col("value").between(F.col("lo"), F.col("hi"))).select("attr", "row_id", "part", "mask")
    return masked_rows(own, ["row_id"], parts, free), parts


def batch_postings(lists: DataFrame, queries: DataFrame) -> DataFrame:
    """The same counts from row-id lists: union within a column, intersection across columns; an entry carries its queries as bits of a mask."""
    return masked_counts(*_batch_lists(lists, queries), queries)


def batch_postings_ids(lists: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, row_id) from row-id lists."""
    met, parts = _batch_lists(lists, queries)
    return masked_ids(met, F.col("row_id"), parts, queries)


def batch_postings_load(lists: DataFrame, queries: DataFrame) -> DataFrame:
    """(qid, entries): how many entries each query's lists have; nothing is combined."""
    asked = lists.join(F.broadcast(queries), "attr").filter(F.col("value").between(F.col("lo"), F.col("hi")))
    return asked.groupBy("qid").agg(F.count("row_id").alias("entries"))


def batch_scan(rows: DataFrame, cols: list[str], queries: DataFrame) -> DataFrame:
    """(qid, row_id): the same from the rows themselves, each looked at once for all queries."""
    boxes: dict[int, dict[int, Column]] = {}
    for r in queries.select("qid", "attr", "lo", "hi").collect():  # ranges of one column are alternatives
        own, test = boxes.setdefault(r["qid"], {}), F.col(cols[r["attr"]]).between(r["lo"], r["hi"])
        own[r["attr"]] = own[r["attr"]] | test if r["attr"] in own else test
    hit = F.array_compact(F.array(*[F.when(reduce(lambda x, y: x & y, own.values()), F.lit(q).cast("long")) for q, own in boxes.items()]))
    return rows.select("row_id", F.explode(hit).alias("qid")).select("qid", "row_id")


# --- baselines -----------------------------------------------------------------------------------


def postings(rows: DataFrame, cols: list[str]) -> DataFrame:
    """(attr, value, row_id) sorted row-id lists, one row an entry, so that no list is held by one task."""
    return rows.select("row_id", F.explode(F.array(*[F.struct(F.lit(i).alias("attr"), F.col(c).alias("value")) for i, c in enumerate(cols)])).alias("s")).select("s.attr", "s.value", "row_id")


def postings_range(lists: DataFrame, ranges: dict[int, tuple[int, int]]) -> DataFrame:
    """Row ids in all ranges, by union of lists within a column and intersection across columns."""
    parts = [lists.filter((F.col("attr") == a) & F.col("value").between(*r)).select("row_id").distinct() for a, r in ranges.items()]
    return reduce(lambda x, y: x.join(y, "row_id", "left_semi"), parts)


def full_scan(rows: DataFrame, ranges: dict[str, tuple[int, int]]) -> DataFrame:
    return rows.filter(reduce(lambda x, y: x & y, [F.col(c).between(*r) for c, r in ranges.items()]))
