"""Quality rules, in DataFrame functions only.

Base figures (word counts, symbols, repeated lines and 3-word windows) plus distribution
divergence: a document's character-class and common-word histograms against references of the
languages, by Jensen-Shannon distance (base 2, so 0 to 1).  The reference nearest to the document
counts.  Short documents have ragged histograms, so each rule has a minimum-length guard.

Defined results: a null text has no words and fails the base rule; columns other than doc_id and
text are not read; repeated rows are judged each on their own.
"""

from __future__ import annotations

import zlib
from itertools import count

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

WORD_BREAKS = r"[\x20\x09-\x0D]+"
#: Marks that can follow a word.
MARKS = ".,;:!?'\"()-"
#: Share of letters, white space, digits, punctuation (.,;:!?'"()-) and all other characters in
#: running text; fixed values, rounded from general prose of the languages.
CLASSES = ("letters", "spaces", "digits", "punctuation", "others")
CLASS_REFERENCE = {
    "en": (0.805, 0.170, 0.003, 0.021, 0.001),
    "de": (0.825, 0.145, 0.004, 0.025, 0.001),
    "fr": (0.805, 0.165, 0.003, 0.026, 0.001),
    "es": (0.810, 0.168, 0.003, 0.018, 0.001),
}
#: Share of the commonest function words among all words, in per mille; fixed values.
WORD_REFERENCE = {
    "en": {"the": 60, "of": 33, "and": 28, "to": 25, "a": 22, "in": 20, "is": 11, "that": 11, "it": 9, "was": 9, "for": 9, "on": 7, "with": 7, "are": 6, "as": 6, "be": 6, "by": 5, "this": 5, "from": 4, "or": 4},
    "de": {"der": 33, "die": 32, "und": 28, "in": 18, "den": 12, "von": 11, "zu": 11, "das": 11, "mit": 9, "sich": 8, "des": 8, "auf": 8, "ist": 8, "für": 8, "nicht": 7, "ein": 7, "eine": 7, "als": 6, "auch": 6, "im": 6},
    "fr": {"de": 52, "la": 29, "le": 26, "et": 22, "les": 21, "des": 18, "en": 14, "un": 13, "du": 12, "une": 11, "que": 10, "est": 9, "pour": 8, "qui": 8, "dans": 8, "par": 7, "sur": 6, "au": 6, "pas": 6, "avec": 5},
    "es": {"de": 62, "la": 40, "que": 30, "el": 29, "en": 27, "y": 26, "a": 20, "los": 17, "se": 15, "del": 13, "las": 12, "un": 10, "por": 10, "con": 9, "no": 9, "una": 9, "para": 8, "es": 7, "al": 6, "su": 7},
}
#: Guards: from so many words on, the class and the word distance at which a document diverges.
#: Short texts have ragged histograms, so their limits are wider, and below 50 words none holds.
LIMITS = ((200, 0.185, 0.27), (100, 0.19, 0.32), (50, 0.25, 1.0))


def js_distance(p: list[Column], q: list[float]) -> Column:
    """Jensen-Shannon distance of two histograms of equal length; p may be scaled by any column."""
    total = None
    for x, y in zip(p, q, strict=True):
        m = (x + F.lit(y)) / 2
        term = F.when(x > 0, x * F.log2(x / m)).otherwise(0.0) + (F.lit(y) * F.log2(F.lit(y) / m) if y > 0 else F.lit(0.0))
        total = term if total is None else total + term
    return F.sqrt(F.greatest(total / 2, F.lit(0.0)))


def _without(column: Column, pattern: str) -> Column:
    return F.length(F.regexp_replace(column, pattern, ""))


#: The known common words; each stands for one character in the string that a document's common words become.
KNOWN = sorted({w for ref in WORD_REFERENCE.values() for w in ref})
LETTERS = [chr(33 + i) for i in range(len(KNOWN))]


def _checksum_slots() -> list[str]:
    """The characters at places by the words' checksums, as many places as keep all of them apart."""
    sums = [zlib.crc32(w.encode()) for w in KNOWN]
    n = next(n for n in count(len(sums)) if len({x % n for x in sums}) == len(sums))
    return [dict(zip((x % n for x in sums), LETTERS, strict=True)).get(i, "") for i in range(n)]


SLOTS = _checksum_slots()


def coded_words(words: Column) -> Column:
    """Known words, one character each: no word is compared with every known one."""
    table = F.array(*[F.lit(x) for x in SLOTS])
    return F.array_join(F.transform(words, lambda w: F.get(table, (F.crc32(w.cast("binary")) % len(SLOTS)).cast("int"))), "")


def counts_of(coded: str) -> Column:
    """How often each known word is there; a function of an array, as 72 expressions would not fit a generated method."""
    return F.transform(F.array(*[F.lit(x) for x in LETTERS]), lambda x: F.length(coded) - F.length(F.replace(F.col(coded), x, F.lit(""))))


def window_hashes(words: Column, n: int = 3) -> Column:
    """The hash of every run of n words of an array."""
    count = F.size(words) - F.lit(n - 1)
    return F.when(count <= 0, F.array().cast("array<bigint>")).otherwise(F.transform(F.sequence(F.lit(0), count - 1), lambda i: F.xxhash64(*[F.get(words, i + k) for k in range(n)])))


def repeated_window_words(hashes: Column, n: int = 3) -> Column:
    """How many words lie in windows of n words whose hash an array holds twice or more."""
    # sorted, equal hashes lie side by side, in order of place
    order = F.sort_array(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def places(s: Column) -> Column:
        marked = F.transform(s, lambda x, j: F.when((x["h"] == F.get(s, j + 1)["h"]) | F.coalesce(x["h"] == F.get(s, j - 1)["h"], F.lit(False)), x["i"]))
        return F.sort_array(F.filter(marked, lambda x: x.isNotNull()))

    def cover(p: Column) -> Column:
        # a window adds the words that no earlier one has: up to n, or the distance to the last
        return F.aggregate(p, F.struct(F.lit(-n).alias("last"), F.lit(0).alias("sum")), lambda a, x: F.struct(x.alias("last"), (a["sum"] + F.least(F.lit(n), x - a["last"])).alias("sum")), lambda a: a["sum"])

    bind = lambda value, f: F.get(F.transform(F.array(value), f), F.lit(0))  # noqa: E731  evaluate once, use many times
    return F.when(F.size(F.array_distinct(hashes)) == F.size(hashes), F.lit(0)).otherwise(bind(order, lambda s: cover(places(s))))


def measured(docs: DataFrame) -> DataFrame:
    """Add the figures of every document: base counts, shares of the classes, both distances."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    df = docs.withColumn("_t", text)
    df = df.withColumn("_w", F.filter(F.split("_t", WORD_BREAKS), lambda x: x != ""))
    lines = F.filter(F.split("_t", "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))
    # letters are most of a text; all other characters are counted in what is left without them
    df = df.withColumn("_lines", lines).withColumn("_h", window_hashes(F.col("_w"))).withColumn("_rest", F.regexp_replace("_t", r"\p{L}+", ""))
    df = (
        df.withColumn("n_words", F.size("_w").cast("long"))
        .withColumn("n_chars_all", F.length("_t").cast("long"))
        .withColumn("n_letters", (F.col("n_chars_all") - F.length("_rest")).cast("long"))
        .withColumn("n_spaces", (F.length("_rest") - _without(F.col("_rest"), WORD_BREAKS)).cast("long"))
        .withColumn("n_digits", _without(F.col("_rest"), r"[^0-9]+").cast("long"))
        .withColumn("n_punctuation", _without(F.col("_rest"), r"""[^.,;:!?'"()\-]+""").cast("long"))
        .withColumn("n_symbols", _without(F.col("_rest"), r"[^#*$%&|<>]+").cast("long"))
        .withColumn("n_dup_lines", (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"))
        .withColumn("n_repeat_words", repeated_window_words(F.col("_h")).cast("long"))
    )
    df = df.withColumn("word_chars", F.col("n_chars_all") - F.col("n_spaces"))
    longest = max(map(len, KNOWN)) + 2  # with up to two marks after it
    short = F.filter(F.col("_w"), lambda w: F.length(w) <= longest)
    common = F.filter(F.transform(short, lambda w: F.lower(F.rtrim(w, F.lit(MARKS)))), lambda w: w.isin(KNOWN))
    df = df.withColumn("_common", coded_words(common))
    df = df.withColumn("_counts", counts_of("_common"))
    chars, words = F.greatest(F.col("n_chars_all"), F.lit(1)), F.greatest(F.col("n_words"), F.lit(1))
    others = F.col("n_chars_all") - F.col("n_letters") - F.col("n_spaces") - F.col("n_digits") - F.col("n_punctuation")
    classes = [(c / chars).cast("double") for c in (F.col("n_letters"), F.col("n_spaces"), F.col("n_digits"), F.col("n_punctuation"), others)]
    df = df.withColumn("class_distance", F.least(*[js_distance(classes, list(q)) for q in CLASS_REFERENCE.values()]))
    by_language = []
    for ref in WORD_REFERENCE.values():
        p = [(F.get("_counts", F.lit(KNOWN.index(w))) / words).cast("double") for w in ref]
        rest = F.lit(1.0) - sum(p[1:], p[0])
        q = [n / 1000 for n in ref.values()]
        by_language.append(js_distance([*p, F.greatest(rest, F.lit(0.0))], [*q, 1 - sum(q)]))
    df = df.withColumn("word_distance", F.least(*by_language))
    return df.drop("_t", "_w", "_h", "_lines", "_rest", "_common", "_counts")


def judged(docs: DataFrame) -> DataFrame:
    """``measured`` plus base_failed, diverges and kept."""
    n = F.col("n_words")
    diverges = F.lit(False)
    for least, by_class, by_word in reversed(LIMITS):
        diverges = F.when(n >= least, (F.col("class_distance") > by_class) | (F.col("word_distance") > by_word)).otherwise(diverges)
    return (
        measured(docs)
        .withColumn("base_failed", (n < 50) | (100 * F.col("n_repeat_words") > 50 * n))
        .withColumn("diverges", diverges)
        .withColumn("kept", ~F.col("base_failed") & ~F.col("diverges"))
    )


def quality_report(docs: DataFrame) -> DataFrame:
    """One row per document with the figures and the verdict."""
    return judged(docs.select("doc_id", "text")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "class_distance", "word_distance")


def kept_documents(docs: DataFrame) -> DataFrame:
    """The rows of ``docs`` that pass, unchanged."""
    own = docs.columns
    whole = docs.select("doc_id", "text", F.struct(*[F.col(f"`{c}`") for c in own]).alias("_row"))
    # a filter on a column that is not deterministic stays above the projections; pushed down, it would
    # repeat the whole tree of figures for every place where the verdict names one
    told = judged(whole).withColumn("_guard", F.monotonically_increasing_id())
    return told.filter(F.col("kept") & (F.col("_guard") >= 0)).select(*[F.col("_row").getField(c).alias(c) for c in own])
