"""Secret scans with corpus-wide ownership frequency, in DataFrame functions only.

Base patterns (assignments, access keys, long hexadecimal strings) and further token formats give
candidate spans.  The value of every candidate is hashed and counted over the whole corpus by
distinct repositories (documents) and owners (sources): values that many owners hold are copied
examples, values of few owners look live.  Base spans always stay; further spans stay unless they
are examples.

Positions come from the lengths of the pieces between matches, so they are code points.

Defined results: a null text has no spans; a null source is an owner of its own; repeated rows are
scanned each on their own; a table without a source column counts as one owner.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from bitsort.llm.stages import written

#: Base kinds, in the order in which ties are listed: pattern, group that holds the value, least length of it.
ASSIGN = r"""(?i:(password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
BASE = {"assign": (ASSIGN, 2, 12), "access": ("AKIA[A-Z0-9]+", 0, 18), "hex": ("[0-9a-f]{16,}", 0, 16)}
#: Published formats of further credentials: pattern, group of the value.
FURTHER = {
    "forge": (r"\bgh[pousr]_[A-Za-z0-9]{36,}", 0),
    "chat": (r"\bxox[abprs]-[A-Za-z0-9-]{10,}", 0),
    "map": (r"\bAIza[0-9A-Za-z_-]{35}", 0),
    "payment": (r"\b[sr]k_live_[0-9A-Za-z]{16,}", 0),
    "jwt": (r"\beyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}", 0),
    "pem": (r"-----BEGIN [A-Z ]{0,20}PRIVATE KEY-----", 0),
    "login": (r"\b[a-z][a-z0-9+.-]{1,20}://[^\s:@/]{1,64}:([^\s:@/]{4,64})@", 1),
}
#: A string that each match of FURTHER holds; only texts with one of them are searched.
FURTHER_GATE = r"gh[pousr]_|xox[abprs]-|AIza|k_live_|eyJ|PRIVATE KEY|://[^\s:@/]{1,64}:"
KINDS = [*BASE, *FURTHER]
#: From so many distinct owners on, or so many distinct documents, a value is a copied example.
EXAMPLE_OWNERS, EXAMPLE_DOCUMENTS = 3, 25
SPAN = "array<struct<start:int,kind:int,end:int,value:bigint>>"


def _spans(text: Column, kind: str, pattern: str, group: int, least: int, gate: Column) -> Column:
    gaps = F.transform(F.split(text, pattern, -1), F.length)
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = F.regexp_extract_all(text, F.lit(pattern), F.lit(group)) if group else found
    pairs = F.arrays_zip(gaps.alias("gap"), F.transform(found, F.length).alias("len"), values.alias("val"))
    code = KINDS.index(kind)

    def step(a: Column, x: Column) -> Column:
        start = a["at"] + x["gap"]
        span = F.struct(start.cast("int").alias("start"), F.lit(code).alias("kind"), (start + x["len"]).cast("int").alias("end"), F.xxhash64(x["val"]).alias("value"))
        good = x["len"].isNotNull() & (F.length(x["val"]) >= least)
        return F.struct((start + F.coalesce(x["len"], F.lit(0))).cast("int").alias("at"), F.when(good, F.array_append(a["out"], span)).otherwise(a["out"]).alias("out"))

    none = F.array().cast(SPAN)
    return F.when(gate, F.aggregate(pairs, F.struct(F.lit(0).alias("at"), none.alias("out")), step, lambda a: a["out"])).otherwise(none)


def candidates(docs: DataFrame) -> DataFrame:
    """Add ``base`` and ``further``: sorted arrays of spans (start, kind, end, value hash)."""
    df = docs.withColumn("_t", F.coalesce(F.col("text").cast("string"), F.lit("")))
    df = df.withColumn("_assign", F.col("_t").rlike(ASSIGN)).withColumn("_hex", F.col("_t").rlike(BASE["hex"][0]))
    df = df.withColumn("_further", F.col("_t").rlike(FURTHER_GATE))
    gates = {"assign": F.col("_assign"), "access": F.col("_t").contains("AKIA"), "hex": F.col("_hex")}
    for kind, (pattern, group, least) in BASE.items():
        df = df.withColumn(f"_{kind}s", _spans(F.col("_t"), kind, pattern, group, least, gates[kind]))
    own = [_spans(F.col("_t"), kind, pattern, group, 1, F.col("_further")) for kind, (pattern, group) in FURTHER.items()]
    df = df.withColumn("further", F.when(F.col("_further"), F.array_sort(F.concat(*own))).otherwise(F.array().cast(SPAN)))
    df = df.withColumn("base", F.array_sort(F.concat(*[F.col(f"_{kind}s") for kind in BASE])))
    return df.drop("_t", "_assign", "_hex", "_further", *[f"_{kind}s" for kind in BASE])


def ownership(spans: DataFrame) -> DataFrame:
    """(value, owners, documents): in how many distinct sources and documents each value occurs.

    ``spans`` has value, source and doc_id.  Each level is combined before its shuffle, and the
    first has the document in its key, so a value that everyone copies is no hot key.
    """
    once = spans.select("value", "source", "doc_id").distinct()
    by_owner = once.groupBy("value", "source").agg(F.count(F.lit(1)).alias("n"))
    return by_owner.groupBy("value").agg(F.count(F.lit(1)).alias("owners"), F.sum("n").alias("documents"))


def listed(spans: Column) -> Column:
    names = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(names, s["kind"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def scanned(docs: DataFrame, carry: list[str] | None = None) -> DataFrame:
    """One row per input row: doc_id, base, spans (base and kept further ones), live and example counts.

    ``carry``: further columns of ``docs`` to keep.
    """
    carry = carry or []
    source = F.col("source").cast("string") if "source" in docs.columns else F.lit(None).cast("string")
    rows = docs.select("doc_id", source.alias("_source"), F.col("text").cast("string").alias("text"), *[F.struct(*[F.col(f"`{c}`") for c in carry]).alias("_row")] * bool(carry))
    rows = written(candidates(rows).drop(*([] if carry else ["text"])).withColumn("_id", F.monotonically_increasing_id()))
    every = rows.filter((F.size("base") > 0) | (F.size("further") > 0)).select("_id", "doc_id", F.col("_source").alias("source"), F.explode(F.concat("base", "further")).alias("s"))
    every = every.select("_id", "doc_id", "source", "s", F.col("s.value").alias("value"))
    wide = ownership(every).filter((F.col("owners") >= EXAMPLE_OWNERS) | (F.col("documents") >= EXAMPLE_DOCUMENTS)).select("value", F.lit(True).alias("example"))
    told = every.join(wide, "value", "left").withColumn("example", F.coalesce("example", F.lit(False)))
    stays = (F.col("s.kind") < len(BASE)) | ~F.col("example")
    told = told.groupBy("_id").agg(F.array_sort(F.collect_list(F.when(stays, F.col("s")))).alias("spans"), F.count_if(~F.col("example")).alias("n_live"), F.count_if("example").alias("n_example"))
    out = rows.join(told, "_id", "left")
    return out.select(
        "doc_id", "base", F.coalesce("spans", F.array().cast(SPAN)).alias("spans"), F.coalesce("n_live", F.lit(0)).cast("long").alias("n_live"), F.coalesce("n_example", F.lit(0)).cast("long").alias("n_example"), *["_row"] * bool(carry)
    )


def secret_report(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans, n_live, n_example."""
    out = scanned(docs)
    counts = [F.size(F.filter("base", _is_kind(k))).cast("long").alias(f"n_{name}") for k, name in enumerate(BASE)]
    return out.select("doc_id", *counts, F.sha2(listed(F.col("base")), 256).alias("base_sha256"), listed(F.col("spans")).alias("spans"), "n_live", "n_example")


def _is_kind(code: int):
    return lambda s: s["kind"] == code


def redacted(docs: DataFrame, mark: str = "[SECRET]") -> DataFrame:
    """The rows of ``docs`` with every span of their text replaced by ``mark``; n_chars follows the text."""
    out = scanned(docs, docs.columns)
    text = F.col("_row")["text"]

    def step(a: Column, s: Column) -> Column:
        # overlapping spans become one mark
        piece = F.when(s["start"] >= a["at"], F.concat(F.substring(text, a["at"] + 1, s["start"] - a["at"]), F.lit(mark))).otherwise(F.lit(""))
        return F.struct(F.greatest(a["at"], s["end"]).alias("at"), F.array_append(a["out"], piece).alias("out"))

    cut = F.aggregate("spans", F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out")), step, lambda a: F.concat(F.array_join(a["out"], ""), F.substring(text, a["at"] + 1, F.length(text))))
    new = F.when(F.size("spans") == 0, text).otherwise(cut)
    out = out.withColumn("_new", new)
    cols = [F.col("_new").alias(c) if c == "text" else F.when(F.size("spans") == 0, F.col("_row")[c]).otherwise(F.length("_new")).cast(docs.schema[c].dataType).alias(c) if c == "n_chars" else F.col("_row")[c].alias(c) for c in docs.columns]
    return out.select(*cols)
