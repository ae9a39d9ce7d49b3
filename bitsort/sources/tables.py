"""Readers for the given tables, flat files and folders, and the derived fixtures (all columns bigint)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from bitsort.operators.dictionary import numbered_values, typed_values
from bitsort.plans.recovery import stored, stored_alone


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def delimited(spark: SparkSession, path: str, schema: str, sep: str = ",") -> DataFrame:
    """Flat delimited files with a declared schema, so nothing is inferred in a second pass."""
    return spark.read.csv(path, schema=schema, sep=sep)


def folder(spark: SparkSession, path: str, schema: str, sep: str = ",") -> DataFrame:
    """All small files of a folder as one table, with the file's name as a column."""
    return spark.read.csv(path, schema=schema, sep=sep).withColumn("file", F.element_at(F.split(F.col("_metadata.file_path"), "/"), -1))


def days(c: str) -> Column:
    return F.datediff(F.to_date(c), F.lit("1970-01-01").cast("date")).cast("long")


def _long(e: Column, name: str) -> Column:
    return e.cast("long").alias(name)


def line4(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "lineitem")
    return t.select(_long(F.col("l_linenumber"), "ln"), _long(F.round(F.col("l_discount") * 100), "disc"), days("l_shipdate").alias("ship"), _long(F.col("l_partkey"), "part"))


def line3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line4(spark, sf_dir).select("ln", "disc", "part")


def line10(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = table(spark, sf_dir, "lineitem")
    return t.select(
        _long(F.ascii("l_linestatus"), "status"), _long(F.ascii("l_returnflag"), "flag"), _long(F.col("l_linenumber"), "ln"), _long(F.round(F.col("l_tax") * 100), "tax"), _long(F.round(F.col("l_discount") * 100), "disc"),
        _long(F.col("l_quantity"), "qty"), days("l_shipdate").alias("ship"), _long(F.col("l_suppkey"), "supp"), _long(F.col("l_partkey"), "part"), _long(F.round(F.col("l_extendedprice") * 100), "price"),
    )


def event4(spark: SparkSession, sf_dir: str, *keep: str) -> DataFrame:
    """``keep``: columns of the events that stay beside the four."""
    t = table(spark, sf_dir, "events")
    return t.select(*keep, _long(F.get_json_object("props", "$.k"), "k"), _long(F.floor(F.unix_timestamp("ts") / 3600), "hour"), _long(F.col("user_id"), "usr"), _long(F.round(F.col("value") * 100), "val"))


def rating4(spark: SparkSession, sf_dir: str) -> DataFrame:
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority", "o_orderdate", "o_custkey")
    j = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    return j.select(_long(F.substring("o_orderpriority", 1, 1), "prio"), days("o_orderdate").alias("day"), _long(F.col("o_custkey"), "cust"), _long(F.col("l_partkey"), "part"))


def rating3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rating4(spark, sf_dir).select("prio", "day", "part")


def corr3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlated columns: order day, ship day, order status."""
    line = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_shipdate")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate", "o_orderstatus")
    return line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(days("o_orderdate").alias("day"), days("l_shipdate").alias("ship"), _long(F.ascii("o_orderstatus"), "status"))


def word_grams(spark: SparkSession, sf_dir: str, n: int = 4) -> DataFrame:
    """Every run of ``n`` long words of every document, whole texts, as strings w1 .. wn.

    Words are lower-cased runs of letters longer than three, stemmed by a short suffix rule that SQL
    can state too; ``functions.stem`` has the full stemmer.
    """
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: F.length(w) > 3)
    stems = F.transform(words, lambda w: F.regexp_replace(w, "(ing|ed|es|s)$", ""))
    t = table(spark, sf_dir, "documents").select(stems.alias("w")).filter(F.size("w") >= n)
    runs = F.transform(F.sequence(F.lit(0), F.size("w") - n), lambda i: F.struct(*[F.get("w", i + k).alias(f"w{k + 1}") for k in range(n)]))
    return t.select(F.explode(runs).alias("s")).select("s.*")


def gram4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runs of four words, each column numbered in the order of its values.  Only the numbers stay stored."""

    def numbered() -> DataFrame:
        grams, cols = stored(word_grams(spark, sf_dir)), ["w1", "w2", "w3", "w4"]
        return numbered_values(grams, cols, typed_values(grams, cols))

    return stored_alone(spark, numbered)


def skewed4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four columns of the documents, c1 to c4, from the most skewed one on: first long word, length in hundreds of characters, source, language."""
    t = table(spark, sf_dir, "documents")
    word = F.regexp_extract(F.lower("text"), r"(\p{L}{4,})", 1)
    own = t.select(word.alias("c1"), _long(F.floor(F.length("text") / 100), "c2"), F.col("source").alias("c3"), F.col("lang").alias("c4"))
    cols = ["c1", "c2", "c3", "c4"]
    return numbered_values(own, cols, typed_values(own, cols))


def _uniform(i: Column, seed: int) -> Column:
    """A number in (0, 1) from a row number, by integer arithmetic that any SQL can repeat."""
    p = 2_147_483_647
    h = F.pmod((i + 1) * F.lit(48_271 + 2 * seed), F.lit(p))
    h = F.pmod(F.pmod(h * F.lit(69_621), F.lit(p)) + F.lit(seed * 7_919 + 12_345), F.lit(p))
    h = F.pmod(h * F.lit(16_807), F.lit(p))
    return (h.cast("double") + 0.5) / float(p)


def uniform(spark: SparkSession, cardinalities: list[int], n: int = 100_000) -> DataFrame:
    """Independent uniform columns, and ``place``: a random order that does not depend on the values."""
    return spark.range(n).select(F.xxhash64("id").alias("place"), *[F.floor(_uniform(F.col("id"), 11 * (k + 1)) * c).cast("long").alias(f"c{k + 1}") for k, c in enumerate(cardinalities)])


def zipf(spark: SparkSession, skews: list[float], values: int = 100, n: int = 100_000) -> DataFrame:
    """Independent columns with Zipf frequencies, by inverse distribution, and ``place`` as in ``uniform``."""
    cols = []
    for k, s in enumerate(skews):
        total = sum(j**-s for j in range(1, values + 1))
        cut, at = [], 0.0
        for j in range(1, values):
            at += j**-s / total
            cut.append(at)
        u = _uniform(F.col("id"), 13 * (k + 1))
        below = F.size(F.filter(F.array(*[F.lit(c) for c in cut]), _at_most(u)))
        cols.append(below.cast("long").alias(f"c{k + 1}"))
    return spark.range(n).select(F.xxhash64("id").alias("place"), *cols)


def _at_most(u: Column):
    return lambda c: c <= u


FIXTURES = {
    "line3": (line3, ["ln", "disc", "part"]),
    "line4": (line4, ["ln", "disc", "ship", "part"]),
    "line10": (line10, ["status", "flag", "ln", "tax", "disc", "qty", "supp", "ship", "part", "price"]),
    "event4": (event4, ["k", "hour", "usr", "val"]),
    "rating3": (rating3, ["prio", "day", "part"]),
    "rating4": (rating4, ["prio", "day", "cust", "part"]),
    "corr3": (corr3, ["day", "ship", "status"]),
    "gram4": (gram4, ["w1", "w2", "w3", "w4"]),
}


def fixture(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, list[str]]:
    f, cols = FIXTURES[name]
    return f(spark, sf_dir), cols


def literal(spark: SparkSession, rows: list[tuple], names: list[str]) -> DataFrame:
    """A small table of bigints from literals."""
    return spark.createDataFrame(rows, T.StructType([T.StructField(n, T.LongType()) for n in names]))
