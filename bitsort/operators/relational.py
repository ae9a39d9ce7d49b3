"""Relational surroundings: range and as-of joins, bitmap join index, grouping sets, top-k."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def range_join(points: DataFrame, ranges: DataFrame, at: str, lo: str, hi: str, width: int) -> DataFrame:
    """Points in [lo, hi) of ranges: an equi-join on buckets of ``width``, then the exact test."""
    p = points.withColumn("_b", F.floor(F.col(at) / width))
    r = ranges.withColumn("_b", F.explode(F.sequence(F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width))))
    return p.join(r, "_b").filter((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_b")


def as_of_join(left: DataFrame, right: DataFrame, keys: list[str], left_time: str, right_time: str, value: str) -> DataFrame:
    """Each left row with the value of the latest right row of its keys that is not later: union and one window."""
    a = left.select(*left.columns, F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.select(*[F.col(k) if k in keys else F.lit(None).cast(left.schema[k].dataType).alias(k) for k in left.columns], F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    order = Window.partitionBy(*keys).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last("_v", ignorenulls=True).over(order)).filter("_side = 1").drop("_t", "_side", "_v")


def bitmap_join_column(facts: DataFrame, dimension: DataFrame, fact_key: str, dim_key: str, attribute: str) -> DataFrame:
    """Facts with a dimension's attribute, ready to be indexed."""
    return facts.join(dimension.select(F.col(dim_key).alias("_k"), attribute), F.col(fact_key) == F.col("_k")).drop("_k")


def histograms_by_sets(df: DataFrame, cols: list[str]) -> DataFrame:
    """(col, value, cnt) of all columns and the total, by grouping sets in one pass."""
    view = df.select(*[F.col(c).cast("string").alias(c) for c in cols])
    view.createOrReplaceTempView("_grouped")
    sets = ", ".join(f"({c})" for c in cols) + ", ()"
    which = "CASE " + " ".join(f"WHEN grouping({c}) = 0 THEN '{c}'" for c in cols) + " ELSE 'all' END"
    return df.sparkSession.sql(f"SELECT {which} AS col, coalesce({', '.join(cols)}) AS value, count(*) AS cnt FROM _grouped GROUP BY GROUPING SETS ({sets})")


def top_values(hist: DataFrame, n: int) -> DataFrame:
    """The n most frequent values of each attribute, ties by value."""
    order = Window.partitionBy("attr").orderBy(F.desc("cnt"), "value")
    return hist.withColumn("place", F.row_number().over(order)).filter(F.col("place") <= n)
