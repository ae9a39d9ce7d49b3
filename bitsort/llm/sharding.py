"""Sharding by a hierarchical weighted hash tree, in DataFrame functions only.

A row descends region, rack and shard.  At each level every child draws -ln(u) / weight, u being
uniform and made from the key and the child's path; the smallest draw wins, so children are taken
in proportion to their weights.  A draw depends on its own child alone: when weights change, rows
move only into subtrees that gained and out of subtrees that lost.  New shards open a region of
their own, so growing moves rows only into the new shard.

Defined results: a null text has size 1 and the CRC of an empty one; a null key is a key like any
other (all such rows share a shard); equal keys share a shard; repeated rows get a slot each, in an
order of key, CRC and size, so results are the same at every run; an empty table gives no rows;
other columns are ignored; texts of any length only count.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: Rows of a shard are numbered in buckets of about this many.
BUCKET_ROWS = 50_000


@dataclass(frozen=True)
class Tree:
    """regions -> racks -> (shard number, weight)."""

    regions: tuple[tuple[tuple[tuple[int, float], ...], ...], ...]

    @staticmethod
    def even(shards: int, regions: int = 2, racks: int = 2) -> Tree:
        """``shards`` shards of weight 1, spread over regions and racks as evenly as they go."""
        numbers = iter(range(shards))
        out = []
        for r in range(regions):
            own = shards // regions + (r < shards % regions)
            split = [own // racks + (k < own % racks) for k in range(racks)]
            out.append(tuple(tuple((next(numbers), 1.0) for _ in range(n)) for n in split if n))
        return Tree(tuple(x for x in out if x))

    def grown(self, weight: float = 1.0) -> Tree:
        """One more shard, in a new region."""
        return Tree((*self.regions, (((self.size, weight),),)))

    @property
    def size(self) -> int:
        return sum(len(rack) for region in self.regions for rack in region)


def _draw(key: Column, path: str, weight: float) -> Column:
    u = (F.shiftrightunsigned(F.xxhash64(F.lit(path), key), 11).cast("double") + 0.5) / float(1 << 53)
    return -F.log(u) / F.lit(float(weight))


def _least(draws: list[Column]) -> Column:
    """Index of the smallest draw (the first of equal ones)."""
    if len(draws) == 1:
        return F.lit(0)
    return (F.array_position(F.array(*draws), F.least(*draws)) - 1).cast("int")


def _choose(index: Column, values: list[Column]) -> Column:
    out = values[-1]
    for k in range(len(values) - 2, -1, -1):
        out = F.when(index == k, values[k]).otherwise(out)
    return out


def placed(df: DataFrame, key: str, tree: Tree, name: str) -> DataFrame:
    """Add the shard of every row; draws are made only along the chosen path."""
    k, weights = F.col(key), [[sum(w for _, w in rack) for rack in region] for region in tree.regions]
    region = _least([_draw(k, f"{i}", sum(w)) for i, w in enumerate(weights)])
    df = df.withColumn("_region", region)
    rack = _choose(F.col("_region"), [_least([_draw(k, f"{i}/{j}", w) for j, w in enumerate(ws)]) for i, ws in enumerate(weights)])
    df = df.withColumn("_rack", rack)
    leaves = []
    for i, racks in enumerate(tree.regions):
        inner = []
        for j, shards in enumerate(racks):
            index = _least([_draw(k, f"{i}/{j}/{n}", w) for n, w in shards])
            inner.append(F.element_at(F.array(*[F.lit(n) for n, _ in shards]), index + 1))
        leaves.append(_choose(F.col("_rack"), inner))
    return df.withColumn(name, _choose(F.col("_region"), leaves).cast("int")).drop("_region", "_rack")


def numbered(df: DataFrame, shard: str, order: list[str], buckets: int) -> DataFrame:
    """Add ``slot``: gapless from 0 within each shard, without a window over a whole shard.

    Rows fall into buckets by a hash; each bucket is numbered on its own, on from the rows of the
    shard's earlier buckets.  The table of counts has one row a bucket.
    """
    bucket = F.pmod(F.xxhash64(F.lit("slot"), *order), F.lit(buckets)).cast("int")
    df = df.withColumn("_bucket", bucket)
    counts = df.groupBy(shard, "_bucket").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(shard).orderBy("_bucket").rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(shard, "_bucket", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_before"))
    own = Window.partitionBy(shard, "_bucket").orderBy(*order)
    return df.withColumn("_rank", F.row_number().over(own)).join(counts, [shard, "_bucket"]).withColumn("slot", (F.col("_before") + F.col("_rank") - 1).cast("long")).drop("_bucket", "_rank", "_before")


def sharded(docs: DataFrame, shards: int = 16, rows: int | None = None, tree: Tree | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row."""
    tree = tree or Tree.even(shards)
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    df = docs.select(F.col("doc_id"), (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(F.encode(text, "UTF-8")).cast("long").alias("text_crc32"))
    df = placed(placed(df, "doc_id", tree, "shard"), "doc_id", tree.grown(), "grown_shard")
    buckets = max(4, -(-(docs.count() if rows is None else rows) // (tree.size * BUCKET_ROWS)))
    df = numbered(df, "shard", ["doc_id", "text_crc32", "size"], buckets)  # rows that tie here are alike in all columns
    return df.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")
