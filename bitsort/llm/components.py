"""Connected components of a table of links, by contraction."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from bitsort.llm.stages import checkpointed


#: Tables of at most so many links are settled by one task; larger ones are contracted until they are as small.
ONE_TASK = 300_000


def _settled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(node, smallest node of its component) of all links of a task."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        while (up := parent.setdefault(x, x)) != x:
            parent[x] = x = parent[up]
        return x

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(a), root(b)
            if a != b:
                parent[max(a, b)] = min(a, b)
    nodes = list(parent)
    yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([root(x) for x in nodes], pa.int64())], ["node", "label"])


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, label) for every node of ``links``; label is the smallest node of its component.

    Each round maps every node to the first of it and its neighbours, and that to its own first, in
    an order by hash, so that no chain of rising numbers is slow; it rewrites the links and drops
    loops and repeats, so the table shrinks fast; once it has at most ONE_TASK links, one
    task settles them.  The maps are chained afterwards.  All of it stays in tables; each round ends
    in a checkpoint.
    """
    edges = links.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b")).filter("a <> b")
    edges = checkpointed(edges.distinct())
    maps: list[DataFrame] = []
    while edges.count() > ONE_TASK:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        rank = lambda c: F.struct(F.xxhash64(c).alias("h"), F.col(c).alias("n"))
        parent = checkpointed(both.groupBy("a").agg(F.min(rank("b")).alias("m")).select("a", F.least("m", rank("a"))["n"].alias("p")))
        # one pointer jump; a node's parent has a row of its own
        grand = parent.select(F.col("a").alias("p"), F.col("p").alias("g"))
        parent = checkpointed(parent.join(grand, "p").select("a", F.col("g").alias("p")))
        maps.append(parent)
        edges = edges.join(parent.withColumnRenamed("p", "pa"), "a").join(parent.select(F.col("a").alias("b"), F.col("p").alias("pb")), "b")
        edges = checkpointed(edges.select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).filter("a <> b").distinct())
    last = edges.coalesce(1).mapInArrow(_settled, "node long, label long")
    if not maps:
        return last
    maps.append(last.withColumnsRenamed({"node": "a", "label": "p"}))
    out = maps[0].select(F.col("a").alias("node"), F.col("p").alias("label"))
    for parent in maps[1:]:
        step = parent.select(F.col("a").alias("label"), F.col("p").alias("_next"))
        out = out.join(step, "label", "left").select("node", F.coalesce("_next", "label").alias("label"))
    least = out.groupBy("label").agg(F.least(F.min("node"), F.col("label")).alias("_least"))
    return out.join(least, "label").select("node", F.col("_least").alias("label"))
