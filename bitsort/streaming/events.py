"""Streams of events: index blocks per micro-batch, windows, deduplication, running histograms."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from bitsort.operators.build import sparse_words
from bitsort.operators.roworder import order_rows


def event_stream(spark: SparkSession, path: str, schema=None, files_per_trigger: int = 1) -> DataFrame:
    schema = schema or spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def append_index(stream: DataFrame, cols: list[str], path: str, checkpoint: str, w: int = 32):
    """Every micro-batch becomes one block: sorted, numbered, cut into unary words by value.

    The block's folder is named by the batch id and overwritten, so a batch that runs twice counts
    once.  ``compact`` re-sorts blocks, as many small ones cost size.
    """

    def add(batch: DataFrame, batch_id: int) -> None:
        rows = order_rows(batch.select(*[F.col(c).cast("long").alias(c) for c in cols]), "lex", cols).withColumn("block", F.lit(batch_id).cast("long"))
        rows.write.mode("overwrite").parquet(f"{path}/rows/block={batch_id}")
        own = batch.sparkSession.read.parquet(f"{path}/rows/block={batch_id}").withColumn("block", F.lit(batch_id).cast("long"))
        sparse_words(own, cols, w).drop("block").write.mode("overwrite").parquet(f"{path}/words/block={batch_id}")

    return stream.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def compact(spark: SparkSession, path: str, cols: list[str], w: int = 32) -> DataFrame:
    """The words of all blocks sorted together as one."""
    return sparse_words(order_rows(spark.read.parquet(f"{path}/rows").select(*cols), "lex", cols), cols, w)


def windowed_counts(events: DataFrame, kind: str = "tumbling", late: str = "1 hour") -> DataFrame:
    """(start, event_type, n) in tumbling, sliding or session windows; later rows than ``late`` are dropped."""
    timed = events.withWatermark("ts", late) if events.isStreaming else events
    window = {"tumbling": lambda: F.window("ts", "1 hour"), "sliding": lambda: F.window("ts", "1 hour", "30 minutes"), "session": lambda: F.session_window("ts", "10 minutes")}[kind]()
    return timed.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("start"), "event_type", "n")


def deduplicated(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def running_histogram(events: DataFrame, col: str) -> DataFrame:
    """(value, cnt) of everything seen so far, in update mode; state is one count a value."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        seen = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((seen,))
        yield pd.DataFrame({"value": [int(key[0])], "cnt": [int(seen)]})

    keyed = events.select(F.col(col).cast("long").alias("value"))
    return keyed.groupBy("value").applyInPandasWithState(update, "value long, cnt long", "cnt long", "update", "NoTimeout")


def with_codes(events: DataFrame, dictionary: DataFrame, col: str) -> DataFrame:
    """Stream-static lookup; values the dictionary lacks get a null rank until the next rebuild."""
    d = dictionary.select(F.col("value").alias("_v"), "rank")
    return events.join(d, F.col(col).cast("long") == F.col("_v"), "left").drop("_v")
