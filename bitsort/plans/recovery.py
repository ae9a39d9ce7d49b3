"""Recovery points: tables that later steps read instead of recomputing a shuffle."""

from __future__ import annotations

import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession


#: Independent jobs on small tables are submitted side by side; their fixed costs overlap.
AT_ONCE = 4
#: Above so many rows the fixed costs do not count, and tables of one job at a time fill less disk.
SIDE_BY_SIDE_ROWS = 1_000_000
#: Shuffle files go when the action that made them has ended.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_lock, _inside, _tables = threading.Lock(), {}, threading.local()


@contextmanager
def tidy(spark: SparkSession) -> Iterator[None]:
    """Actions inside leave no shuffle files.  The session's own setting comes back with the last one."""
    with _lock:
        depth, own = _inside.get(spark, (0, None))
        own = spark.conf.get(CLEANUP, "false") if not depth else own
        _inside[spark] = (depth + 1, own)
        spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        with _lock:
            depth, own = _inside[spark]
            if depth == 1:
                spark.conf.set(CLEANUP, own)
                del _inside[spark]
            else:
                _inside[spark] = (depth - 1, own)


@contextmanager
def passing(spark: SparkSession) -> Iterator[None]:
    """Tables that this thread stores inside are deleted at the end: what is made from them must have been collected or stored before."""
    before, _tables.paths = getattr(_tables, "paths", None), []
    try:
        yield
    finally:
        made, _tables.paths = _tables.paths, before
        jvm, conf = spark._jvm, spark.sparkContext._jsc.hadoopConfiguration()
        for path in made:
            at = jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(conf).delete(at, True)


def together(spark: SparkSession, tasks: list[Callable[[], DataFrame]], rows: int = 0) -> DataFrame:
    """The rows of many small results, each of its own jobs, in the order of the tasks.

    Every result is a summary of a few rows; these reach the driver, their inputs do not.  ``rows``:
    how many each task works on; with many there is one task at a time.
    """
    ensure_folder(spark)

    def run(task: Callable[[], DataFrame]):
        with passing(spark), tidy(spark):
            df = task()
            return df.schema, df.collect()

    with ThreadPoolExecutor(AT_ONCE if rows <= SIDE_BY_SIDE_ROWS else 1) as pool:
        done = list(pool.map(inheritable_thread_target(spark)(run), tasks))
    return spark.createDataFrame([r for _, rows in done for r in rows], done[0][0])


def ensure_folder(spark: SparkSession) -> None:
    """Set the checkpoint folder once."""
    if not spark.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder and not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(folder or tempfile.mkdtemp(prefix="bitsort-"))


def checkpointed(df: DataFrame) -> DataFrame:
    """checkpoint() into spark.checkpoint.dir; a folder of its own only where that is unset and Spark is local."""
    ensure_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """The same rows from Parquet files in the shared folder: a compressed recovery point.

    A checkpoint keeps rows of 8 bytes a column, uncompressed; encoded columns take a small part of that.
    """
    path = stored_at(df)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def stored_at(df: DataFrame) -> str:
    """Write ``df`` as ``stored`` does, one file a partition; where it lies."""
    spark = df.sparkSession
    ensure_folder(spark)
    path = shared_folder(spark)
    if getattr(_tables, "paths", None) is not None:
        _tables.paths.append(path)
    with tidy(spark):
        df.write.parquet(path)
    return path


def stored_alone(spark: SparkSession, make: Callable[[], DataFrame]) -> DataFrame:
    """The rows of ``make()`` as ``stored`` keeps them; the tables stored to make them are deleted."""
    ensure_folder(spark)
    path = shared_folder(spark)
    with passing(spark), tidy(spark):
        df = make()
        df.write.parquet(path)
    if getattr(_tables, "paths", None) is not None:
        _tables.paths.append(path)
    return spark.read.schema(df.schema).parquet(path)


def shared_folder(spark) -> str:
    """A new folder that the driver and all executors see."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        known = spark.sparkContext._jsc.sc().getCheckpointDir()
        if known.isDefined():
            folder = known.get()
        elif spark.sparkContext.master.startswith("local"):
            folder = tempfile.mkdtemp(prefix="bitsort-")
        else:
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return f"{folder.rstrip('/')}/{uuid.uuid4().hex}"


def partitions(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions", "200"))
