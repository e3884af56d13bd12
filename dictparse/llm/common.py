"""Helpers that the corpus operators share: reading, Arrow row mapping, cutting lineage."""

from __future__ import annotations

import atexit
import ctypes
import gc
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Text that one Arrow batch may hold; a single longer text makes a batch of its own.
BATCH_BYTES = 4 << 20


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One table of a data folder; the path may be any that Spark's own readers open."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{table}.parquet")


def bound_batches(spark: SparkSession) -> None:
    """Arrow batches are limited by bytes, so rows with very long texts don't add up in a Python worker."""
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def spread(df: DataFrame) -> DataFrame:
    """Deals the rows out anew if the scan has fewer tasks than the cluster has cores (one file with one row group)."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() * 2 <= cores else df


def lean(make: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """The same function, giving its freed memory back to the system at its end: a worker then waits for its next task without it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from make(batches)
        give_back()

    return run


def give_back() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def map_batches(df: DataFrame, make: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """mapInArrow behind the byte bound and the spread."""
    bound_batches(df.sparkSession)
    return spread(df).mapInArrow(lean(make), schema)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one beside the warehouse, which they share too, where none is set."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/dictparse-checkpoints")
    return sc.getCheckpointDir()


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session is gone; the cluster's own cleaning takes over
        pass


def written(df: DataFrame, name: str, codec: str = "zstd", by: list[str] | None = None) -> DataFrame:
    """The rows as a Parquet table in the shared folder, read back: lineage ends there, and a lost executor loses none of it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    w = df.write.option("compression", codec)
    (w.partitionBy(*by) if by else w).parquet(path)
    atexit.register(_delete, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame, name: str) -> str:
    """A column name like the given one that the table doesn't have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def skewed_join(rows: DataFrame, small: DataFrame, *keys: str, how: str = "left", share: int = 1000) -> DataFrame:
    """Joins a table that has each key once, where one key may hold a large part of the rows.

    A key that holds more than 1/share of all rows is hot; there are fewer than `share` of those, so what belongs to them is sent to
    all tasks, and only the other rows are shuffled.
    """
    on = [*keys]
    counts = rows.groupBy(*on).agg(F.count(F.lit(1)).alias("held")).where(F.col(on[0]).isNotNull())
    total = rows.count()
    hot = written(small.join(counts.where(F.col("held") > max(total // share, 64)).select(*on), on), "hot-keys")
    if hot.isEmpty():
        return rows.join(small, on, how)
    cold = rows.join(F.broadcast(hot.select(*on)), on, "left_anti").join(small, on, how)
    return rows.join(F.broadcast(hot), on).unionByName(cold)


def utf8_bytes(text: Column) -> Column:
    return F.octet_length(F.coalesce(text, F.lit("")))


def texts_of(batch: pa.RecordBatch, column: str) -> list[bytes]:
    """A string column's values as UTF-8; null counts as empty."""
    a = batch.column(column)
    return [x if x is not None else b"" for x in a.cast(pa.binary()).to_pylist()]
