"""Helpers shared by the training-data operators."""

from __future__ import annotations

import ctypes
import gc
import re
import tempfile
import uuid
import zlib
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from itertools import count

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

ASCII_UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """The cluster's shared folder if it names one, else, in local mode alone, a folder of our own."""
    sc = spark.sparkContext
    if spark.conf.get("spark.checkpoint.dir", None) or not sc._jsc.sc().getCheckpointDir().isEmpty():
        return
    if not re.fullmatch(r"local(\[.*\])?", sc.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    sc.setCheckpointDir(tempfile.mkdtemp(prefix="adapterlab-checkpoint-"))


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new path in the checkpoint folder, for a table of our own."""
    ensure_checkpoint_dir(spark)
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir"))
    return f"{sc._jsc.sc().getCheckpointDir().get()}/{name}-{uuid.uuid4().hex}"


@contextmanager
def tables(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Writes frames as Parquet, far smaller than a checkpoint's rows, and reads them again; all go at the end of the block."""
    folder = shared_folder(spark, "tables")
    n = count()

    def written(df: DataFrame) -> DataFrame:
        path = f"{folder}/{next(n)}"
        df.write.parquet(path)
        return spark.read.schema(df.schema).parquet(path)

    try:
        yield written
    finally:
        path = spark._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def broadcast_within(df: DataFrame, rows: int = 300_000) -> DataFrame:
    """A broadcast hint if the frame has at most `rows` rows, narrow ones; else it is joined by a shuffle."""
    return F.broadcast(df) if df.count() <= rows else df


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage through a replicated, shared folder; survives lost executors."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def let_go(spark: SparkSession) -> None:
    """Shuffles and checkpoints that nothing refers to go when the driver collects garbage, which it seldom does where executors do the work."""
    gc.collect()
    spark._jvm.System.gc()


def ascii_lower(c: Column) -> Column:
    return F.translate(c, ASCII_UPPER, ASCII_UPPER.lower())


def is_held_out(doc_id: int | None) -> bool:
    """Python twin of `held_out`: crc32 of the decimal id, remainder 0 of 5."""
    return doc_id is None or zlib.crc32(str(doc_id).encode()) % 5 == 0


def held_out(doc_id: Column) -> Column:
    """Rows that never train; a null id counts as held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(True))


def training_ids(labels: DataFrame, label: str, limit: int) -> DataFrame:
    """At most `limit` labelled ids per class, never held-out ones, in the order of a hash of the id.

    A bounded sample (the bound is the parameter), so that the result may be broadcast. Conflicting labels
    of one id count as the larger; null ids and null labels are left out.
    """
    rows = (
        labels.where(F.col("doc_id").isNotNull() & F.col(label).isNotNull() & ~held_out(F.col("doc_id")))
        .groupBy("doc_id")
        .agg(F.max(label).cast("int").alias("y"))
        .withColumn("h", F.xxhash64("doc_id"))
    )
    parts = [rows.where(F.col("y") == y).orderBy("h", "doc_id").limit(limit) for y in (0, 1)]
    return parts[0].unionByName(parts[1]).select(F.col("doc_id").alias("train_id"), "y")


def texts(column, step: int = 256):
    """The strings of an Arrow column one after the other (null: empty), few of them in memory as Python objects."""
    for i in range(0, len(column), step):
        for t in column.slice(i, step).to_pylist():
            yield t or ""


def tidied(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """The same map over batches; a worker, which outlives its tasks, gives freed memory back at the end of each."""

    def wrapped(batches: Iterator) -> Iterator:
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of the GNU library only
            if trim:
                trim(0)

    return wrapped


def with_small_batches(df: DataFrame) -> DataFrame:
    """The same frame; its session sends texts to Python in Arrow batches of 8 MB at most, however long they are."""
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", "8m")
    return df
