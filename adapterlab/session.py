"""Session helpers: a session for tests, and checkpoints that survive lost executors."""

from __future__ import annotations

import re
import tempfile
from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from typing import TypeVar

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

T = TypeVar("T")


def local_session(cores: int = 4, partitions: int = 8) -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", partitions)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )


def checkpointed(df: DataFrame) -> DataFrame:
    """Cuts the lineage in the folder of spark.checkpoint.dir; our own folder only where none is set (tests)."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share; one of our own in local mode alone, elsewhere its absence is an error."""
    sc = spark.sparkContext
    if folder := spark.conf.get("spark.checkpoint.dir", None):
        return folder
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="adapterlab-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def broadcast_within(df: DataFrame, rows: int = 1_000_000) -> DataFrame:
    """A broadcast hint if the frame has at most `rows` rows (a count from file footers, for a plain scan); else none."""
    return F.broadcast(df) if df.count() <= rows else df


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def spread(df: DataFrame, *keys: str) -> DataFrame:
    """Dealt by the keys to a number of tasks that stays as it is.

    Few bytes may be much work: packing, merging and simulating would else end up in one task, as an exchange by size is coalesced.
    """
    spark = df.sparkSession
    return df.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), 4 * spark.sparkContext.defaultParallelism), *keys)


def side_by_side(spark: SparkSession, todo: list[Callable[[], T]], at_once: int = 6) -> list[T]:
    """What the functions give, in order; the Spark jobs of several run at once, as short ones leave most of a cluster idle."""
    with ThreadPoolExecutor(max(1, min(at_once, len(todo)))) as pool:
        return [x.result() for x in [pool.submit(inheritable_thread_target(spark)(f)) for f in todo]]
