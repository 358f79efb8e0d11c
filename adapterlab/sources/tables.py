"""Base tables as DataFrames, views of them, and sinks for schedules."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_views(spark: SparkSession, sf_dir: str, prefix: str = "") -> None:
    for name in NAMES:
        load(spark, sf_dir, name).createOrReplaceTempView(f"{prefix}{name}")


def write_schedule(schedule: DataFrame, path: str) -> None:
    """Parquet by segment, rows in schedule order inside each file."""
    schedule.repartition("segment").sortWithinPartitions("segment", "pos").write.mode("overwrite").partitionBy("segment").parquet(path)


def write_manifest(items: DataFrame, path: str) -> None:
    """JSON lines, one microbatch each, for a trainer outside."""
    item = F.struct("adapter_id", "sample_id", "tok_len")
    rows = items.groupBy("group_id", "gb", "bin").agg(F.array_sort(F.collect_list(item)).alias("items"))  # a bin is bounded by its capacity
    rows.select(F.to_json(F.struct("group_id", "gb", "bin", "items")).alias("value")).write.mode("overwrite").text(path)
