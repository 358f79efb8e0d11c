"""Ordinals and running totals over ordered keys without a one-partition window.

Rows are cut into key ranges, numbered inside each range, and shifted by what lies before: a table with one row
for each key and range.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from adapterlab.session import checkpointed, shuffle_partitions


def running(df: DataFrame, keys: list[str], order: list[str], value: str | None = None, name: str = "rn") -> DataFrame:
    """Adds `name`: how much lies before a row within its keys (rows, or the sum of `value`), in `order`.

    `order` must tell the rows of a key apart. Bounds of ranges are sampled, so the ranges are written out first.
    """
    amount = F.lit(1).cast("bigint") if value is None else F.col(value).cast("bigint")
    ranged = df.repartitionByRange(shuffle_partitions(df.sparkSession), *keys, *order)
    ranged = checkpointed(ranged.withColumn("_range", F.spark_partition_id()))
    local = Window.partitionBy("_range", *keys).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    inside = ranged.withColumn("_before", F.coalesce(F.sum(amount).over(local), F.lit(0)))
    parts = ranged.groupBy("_range", *keys).agg(F.sum(amount).alias("_n"))
    ahead = Window.partitionBy(*keys).orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)
    parts = parts.select("_range", *keys, F.coalesce(F.sum("_n").over(ahead), F.lit(0)).alias("_base"))
    return inside.join(parts, ["_range", *keys]).withColumn(name, F.col("_before") + F.col("_base")).drop("_range", "_before", "_base")


def rank_within(df: DataFrame, keys: list[str], order: list[str], name: str = "rn") -> DataFrame:
    """Ordinals from 0."""
    return running(df, keys, order, None, name)
