"""Adapter statistics, grouping policies, global batches, and the spacing rule."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from adapterlab.operators.numbering import rank_within


def adapter_stats(samples: DataFrame) -> DataFrame:
    """(adapter_id, n_samples, tokens, mean_len) with partial aggregation."""
    return samples.groupBy("adapter_id").agg(F.count(F.lit(1)).alias("n_samples"), F.sum("tok_len").alias("tokens"), F.round(F.avg("tok_len"), 6).alias("mean_len"))


def head_tail_groups(stats: DataFrame) -> DataFrame:
    """The i-th shortest adapter shares a group with the i-th longest; an odd one stays alone."""
    by_mean = Window.orderBy("mean_len", "adapter_id")  # one row per adapter
    everything = Window.partitionBy(F.lit(0))
    ranked = stats.withColumn("len_rank", F.row_number().over(by_mean)).withColumn("n", F.count(F.lit(1)).over(everything))
    group = F.least(F.col("len_rank"), F.col("n") + 1 - F.col("len_rank")) - 1
    return ranked.select("adapter_id", "mean_len", "len_rank", group.cast("int").alias("group_id"))


def group_adapters(stats: DataFrame, policy: str = "pair", k: int = 2) -> DataFrame:
    """pair: head-tail pairs; singleton: each adapter alone; single: all together; k_groups: pairs dealt to k groups."""
    pairs = head_tail_groups(stats)
    if policy == "pair":
        return pairs
    if policy == "singleton":
        return pairs.withColumn("group_id", (F.col("len_rank") - 1).cast("int"))
    if policy == "single":
        return pairs.withColumn("group_id", F.lit(0))
    if policy == "k_groups":
        return pairs.withColumn("group_id", (F.col("group_id") % k).cast("int"))
    raise ValueError(f"unknown policy {policy}")


def assign_global_batches(samples: DataFrame, adapters: DataFrame, groups: DataFrame, drop_last: bool = False) -> DataFrame:
    """(group_id, gb, adapter_id, sample_id, tok_len, rn): slices of each adapter's order, of its own batch size.

    Samples that have `rn` keep it; else they are ranked.
    """
    dim = adapters.select("adapter_id", "global_batch_size").join(groups.select("adapter_id", "group_id"), "adapter_id")  # one row per adapter
    ranked = samples if "rn" in samples.columns else rank_within(samples, ["adapter_id"], ["order_key", "sample_id"])
    rows = ranked.join(F.broadcast(dim), "adapter_id")
    rows = rows.select("group_id", F.floor(F.col("rn") / F.col("global_batch_size")).cast("bigint").alias("gb"), "adapter_id", "sample_id", "tok_len", F.col("rn").cast("bigint").alias("rn"), "global_batch_size")
    if drop_last:
        full = rows.groupBy("adapter_id", "gb").agg(F.count(F.lit(1)).alias("n"), F.max("global_batch_size").alias("g")).where("n = g").select("adapter_id", "gb")
        rows = rows.join(full, ["adapter_id", "gb"], "left_semi")
    return rows.drop("global_batch_size")


def spacing_violations(positions: DataFrame, gap: int) -> DataFrame:
    """Where an adapter's batch starts fewer than `gap` positions after its previous batch ended.

    positions: (adapter_id, gb, pos), one row per adapter and microbatch.
    """
    span = positions.groupBy("adapter_id", "gb").agg(F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"))
    before = span.select("adapter_id", (F.col("gb") + 1).alias("gb"), F.col("last_pos").alias("previous_last"))
    both = span.join(before, ["adapter_id", "gb"])
    return both.where(F.col("first_pos") - F.col("previous_last") < gap).select("adapter_id", "gb", "first_pos", "previous_last")
