"""Baseline schedules: one job after another (pipeline, sharded), and uniform filling."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.functions.tokens import pad_to
from adapterlab.operators.numbering import rank_within


def fixed_microbatches(batches: DataFrame, size: int = 4, multiple: int = 64) -> DataFrame:
    """`size` samples of one adapter's batch each: (adapter_id, gb, mb, n, tokens, cost_tokens).

    batches: what `assign_global_batches` gives.
    """
    first = batches.groupBy("adapter_id", "gb").agg(F.min("rn").alias("lo"))
    mb = F.floor((F.col("rn") - F.col("lo")) / size).cast("bigint")
    rows = batches.join(first, ["adapter_id", "gb"]).groupBy("adapter_id", "gb", mb.alias("mb"))
    return rows.agg(F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("tokens")).withColumn("cost_tokens", pad_to(F.col("tokens"), multiple))


def baseline_pipeline(micro: DataFrame) -> DataFrame:
    """Jobs one after another, batches and microbatches in order: adds `pos`."""
    return rank_within(micro, [], ["adapter_id", "gb", "mb"], "pos")


def baseline_sharded(micro: DataFrame, ranks: int = 4) -> DataFrame:
    """Each step takes `ranks` microbatches of one batch: (adapter_id, gb, step, step_tokens, lost_tokens)."""
    step = F.floor(F.col("mb") / ranks).cast("bigint")
    return micro.groupBy("adapter_id", "gb", step.alias("step")).agg(F.max("cost_tokens").alias("step_tokens"), (F.max("cost_tokens") * ranks - F.sum("cost_tokens")).alias("lost_tokens"))


def baseline_uniform_fill(micro: DataFrame) -> DataFrame:
    """Adapters take turns with equal numbers of samples, blind to their lengths: adds `pos`."""
    return rank_within(micro, [], ["gb", "mb", "adapter_id"], "pos")


def as_runs(micro: DataFrame, run_id: str, stages: int) -> DataFrame:
    """Microbatches of one adapter each, in the form that the simulator takes."""
    key = F.array(F.struct(F.col("adapter_id"), F.col("gb").alias("batch")))
    return micro.select(F.lit(run_id).alias("run_id"), "pos", "cost_tokens", F.col("tokens").alias("real_tokens"), key.alias("keys"), F.lit(stages).alias("stages"))
