"""Sharded data parallel, data-parallel replicas, single device, and the ideal run, as aggregates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.errors import Unsupported


def simulate_sharded(runs: DataFrame, ranks: int = 4, backward: int = 2, comm: int = 0, overlapped: bool = True) -> DataFrame:
    """Ranks take consecutive microbatches and meet before each layer: (run_id, makespan, idle_per_mille, tokens).

    runs: (run_id, pos, tokens). A step lasts as long as its longest rank, or its communication if that is longer.
    """
    compute = F.col("tokens") * (1 + backward)
    step = runs.groupBy("run_id", F.floor(F.col("pos") / ranks).cast("bigint").alias("step")).agg(F.max(compute).alias("slowest"), F.sum(compute).alias("work"), F.sum("tokens").alias("tokens"))
    took = F.greatest(F.col("slowest"), F.lit(comm).cast("bigint")) if overlapped else F.col("slowest") + comm
    return step.withColumn("took", took).groupBy("run_id").agg(
        F.sum("took").alias("makespan"), F.expr(f"({ranks} * sum(slowest) - sum(work)) * 1000 div ({ranks} * sum(slowest))").alias("idle_per_mille"), F.sum("tokens").alias("tokens")
    )


def simulate_single(runs: DataFrame, backward: int = 2) -> DataFrame:
    """One device: no imbalance, no bubble."""
    return runs.groupBy("run_id").agg((F.sum("tokens") * (1 + backward)).alias("makespan"), F.sum("tokens").alias("tokens"))


def simulate_dp(runs: DataFrame, degree: int, stages: int, backward: int = 2) -> DataFrame:
    """Replicas of a pipeline meet after each batch; a step lasts as long as its slowest replica, plus its fill."""
    work = runs.groupBy("run_id", "gb", F.pmod("pos", F.lit(degree)).alias("replica")).agg(F.sum("tokens").alias("w"), F.max("tokens").alias("longest"))
    step = work.groupBy("run_id", "gb").agg(F.max(F.col("w") + (stages - 1) * F.col("longest")).alias("took"), F.sum("w").alias("tokens"))
    return step.groupBy("run_id").agg((F.sum("took") * (1 + backward)).alias("makespan"), F.sum("tokens").alias("tokens"))


def ideal_run(lengths: DataFrame, global_batches: list[int], stages: int = 4, ranks: int = 4, comm: int = 2000) -> DataFrame:
    """Every sample as long as the mean: tokens per 1000 time units by batch size, pipeline and sharded.

    One sample per microbatch. Sharded: each step also gathers the layers, which takes at least `comm`.
    """
    mean = lengths.agg(F.expr("sum(tok_len) div count(1)").alias("mean"))
    sizes = lengths.sparkSession.createDataFrame([(g,) for g in global_batches], "global_batch int")
    both = sizes.join(F.broadcast(mean))  # a row per batch size
    tokens = F.col("global_batch") * F.col("mean")
    pipe = (F.col("global_batch") + stages - 1) * F.col("mean") * 3
    steps = F.ceil(F.col("global_batch") / ranks)
    shard = F.greatest(steps * F.col("mean") * 3, F.lit(comm)) + comm
    return both.select(
        "global_batch", F.floor(tokens * stages * 1000 / pipe).cast("bigint").alias("pipeline_rate"), F.floor(tokens * 1000 / shard).cast("bigint").alias("sharded_rate")
    )


def simulate_tensor_parallel(*_args, **_kwargs):
    raise Unsupported("tensor parallelism is described by the method but was not evaluated")
