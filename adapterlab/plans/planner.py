"""The method from samples to schedule, with switches for its variants."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from adapterlab.functions.tokens import pad_to
from adapterlab.operators.grouping import adapter_stats, assign_global_batches, group_adapters
from adapterlab.operators.packing import pack_batches
from adapterlab.operators.schedule import build_schedule
from adapterlab.samples import Adapter, adapters_frame, oversize, pieces, token_samples
from adapterlab.simulate.pipeline import PipeConfig, simulate_pipeline


@dataclass(frozen=True)
class Options:
    stages: int = 4
    capacity: int = 2048
    multiple: int = 64
    nodes: int = 400
    exact: bool = True
    merge: bool = True
    guard: bool = True
    scope: str = "interleaved"
    policy: str = "pair"
    segment: int | None = 64
    gap: int | None = None
    on_oversize: str = "split"

    def with_(self, **changes) -> Options:
        return replace(self, **changes)


def global_batches(spark: SparkSession, samples: DataFrame, adapters: list[Adapter], options: Options = Options()) -> DataFrame:
    fitting, _ = oversize(samples, options.capacity, options.on_oversize)
    groups = group_adapters(adapter_stats(samples), options.policy)
    batches = assign_global_batches(fitting, adapters_frame(spark, adapters), groups)
    return pieces(batches, options.capacity) if options.on_oversize == "split" else batches


def pack(batches: DataFrame, options: Options = Options()) -> DataFrame:
    return pack_batches(batches, options.capacity, options.multiple, nodes=options.nodes, exact=options.exact)


def schedule_batches(batches: DataFrame, options: Options = Options()) -> DataFrame:
    return schedule_packed(pack(batches, options), options)


def schedule_packed(packed: DataFrame, options: Options = Options()) -> DataFrame:
    return build_schedule(packed, options.capacity, options.multiple, options.stages, options.gap, options.merge, options.scope, options.segment, options.guard)


def plan(spark: SparkSession, samples: DataFrame, adapters: list[Adapter], options: Options = Options()) -> DataFrame:
    """Schedule of all samples: statistics, groups, global batches, packing, merge, repair, positions."""
    return schedule_batches(global_batches(spark, samples, adapters, options), options)


def plan_tables(spark: SparkSession, sf_dir: str, adapters: list[Adapter], options: Options = Options()) -> DataFrame:
    return plan(spark, token_samples(spark, sf_dir, adapters), adapters, options)


def as_runs(schedule: DataFrame, run_id: str, stages: int, multiple: int = 64, by_segment: bool = False) -> DataFrame:
    """A schedule in the form that the simulator takes; by_segment: a run for each segment."""
    name = F.concat_ws("/", F.lit(run_id), F.col("segment").cast("string")) if by_segment else F.lit(run_id)
    rows = schedule.withColumn("run_id", name)
    per = rows.groupBy("run_id", "pos", "adapter_id", "batch").agg(F.sum("tok_len").alias("t"))
    adapter = rows.groupBy("run_id", "pos", "adapter_id").agg(F.sum("tok_len").alias("t"))
    cost = adapter.groupBy("run_id", "pos").agg(F.sum(pad_to(F.col("t"), multiple)).alias("cost_tokens"), F.sum("t").alias("real_tokens"))
    keys = per.groupBy("run_id", "pos").agg(F.collect_list(F.when(F.col("adapter_id").isNotNull(), F.struct("adapter_id", "batch"))).alias("keys"))
    return cost.join(keys, ["run_id", "pos"]).select("run_id", "pos", "cost_tokens", "real_tokens", "keys", F.lit(stages).alias("stages"))


def simulate_schedule(schedule: DataFrame, stages: int, config: PipeConfig = PipeConfig(), multiple: int = 64) -> DataFrame:
    """(makespan, busy, bubble, microbatches, tokens) of a schedule of any length: segments are simulated side by side.

    The pipeline is taken to drain at each seam, so the makespan is an upper bound; one segment gives the exact value.
    No task holds more than one segment.
    """
    each = simulate_pipeline(as_runs(schedule, "s", stages, multiple, by_segment=True), config)
    total = each.agg(*[F.sum(c).alias(c) for c in ("makespan", "busy", "microbatches", "tokens")])
    return total.select("makespan", "busy", F.round(1 - F.col("busy") / (stages * F.col("makespan")), 6).alias("bubble"), "microbatches", "tokens")
