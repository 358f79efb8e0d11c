"""Layout profiling, the tuning loop, and scaling over devices. Loops run over configurations, never over data."""

from __future__ import annotations

from dataclasses import replace
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from adapterlab.cost.ledger import kernel_factors
from adapterlab.operators.baselines import as_runs as baseline_runs
from adapterlab.operators.baselines import baseline_pipeline, baseline_uniform_fill, fixed_microbatches
from adapterlab.operators.grouping import adapter_stats
from adapterlab.operators.numbering import rank_within, running
from adapterlab.plans.planner import Options, as_runs, global_batches, schedule_batches
from adapterlab.samples import Adapter
from adapterlab.session import checkpointed, side_by_side
from adapterlab.simulate.pipeline import PipeConfig, simulate_pipeline
from adapterlab.simulate.sharded import simulate_single

# kind, degree, largest capacity its memory allows, fixed cost of a microbatch
LAYOUTS = [("single", 1, 2048, 0), ("sharded", 4, 4096, 400), ("pipeline", 4, 8192, 150), ("pipeline", 2, 4096, 150)]


def profile_layouts(spark: SparkSession, capacities: list[int] = (1024, 2048, 4096, 8192), layouts=LAYOUTS, microbatches: int = 32, backward: int = 2) -> DataFrame:
    """Benchmarks layouts on equal microbatches that fill each capacity: (kind, degree, capacity, feasible, rate)."""
    grid = spark.createDataFrame([(*x, c) for x in layouts for c in capacities], "kind string, degree int, limit int, fixed int, capacity int")
    step = (F.col("capacity") + F.col("fixed")) * (1 + backward)
    span = F.when(F.col("kind") == "pipeline", (microbatches + F.col("degree") - 1) * step).when(F.col("kind") == "sharded", F.ceil(F.lit(microbatches) / F.col("degree")) * (step + 1600) * F.col("degree")).otherwise(microbatches * step)
    scaled = F.when(F.col("kind") == "single", F.lit(1)).otherwise(F.col("degree"))
    rate = F.floor(F.lit(microbatches) * F.col("capacity") * scaled * 1000 / span).cast("bigint")
    return grid.select("kind", "degree", "capacity", (F.col("capacity") <= F.col("limit")).alias("feasible"), rate.alias("rate"))


def simulate_layouts(spark: SparkSession, capacities: list[int] = (1024, 2048, 4096, 8192), layouts=LAYOUTS, microbatches: int = 32, backward: int = 2) -> DataFrame:
    """The same by running them: pipelines event by event, the others step by step."""
    grid = spark.createDataFrame([(f"{k}/{d}/{c}", k, d, lim, f, c) for k, d, lim, f in layouts for c in capacities], "run_id string, kind string, degree int, lim int, fixed int, capacity int")
    key = F.array(F.struct(F.lit("a").alias("adapter_id"), F.lit(0).cast("bigint").alias("batch")))
    each = grid.withColumn("pos", F.explode(F.sequence(F.lit(0), F.lit(microbatches - 1)))).withColumn("tokens", F.col("capacity") + F.col("fixed"))
    pipes = each.where("kind = 'pipeline'").select("run_id", "pos", F.col("tokens").alias("cost_tokens"), F.col("tokens").alias("real_tokens"), key.alias("keys"), F.col("degree").alias("stages"))
    spans = [simulate_pipeline(pipes, PipeConfig(backward=float(backward))).select("run_id", "makespan")]
    for r in {(k, d) for k, d, *_ in layouts if k != "pipeline"}:
        some = each.where((F.col("kind") == r[0]) & (F.col("degree") == r[1]))
        if r[0] == "single":
            spans.append(simulate_single(some, backward).select("run_id", F.col("makespan").cast("double")))
        else:  # each rank runs all layers, so a step is as long as `degree` stages; gathering the layers comes on top
            step = some.groupBy("run_id", F.floor(F.col("pos") / r[1]).alias("step")).agg(((F.max("tokens") * (1 + backward) + 1600) * r[1]).alias("took"))
            spans.append(step.groupBy("run_id").agg(F.sum("took").cast("double").alias("makespan")))
    scaled = F.when(F.col("kind") == "single", F.lit(1)).otherwise(F.col("degree"))
    done = grid.join(F.broadcast(reduce(DataFrame.unionByName, spans)), "run_id")
    return done.select("kind", "degree", "capacity", (F.col("capacity") <= F.col("lim")).alias("feasible"), F.floor(F.lit(microbatches) * F.col("capacity") * scaled * 1000 / F.col("makespan")).cast("bigint").alias("rate"))


def profile_batches(batches: DataFrame, capacities: list[int] = (1024, 2048, 4096, 8192), layouts=LAYOUTS, backward: int = 2) -> DataFrame:
    """The profile over given global batches (tokens): each as few microbatches as hold it, every one as long as a full one."""
    grid = batches.sparkSession.createDataFrame([(*x, c) for x in layouts for c in capacities], "kind string, degree int, limit int, fixed int, capacity int")
    step, n = f"(capacity + fixed) * {1 + backward}L", "((tokens + capacity - 1) div capacity)"
    span = F.expr(f"CASE kind WHEN 'pipeline' THEN ({n} + degree - 1) * {step} WHEN 'sharded' THEN (({n} + degree - 1) div degree) * ({step} + 1600) * degree ELSE {n} * {step} END")
    total = batches.crossJoin(F.broadcast(grid)).groupBy("kind", "degree", "capacity", "limit").agg(F.sum("tokens").alias("tokens"), F.sum(span).alias("span"))
    rate = F.expr("tokens * CASE WHEN kind = 'single' THEN 1 ELSE degree END * 1000 div span")
    return total.select("kind", "degree", "capacity", (F.col("capacity") <= F.col("limit")).alias("feasible"), rate.alias("rate"))


def best_layout(profile: DataFrame) -> DataFrame:
    order = F.struct("rate", "capacity", "kind", "degree")
    return profile.where("feasible").agg(F.max_by(F.struct("kind", "degree", "capacity", "rate"), order).alias("b")).select("b.*")


def candidates(base: Options, capacities: list[int], policies: list[str], gaps: list[int | None]) -> list[Options]:
    return [base.with_(capacity=c, policy=p, gap=g) for c in capacities for p in policies for g in gaps]


def evaluate(spark: SparkSession, samples: DataFrame, adapters: list[Adapter], options: list[Options], config: PipeConfig = PipeConfig()) -> DataFrame:
    """Simulated runs of all candidates: (run_id, makespan, busy, bubble, microbatches, tokens, rate)."""
    samples = checkpointed(samples)
    parts = []
    for o in options:
        schedule = schedule_batches(global_batches(spark, samples, adapters, o), o)
        parts.append(as_runs(schedule, f"{o.policy}/{o.capacity}/{'S-1' if o.gap is None else o.gap}", o.stages, o.multiple))
    runs = reduce(DataFrame.unionByName, parts)
    done = simulate_pipeline(runs, config)
    return done.withColumn("rate", F.round(F.col("tokens") * 1000 / F.col("makespan"), 6))


def tune(spark: SparkSession, samples: DataFrame, adapters: list[Adapter], base: Options = Options(), capacities: list[int] = (2048, 4096), policies: list[str] = ("pair", "singleton", "single"), gaps=(None, 4), rounds: int = 2) -> tuple[str, DataFrame]:
    """Capacities first, then groups, then spacing around the best so far; stops when a round gains nothing."""
    results: dict[str, tuple] = {}
    best, best_name = base, None
    for _ in range(rounds):
        before = best_name
        for axis in (candidates(best, list(capacities), [best.policy], [best.gap]), candidates(best, [best.capacity], list(policies), [best.gap]), candidates(best, [best.capacity], [best.policy], list(gaps))):
            name = lambda o: f"{o.policy}/{o.capacity}/{'S-1' if o.gap is None else o.gap}"
            todo = [o for o in axis if name(o) not in results]
            if todo:
                results |= {r["run_id"]: tuple(r) for r in evaluate(spark, samples, adapters, todo).collect()}  # one row a candidate
            best = max(axis, key=lambda o: (results[name(o)][-1], name(o)))
            best_name = name(best)
        if best_name == before:
            break
    rows = [(*r, r[0] == best_name) for r in results.values()]
    return best_name, spark.createDataFrame(rows, "run_id string, makespan double, busy double, bubble double, microbatches bigint, tokens bigint, rate double, chosen boolean")


def balanced_clusters(samples: DataFrame, clusters: int) -> DataFrame:
    """Adapters dealt to clusters, the heaviest first to the lightest cluster: (adapter_id, tokens, cluster)."""
    load, rows = [0] * clusters, []
    for r in adapter_stats(samples).orderBy(F.col("tokens").desc(), "adapter_id").collect():  # one row per adapter
        k = min(range(clusters), key=lambda i: (load[i], i))
        load[k] += r["tokens"]
        rows.append((r["adapter_id"], r["tokens"], k))
    return samples.sparkSession.createDataFrame(rows, "adapter_id string, tokens bigint, cluster int")


def for_replicas(schedule: DataFrame, runs: DataFrame, replicas: int) -> DataFrame:
    """Runs in which every replica gets as many microbatches of each batch: batches are filled up with no-ops.

    Replicas take microbatches in turn and step together, so one that has fewer in a batch waits for the others.
    """
    slots = schedule.select("pos", "gb", "group_id").distinct()
    index = F.row_number().over(Window.partitionBy("gb", "group_id").orderBy("pos")) - 1  # a batch is bounded by its size
    whole = (F.ceil(F.col("n") / replicas) * replicas).cast("bigint")
    batches = slots.groupBy("gb", "group_id").agg(F.min("pos").alias("first"), F.count(F.lit(1)).alias("n")).withColumn("whole", whole)
    batches = checkpointed(running(batches, [], ["first"], "whole", "base"))
    placed = slots.withColumn("index", index).join(batches.select("gb", "group_id", "base"), ["gb", "group_id"]).select("pos", (F.col("base") + F.col("index")).alias("at"))
    real = runs.join(placed, "pos").withColumn("pos", F.col("at")).drop("at")
    extra = batches.where("whole > n").select(F.explode(F.sequence(F.col("base") + F.col("n"), F.col("base") + F.col("whole") - 1)).alias("pos"))
    like = runs.select("run_id", "stages").distinct()  # one run
    empty = F.array().cast(runs.schema["keys"].dataType)
    return real.unionByName(extra.crossJoin(F.broadcast(like)).select("run_id", "pos", F.lit(0).alias("cost_tokens"), F.lit(0).alias("real_tokens"), empty.alias("keys"), "stages"))


def scaling_study(spark: SparkSession, samples: DataFrame, adapters: list[Adapter], devices: tuple[int, ...] = (4, 8, 16), stages: int = 4, options: Options = Options(), sync: float = 0.0) -> DataFrame:
    """Data-parallel against job scaling: (mode, devices, makespan, tokens, rate_per_device).

    Data parallel: replicas of the pipeline share each global batch, whose size grows with the devices, and meet at
    its end. Jobs: as many more jobs of the plain batch size, dealt to clusters of `stages` devices that work side by
    side. Both train the same samples, as do both sequential baselines under data parallelism, with stock kernels. sync: what the replicas take to sum a batch's gradients.
    """
    samples = checkpointed(samples)
    ranked = checkpointed(rank_within(samples, ["adapter_id"], ["order_key", "sample_id"]))  # whatever the size of a batch
    factors = kernel_factors(spark)
    stock, fused = factors["naive"], factors["routed"]

    def data_parallel(d: int) -> list[DataFrame]:
        replicas = d // stages
        wide = [replace(a, global_batch_size=a.global_batch_size * replicas) for a in adapters]
        spaced = options.with_(stages=stages, gap=(stages - 1) * replicas)
        batches = checkpointed(global_batches(spark, ranked, wide, spaced))

        def simulated(name: str, slots: DataFrame, runs: DataFrame, factor: float) -> DataFrame:
            shared = for_replicas(slots, runs, replicas)
            return checkpointed(simulate_pipeline(shared, PipeConfig(sync=sync, per_token=factor), replicas=replicas).select(F.lit(name).alias("mode"), F.lit(d).alias("devices"), "makespan", "tokens"))

        def method() -> DataFrame:
            schedule = checkpointed(schedule_batches(batches, spaced))
            return simulated("data_parallel", schedule, as_runs(schedule, f"dp/{d}", stages, options.multiple), fused)

        micro = checkpointed(fixed_microbatches(batches))

        def sequential() -> DataFrame:  # an adapter's batches come one after the other
            placed = checkpointed(baseline_pipeline(micro))
            order = F.dense_rank().over(Window.partitionBy("gb").orderBy("adapter_id")).cast("int")  # adapters of a batch
            slots = placed.withColumn("group_id", order).withColumn("gb", F.concat_ws("/", "adapter_id", F.col("gb").cast("string")))
            return simulated("dp_sequential_pipeline", slots, baseline_runs(placed, f"dp_sequential_pipeline/{d}", stages), stock)

        def filled() -> DataFrame:
            placed = checkpointed(baseline_uniform_fill(micro))
            return simulated("dp_uniform_fill", placed.withColumn("group_id", F.lit(0)), baseline_runs(placed, f"dp_uniform_fill/{d}", stages), stock)

        return side_by_side(spark, [method, sequential, filled])

    def job_parallel(d: int) -> list[DataFrame]:
        replicas = d // stages
        part = F.pmod(F.crc32("order_key"), F.lit(replicas)).cast("string")
        jobs = checkpointed(rank_within(samples.withColumn("adapter_id", F.concat_ws("#", "adapter_id", part)), ["adapter_id"], ["order_key", "sample_id"]))
        each = [replace(a, adapter_id=f"{a.adapter_id}#{k}") for a in adapters for k in range(replicas)]
        clusters = balanced_clusters(jobs, replicas)

        def cluster(k: int) -> DataFrame:
            mine = jobs.join(F.broadcast(clusters.where(F.col("cluster") == k)).select("adapter_id"), "adapter_id", "left_semi")
            return as_runs(schedule_batches(global_batches(spark, mine, each, options), options), f"job/{d}/{k}", stages, options.multiple)

        parts = side_by_side(spark, [partial(cluster, k) for k in range(replicas)])
        job = simulate_pipeline(reduce(DataFrame.unionByName, parts), PipeConfig(per_token=fused)).agg(F.max("makespan").alias("makespan"), F.sum("tokens").alias("tokens"))
        return [checkpointed(job.select(F.lit("jobs").alias("mode"), F.lit(d).alias("devices"), "makespan", "tokens"))]

    made = side_by_side(spark, [partial(f, d) for d in devices for f in (data_parallel, job_parallel)])
    out = reduce(DataFrame.unionByName, [x for part in made for x in part])
    return out.withColumn("rate_per_device", F.round(F.col("tokens") * 1000 / F.col("makespan") / F.col("devices"), 6))
