"""The experiments as functions (spark, sf_dir) -> rows; W-numbers follow the inventory."""

from __future__ import annotations

import time
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from adapterlab.algebra.bank import default_bank, with_gradient, x_rows
from adapterlab.algebra.layers import agreement, naive_backward, naive_forward, routed_backward, routed_forward
from adapterlab.cost.ledger import kernel_factors, kernel_speedup, layer_sweep, layers_of, runtime_breakdown, shapes_frame, traffic_ledger, traffic_ratio
from adapterlab.cost.measures import ideal_gap, overlap, packing_quality, speedup_table, tuning_fit
from adapterlab.operators.baselines import as_runs as baseline_runs
from adapterlab.operators.baselines import baseline_pipeline, baseline_uniform_fill, fixed_microbatches
from adapterlab.operators.batching import imbalance, microbatch_tokens
from adapterlab.operators.packing import bin_loads, pack_batches, solver_report
from adapterlab.operators.schedule import build_schedule, schedule_counts
from adapterlab.plans.planner import Options, as_runs, global_batches, pack, schedule_batches, schedule_packed, simulate_schedule
from adapterlab.plans.tuner import scaling_study, tune
from adapterlab.samples import Adapter, dataset_lengths, equal_samples, het_adapters, homogeneous_adapters, layer_rows, token_samples
from adapterlab.session import checkpointed, side_by_side
from adapterlab.simulate.pipeline import PipeConfig, simulate_pipeline
from adapterlab.simulate.presets import HARDWARE, MODELS, pipe_config
from adapterlab.simulate.sharded import ideal_run, simulate_sharded
from adapterlab.sources.tables import load
from adapterlab.sources.weights import base_matrix

FAST = Options(nodes=1000)
LAYERS = [(8192, 4096, 4096, 16), (8192, 4096, 14336, 16), (8192, 14336, 4096, 16), (8192, 5120, 5120, 16), (8192, 8192, 8192, 16), (8192, 8192, 28672, 16)]


def w1_layer_slowdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the layer: padded lengths of the orders' microbatches."""
    shapes = layers_of(layer_rows(spark, sf_dir), [(4096, 4096, r) for r in (16, 32)])
    return layer_sweep(traffic_ledger(shapes)).where("impl IN ('naive', 'compiled', 'split', 'routed')")


def w2_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    return runtime_breakdown(traffic_ledger(shapes_frame(spark, LAYERS[:1])))


def w3_traffic(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ideal ledger, and the one whose frozen product reads again as a real one does."""
    plain = traffic_ratio(traffic_ledger(shapes_frame(spark, LAYERS))).withColumn("model", F.lit("ideal"))
    real = traffic_ratio(traffic_ledger(shapes_frame(spark, LAYERS), gemm_reread=7.8)).withColumn("model", F.lit("reread"))
    return plain.unionByName(real)


def w4_ideal_batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ideal_run(dataset_lengths(spark, sf_dir, "medium").where("tok_len > 0"), [4, 8, 16, 32])


def w5_imbalance(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = token_samples(spark, sf_dir, het_adapters())
    return imbalance(microbatch_tokens(samples.where("dataset IN ('medium', 'mixed')")), ["adapter_id"])


def w6_practical_against_ideal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sequential pipeline with real lengths and with each microbatch as long as the mean; and no flush at all."""
    micro = checkpointed(_micro(spark, sf_dir, het_adapters(), FAST))
    mean = micro.agg(F.expr("sum(cost_tokens) div count(1)").alias("mean"))
    even = micro.crossJoin(F.broadcast(mean)).withColumn("cost_tokens", F.col("mean")).drop("mean")
    runs = [baseline_runs(baseline_pipeline(micro), "practical", 4), baseline_runs(baseline_pipeline(even), "ideal", 4), baseline_runs(baseline_uniform_fill(even), "ideal_multi", 4)]
    done = simulate_pipeline(reduce(DataFrame.unionByName, runs)).select("run_id", "makespan", F.round("bubble", 6).alias("bubble"), "tokens")
    ranks = [baseline_pipeline(m).select(F.lit(n).alias("run_id"), "pos", F.col("cost_tokens").alias("tokens")) for m, n in ((micro, "sharded_practical"), (even, "sharded_ideal"))]
    shard = simulate_sharded(ranks[0].unionByName(ranks[1])).select("run_id", F.col("makespan").cast("double"), F.lit(None).cast("double").alias("bubble"), "tokens")
    rows = checkpointed(done.unionByName(shard))
    kind = F.regexp_replace("run_id", "(_?)(practical|ideal)$", "")
    ends = [rows.where(F.col("run_id").endswith(end)).select(kind.alias("run_id"), "makespan") for end in ("practical", "ideal")]
    slow = ideal_gap(*ends).select(F.concat(F.col("run_id"), F.when(F.col("run_id") == "", "practical").otherwise("_practical")).alias("run_id"), "slowdown_per_mille")
    return rows.join(F.broadcast(slow), "run_id", "left")


def _samples(spark: SparkSession, sf_dir: str, adapters: list[Adapter]) -> DataFrame:
    """Equally many samples of each adapter, so that none is left to run alone."""
    return equal_samples(token_samples(spark, sf_dir, adapters))


def _micro(spark: SparkSession, sf_dir: str, adapters: list[Adapter], options: Options) -> DataFrame:
    return fixed_microbatches(global_batches(spark, _samples(spark, sf_dir, adapters), adapters, options))


def compare(spark: SparkSession, sf_dir: str, cases: list[tuple[str, list[Adapter], str, str]]) -> DataFrame:
    """Both sequential baselines, uniform filling and the full method: (workload, method, makespan, bubble, tokens, rate).

    cases: (name, adapters, model preset, hardware). What cases share is made once, for several sets of adapters at a time:
    samples by adapters, batches, baselines and packing by capacity, schedules by options. All simulations run side by side.
    """
    factors = kernel_factors(spark)
    chosen = [FAST.with_(stages=MODELS[preset].stages, capacity=max(1024, int(MODELS[preset].capacity * HARDWARE[hardware][0] / 2))) for _, _, preset, hardware in cases]

    def prepared(adapters: list[Adapter], wanted: list[Options]) -> dict[tuple, tuple[DataFrame, DataFrame, DataFrame, DataFrame]]:
        samples, out, packings = checkpointed(_samples(spark, sf_dir, adapters)), {}, {}
        for options in dict.fromkeys(wanted):
            shared = options.with_(stages=0)  # neither batches nor their packing depend on the stages
            if shared not in packings:
                batches = checkpointed(global_batches(spark, samples, adapters, options))
                micro = checkpointed(fixed_microbatches(batches))
                packings[shared] = micro, checkpointed(baseline_pipeline(micro)), checkpointed(baseline_uniform_fill(micro)), checkpointed(pack(batches, options))
            *baselines, packed = packings[shared]
            out[(tuple(adapters), options)] = (*baselines, schedule_packed(packed, options))
        return out

    by_set: dict[tuple, list[Options]] = {}
    for (_, adapters, *_), options in zip(cases, chosen):
        by_set.setdefault(tuple(adapters), []).append(options)
    made = {k: v for one in side_by_side(spark, [partial(prepared, list(a), o) for a, o in by_set.items()]) for k, v in one.items()}
    runs, sharded = [], []
    for (name, adapters, preset, hardware), options in zip(cases, chosen):
        p = MODELS[preset]
        micro, sequential, filled, schedule = made[(tuple(adapters), options)]
        label = f"{preset}/{name}/{hardware}"
        stock, fused = pipe_config(p, factors["naive"], hardware), pipe_config(p, factors["routed"], hardware)
        for method, rows, config in (
            ("sequential_pipeline", baseline_runs(sequential, f"{label}|sequential_pipeline", p.stages), stock),
            ("uniform_fill", baseline_runs(filled, f"{label}|uniform_fill", p.stages), stock),
            ("method", as_runs(schedule, f"{label}|method", p.stages), fused),
        ):
            runs.append(rows.withColumns({"per_token": F.lit(config.per_token), "last_extra": F.lit(config.last_extra)}))
        # Ranks of the sharded baseline meet before each layer, and each runs all layers for its own rows; gathering
        # the layers takes a share of a full step at least.
        each = stock.per_token * (1 + stock.backward) * p.stages
        floor = 0.0 if p.stages == 1 else 0.35 * options.capacity * each
        step = micro.groupBy("adapter_id", "gb", F.floor(F.col("mb") / p.stages).alias("step")).agg(F.max("cost_tokens").alias("t"), F.sum("tokens").alias("tokens"))
        shard = step.agg(F.sum(F.greatest(F.col("t") * each, F.lit(floor))).alias("makespan"), F.sum("tokens").alias("tokens"))
        sharded.append(shard.select(F.lit(f"{label}|sequential_sharded").alias("run_id"), "makespan", F.lit(None).cast("double").alias("bubble"), "tokens"))
    done = simulate_pipeline(reduce(DataFrame.unionByName, runs)).select("run_id", "makespan", "bubble", "tokens")
    parts = F.split("run_id", r"\|")
    rows = reduce(DataFrame.unionByName, [done, *sharded])
    return rows.select(parts[0].alias("workload"), parts[1].alias("method"), "makespan", "bubble", "tokens", F.round(F.col("tokens") * 1000 / F.col("makespan"), 6).alias("rate"))


def w8_end_to_end(spark: SparkSession, sf_dir: str) -> DataFrame:
    sets = {d: homogeneous_adapters(d) for d in ("short", "medium", "long", "mixed")} | {"het": het_adapters()}
    runs = checkpointed(compare(spark, sf_dir, [(n, a, p, "first") for p in ("small", "medium", "large") for n, a in sets.items()]))
    table = speedup_table(runs, "sequential_pipeline")
    return runs.join(table, ["workload", "method"]).select("workload", "method", "rate", F.round("bubble", 6).alias("bubble"), "speedup")


def w9_second_hardware(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Less memory, slower links: the small model on one device, the medium one on four, over the five workloads."""
    sets = {d: homogeneous_adapters(d) for d in ("short", "medium", "long", "mixed")} | {"het": het_adapters()}
    runs = checkpointed(compare(spark, sf_dir, [(n, a, p, "second") for p in ("small", "medium_four") for n, a in sets.items()]))
    return runs.join(speedup_table(runs, "sequential_pipeline"), ["workload", "method"]).select("workload", "method", "rate", "speedup")


def order_adapters(g: int = 16) -> list[Adapter]:
    return [Adapter(s.lower(), "orders", 16, 16.0, 0.0, g, 31 + i) for i, s in enumerate(("AUTOMOBILE", "BUILDING", "FURNITURE", "MACHINERY"))]


def order_samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as samples, the adapter by the customer's market segment (four of five), the length by the quantities."""
    lengths = dataset_lengths(spark, sf_dir, "orders").where("tok_len > 0")
    orders = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customer = load(spark, sf_dir, "customer").where("c_mktsegment <> 'HOUSEHOLD'").select("c_custkey", F.lower("c_mktsegment").alias("adapter_id"))
    rows = lengths.join(orders, F.col("sample_id") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    return rows.select("adapter_id", F.col("sample_id").cast("bigint").alias("sample_id"), F.lit("orders").alias("dataset"), "tok_len", F.md5(F.concat_ws("-", "adapter_id", F.col("sample_id").cast("string"))).alias("order_key"))


def w10_scaling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Summing gradients over replicas takes as long as six full microbatches, as over a network of nodes."""
    options = FAST.with_(capacity=512, exact=False)
    return scaling_study(spark, order_samples(spark, sf_dir), order_adapters(16), (4, 8, 16), 4, options, sync=6.0 * options.capacity)


def w11_kernels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kernel_speedup(traffic_ledger(layers_of(layer_rows(spark, sf_dir), [(4096, 4096, 16)])))


def w12_layers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kernel_speedup(traffic_ledger(layers_of(layer_rows(spark, sf_dir), [x[1:] for x in LAYERS]))).where("impl IN ('split', 'routed')")


def w13_bubbles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bubble of 1 to 4 adapters of one dataset against the baselines with four."""
    parts = []
    for n in (1, 2, 3, 4):
        a = homogeneous_adapters("medium", n=n)
        policy = "singleton" if n <= 2 else "k_groups"
        parts.append(as_runs(schedule_batches(global_batches(spark, _samples(spark, sf_dir, a), a, FAST.with_(policy=policy)), FAST), f"method_{n}", 4))
    micro = checkpointed(_micro(spark, sf_dir, homogeneous_adapters("medium"), FAST))
    parts += [baseline_runs(baseline_pipeline(micro), "sequential_pipeline", 4), baseline_runs(baseline_uniform_fill(micro), "uniform_fill", 4)]
    return simulate_pipeline(reduce(DataFrame.unionByName, parts), PipeConfig(last_extra=0.05)).select("run_id", F.round("bubble", 6).alias("bubble"), "microbatches")


def w14_scheduling_time(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (640, 1600, 3200, 6400, 12800, 25600)) -> DataFrame:
    """Measured seconds of packing, merging and repair; as many of the sizes as the table has orders."""
    samples = checkpointed(order_samples(spark, sf_dir))
    have, rows = samples.count(), []
    for n in sizes:
        if n > have and rows:
            break
        part = samples.orderBy("order_key", "sample_id").limit(n)
        batches = checkpointed(global_batches(spark, part, order_adapters(), FAST.with_(capacity=512)))
        began = time.time()
        schedule_batches(batches, FAST.with_(capacity=512)).agg(F.max("pos")).collect()
        rows.append((min(n, have), time.time() - began))
    return spark.createDataFrame(rows, "samples bigint, seconds double")


def w14_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tuning_fit(w14_scheduling_time(spark, sf_dir))


def w14_overlap(spark: SparkSession, sf_dir: str, sizes: tuple[int, ...] = (640, 1600, 3200, 6400, 12800, 25600), tokens_per_second: float = 10_000.0) -> DataFrame:
    """Measured scheduling beside simulated training, by number of samples; what the training before does not hide.

    (gb, samples, schedule_time, train_time, exposed). tokens_per_second: of one stage of the frozen layer, an assumption,
    as no absolute rate is known. Each size counts as one round after the one before.
    """
    samples = checkpointed(order_samples(spark, sf_dir))
    have, rows, factor = samples.count(), [], kernel_factors(spark)["routed"]
    for k, n in enumerate(sizes):
        if n > have and rows:
            break
        part = samples.orderBy("order_key", "sample_id").limit(n)
        batches = checkpointed(global_batches(spark, part, order_adapters(), FAST.with_(capacity=512)))
        began = time.time()
        schedule = checkpointed(schedule_batches(batches, FAST.with_(capacity=512)))
        seconds = time.time() - began
        span = simulate_schedule(schedule, 4, PipeConfig(per_token=factor)).first()["makespan"]
        rows.append((k, min(n, have), seconds, span / tokens_per_second))
    timings = spark.createDataFrame(rows, "gb bigint, samples bigint, schedule_time double, train_time double")
    return timings.select("gb", "samples").join(overlap(timings), "gb")


def w15_ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Merge on and off, exact and greedy, both scopes: simulated rate."""
    a = het_adapters()
    batches = checkpointed(global_batches(spark, token_samples(spark, sf_dir, a), a, FAST))
    kinds = {
        "full": FAST, "no_merge": FAST.with_(merge=False), "greedy": FAST.with_(exact=False), "neither": FAST.with_(exact=False, merge=False),
        "within_group": FAST.with_(scope="within_group"), "unguarded": FAST.with_(guard=False),
    }
    runs = [as_runs(schedule_batches(batches, o), n, 4) for n, o in kinds.items()]
    done = simulate_pipeline(reduce(DataFrame.unionByName, runs))
    return done.select("run_id", F.round(F.col("tokens") * 1000 / F.col("makespan"), 6).alias("rate"), F.round("bubble", 6).alias("bubble"), "microbatches")


def w15_solver_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = het_adapters()
    return solver_report(pack_batches(global_batches(spark, token_samples(spark, sf_dir, a), a, FAST), FAST.capacity, FAST.multiple, nodes=20_000))


# Published bars of the breakdown, printed beside ours.
PUBLISHED_BARS = {"1_sequential": 1.0, "2_split_fused": 1.13, "3_continuous": 1.5, "4_continuous_routed": 1.72, "5_scheduler": 1.57, "6_all": 2.05}


def w16_breakdown(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six configurations on het with the largest model: rate and speedup over the first, beside the published bars.

    What the kernels gain is what the ledger's roofline says, an upper bound of what real ones gain.
    """
    a, p, factors = het_adapters(), MODELS["large"], kernel_factors(spark)
    batches = checkpointed(global_batches(spark, _samples(spark, sf_dir, a), a, FAST))
    micro = checkpointed(fixed_microbatches(batches))
    sequential, filled = baseline_pipeline(micro), baseline_uniform_fill(micro)
    schedule = checkpointed(as_runs(schedule_batches(batches, FAST), "x", p.stages))
    steps = [
        ("1_sequential", baseline_runs(sequential, "1_sequential", 4), "naive"), ("2_split_fused", baseline_runs(sequential, "2_split_fused", 4), "split"),
        ("3_continuous", baseline_runs(filled, "3_continuous", 4), "naive"), ("4_continuous_routed", baseline_runs(filled, "4_continuous_routed", 4), "routed"),
        ("5_scheduler", schedule.withColumn("run_id", F.lit("5_scheduler")), "naive"), ("6_all", schedule.withColumn("run_id", F.lit("6_all")), "routed"),
    ]
    done = [simulate_pipeline(runs, pipe_config(p, factors[kernel])).withColumn("workload", F.lit("het")) for _, runs, kernel in steps]
    rates = checkpointed(reduce(DataFrame.unionByName, done).select("workload", F.col("run_id").alias("method"), F.round(F.col("tokens") * 1000 / F.col("makespan"), 6).alias("rate"), F.round("bubble", 6).alias("bubble")))
    bars = spark.createDataFrame(list(PUBLISHED_BARS.items()), "method string, published double")
    return rates.join(speedup_table(rates.select("workload", "method", "rate"), "1_sequential"), ["workload", "method"]).join(F.broadcast(bars), "method")


def w17_budgets(spark: SparkSession, sf_dir: str, budgets: tuple[int, ...] = (0, 1000, 10_000)) -> DataFrame:
    """Node budgets: fill of the smallest microbatch and share of batches solved exactly."""
    a = het_adapters()
    batches = checkpointed(global_batches(spark, token_samples(spark, sf_dir, a), a, FAST))
    out = None
    for nodes in budgets:
        items = checkpointed(pack_batches(batches, FAST.capacity, FAST.multiple, nodes=nodes))
        fill = packing_quality(bin_loads(items, FAST.multiple), FAST.capacity).agg(F.sum("microbatches").alias("microbatches"), F.expr("sum(smallest_fill) div count(1)").alias("smallest_fill"))
        share = items.select("group_id", "gb", "solver_path").distinct().agg(F.expr("count_if(solver_path = 'exact') * 1000 div count(1)").alias("exact_per_mille"))
        row = fill.join(share).select(F.lit(nodes).alias("nodes"), "microbatches", "smallest_fill", "exact_per_mille")
        out = row if out is None else out.unionByName(row)
    return out


def w18_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fused and naive results cell by cell: none differs."""
    x, w, bank = x_rows(spark, sf_dir), base_matrix(), default_bank()
    y = agreement(naive_forward(x, w, bank), routed_forward(x, w, bank)).withColumn("result", F.lit("y"))
    both = with_gradient(x)
    dx = agreement(naive_backward(both, w, bank)["dx"], routed_backward(both, w, bank)["dx"], "dx").withColumn("result", F.lit("dx"))
    return y.unionByName(dx).select("result", "cells", "unequal", "largest")


def w19_tuning_jobs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Adapters of a search over rank, scale and dropout on one dataset: rate by number of adapters."""
    grid = [(r, al, p) for r in (8, 16) for al in (16.0, 32.0) for p in (0.0, 0.5)]
    parts = []
    for n in (1, 2, 4, 8):
        a = [Adapter(f"t{i}", "medium", r, al, p, 16, 41 + i) for i, (r, al, p) in enumerate(grid[:n])]
        o = FAST.with_(policy="singleton" if n < 4 else "pair", exact=False)
        parts.append(as_runs(schedule_batches(global_batches(spark, token_samples(spark, sf_dir, a), a, o), o), f"adapters_{n}", 4))
    done = simulate_pipeline(reduce(DataFrame.unionByName, parts))
    return done.select("run_id", F.round(F.col("tokens") * 1000 / F.col("makespan"), 6).alias("rate"), F.round("bubble", 6).alias("bubble"))


def tune_loop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tuning loop with exact packing: every candidate it simulated, and the one it chose."""
    a = het_adapters()
    return tune(spark, _samples(spark, sf_dir, a), a, FAST)[1].select("run_id", "rate", F.round("bubble", 6).alias("bubble"), "chosen")


def tenant_adapters(spark: SparkSession, sf_dir: str, tenants: int = 8) -> list[Adapter]:
    return [Adapter(f"u{i}", "events", 16, 16.0, 0.0, 16, 51 + i) for i in range(tenants)]


def w19_tenants(spark: SparkSession, sf_dir: str, tenants: int = 8) -> DataFrame:
    """Jobs of several tenants, who are users dealt by hash: an event is a sample as long as its value says.

    Each tenant's job by itself, one after another, against all of them in one schedule.
    """
    a = tenant_adapters(spark, sf_dir, tenants)
    rows = load(spark, sf_dir, "events").where("event_id IS NOT NULL")
    length = (F.pmod(F.xxhash64("event_id"), F.lit(480)) + 32).cast("bigint")
    samples = rows.select(
        F.concat(F.lit("u"), F.pmod(F.xxhash64("user_id"), F.lit(tenants)).cast("string")).alias("adapter_id"), F.col("event_id").cast("bigint").alias("sample_id"), F.lit("events").alias("dataset"),
        length.alias("tok_len"), F.md5(F.col("event_id").cast("string")).alias("order_key"),
    )
    o = FAST.with_(exact=False)
    batches = checkpointed(global_batches(spark, checkpointed(samples), a, o))
    together = as_runs(schedule_batches(batches, o), "together", 4)
    alone = baseline_runs(baseline_pipeline(fixed_microbatches(batches)), "one_after_another", 4)
    done = simulate_pipeline(together.unionByName(alone))
    return done.select("run_id", "tokens", F.round(F.col("tokens") * 1000 / F.col("makespan"), 6).alias("rate"), F.round("bubble", 6).alias("bubble"))


def merge_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    a = het_adapters()
    items = checkpointed(pack_batches(global_batches(spark, token_samples(spark, sf_dir, a), a, FAST), FAST.capacity, FAST.multiple, nodes=FAST.nodes))
    out = None
    for scope, merge in (("interleaved", True), ("within_group", True), ("none", False)):
        made = build_schedule(items, FAST.capacity, FAST.multiple, 4, merge=merge, scope=scope if merge else "interleaved", guard=False)
        row = schedule_counts(made).select(F.lit(scope).alias("scope"), "microbatches", "noops", "merged")
        out = row if out is None else out.unionByName(row)
    return out
