"""Cost and quality measures; each takes rows and gives rows."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def state_memory(shapes: DataFrame, per_trainable: int = 16) -> DataFrame:
    """Model-state bytes of a linear layer. per_trainable: bytes for each trainable parameter, 32 as printed, 16 as derived."""
    full, adapter = F.expr("16 * n * k"), F.expr(f"2 * n * k + {per_trainable} * r * (n + k)")
    return shapes.select("k", "n", "r", full.alias("full_bytes"), adapter.alias("adapter_bytes"), F.expr(f"16 * n * k * 1000 div (2 * n * k + {per_trainable} * r * (n + k))").alias("reduction_per_mille"))


def param_ratio(shapes: DataFrame) -> DataFrame:
    """Trainable over frozen parameters, parts per million: both matrices, and one of them."""
    return shapes.select("k", "n", "r", F.expr("r * (n + k) * 1000000 div (n * k)").alias("both_ppm"), F.expr("r * 1000000 div n").alias("one_ppm"))


def arithmetic_intensity(rows: float, inner: float, cols: float) -> float:
    return 1 / (1 / rows + 1 / inner + 1 / cols)


def intensity(shapes: DataFrame, balance: int = 295) -> DataFrame:
    """Operations per element moved (thousandths) of the three products, and whether each is bound by memory."""
    f = lambda a, b, c: f"1000 * {a} * {b} * {c} div ({a} * {b} + {b} * {c} + {a} * {c})"
    cols = {"base": f("m", "k", "n"), "down": f("m", "k", "r"), "up": f("m", "r", "n")}
    made = [F.expr(e).alias(f"{p}_thousandths") for p, e in cols.items()]
    return shapes.select("m", "k", "n", "r", *made, *[F.expr(f"({e}) < {balance * 1000}").alias(f"{p}_memory_bound") for p, e in cols.items()])


def throughput(runs: DataFrame) -> DataFrame:
    """Real tokens per 1000 units of time. runs: (run_id, makespan, tokens)."""
    return runs.select("run_id", "tokens", "makespan", F.round(F.col("tokens") * 1000 / F.col("makespan"), 6).alias("rate"))


def speedup_table(runs: DataFrame, base: str) -> DataFrame:
    """Speed of each method over `base` on the same workload. runs: (workload, method, rate)."""
    b = runs.where(F.col("method") == base).select("workload", F.col("rate").alias("base_rate"))
    return runs.join(b, "workload").select("workload", "method", F.round(F.col("rate") / F.col("base_rate"), 6).alias("speedup"))


def speedup_summary(table: DataFrame) -> DataFrame:
    return table.groupBy("method").agg(F.round(F.avg("speedup"), 6).alias("mean"), F.max("speedup").alias("largest"), F.min("speedup").alias("smallest"))


def bubble_ratio(trace: DataFrame, stages: int) -> DataFrame:
    """Idle share over all stages. trace: (run_id, start, end) of every piece of work."""
    return trace.groupBy("run_id").agg(F.round(1 - F.sum(F.col("end") - F.col("start")) / (stages * F.max("end")), 6).alias("bubble"))


def utilization(bubbles: DataFrame) -> DataFrame:
    return bubbles.withColumn("utilization", F.round(1 - F.col("bubble"), 6))


def packing_quality(loads: DataFrame, capacity: int, theta: float = 0.5) -> DataFrame:
    """Per group: microbatches, padding waste, fill, mean fill of each batch's smallest microbatch, and underfilled ones.

    loads: what `bin_loads` gives. All shares per mille.
    """
    small = loads.groupBy("group_id", "gb").agg(F.min("padded_tokens").alias("least"))
    least = small.groupBy("group_id").agg(F.expr(f"sum(least) * 1000 div (count(1) * {capacity})").alias("smallest_fill"))
    whole = loads.groupBy("group_id").agg(
        F.count(F.lit(1)).alias("microbatches"), F.expr("(sum(padded_tokens) - sum(real_tokens)) * 1000 div sum(padded_tokens)").alias("waste"),
        F.expr(f"sum(padded_tokens) * 1000 div (count(1) * {capacity})").alias("fill"), F.count_if(F.col("padded_tokens") < theta * capacity).alias("underfilled"),
    )
    return whole.join(least, "group_id")


def ideal_gap(practical: DataFrame, ideal: DataFrame) -> DataFrame:
    """Slowdown of practical runs against ideal ones of equal lengths, per mille; both (run_id, makespan)."""
    i = ideal.select("run_id", F.col("makespan").alias("ideal"))
    return practical.join(i, "run_id").select("run_id", F.round((F.col("makespan") - F.col("ideal")) * 1000 / F.col("makespan"), 3).alias("slowdown_per_mille"))


def tuning_fit(timings: DataFrame) -> DataFrame:
    """Linear fit of scheduling seconds over samples. timings: (samples, seconds)."""
    return timings.agg(
        F.round(F.regr_slope("seconds", "samples") * 1000, 6).alias("ms_per_sample"), F.round(F.regr_intercept("seconds", "samples"), 6).alias("fixed_seconds"), F.round(F.regr_r2("seconds", "samples"), 6).alias("r2")
    )


def overlap(timings: DataFrame) -> DataFrame:
    """Scheduling that the training of the preceding batch does not hide. timings: (gb, schedule_time, train_time)."""
    w = Window.orderBy("gb")  # one row per global batch of a report
    before = F.lag("train_time", 1, 0).over(w)
    return timings.select("gb", "schedule_time", "train_time", F.greatest(F.col("schedule_time") - before, F.lit(0)).alias("exposed"))


def observe_cost(df: DataFrame, name: str = "cost") -> tuple[DataFrame, object]:
    """The frame with a row count observed as it runs, and the observation to read afterwards."""
    from pyspark.sql import Observation

    seen = Observation(name)
    return df.observe(seen, F.count(F.lit(1)).alias("rows")), seen


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()
