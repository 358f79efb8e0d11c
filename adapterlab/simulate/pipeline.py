"""Event-driven 1F1B pipeline of S stages over ordered microbatches.

A stage does one thing at a time, a ready backward goes before a ready forward, and stage s holds at most S - s
microbatches between their two passes. A microbatch enters only after the first stage has run the backward of
the last microbatch with the preceding batch of any of its adapters, whatever spacing the schedule assumed.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.jvm import kernel
from adapterlab.session import spread


@dataclass(frozen=True)
class PipeConfig:
    stages: int = 4
    fixed: float = 0.0  # cost of a microbatch beside its tokens
    per_token: float = 1.0
    backward: float = 2.0  # backward over forward
    last_extra: float = 0.0  # more work on the last stage, as a share
    sync: float = 0.0  # what replicas take to sum a batch's gradients


@dataclass
class Trace:
    makespan: float
    busy: list[float]
    events: list[tuple[int, int, str, float, float]]  # stage, microbatch, kind, start, end

    @property
    def bubble(self) -> float:
        whole = len(self.busy) * self.makespan
        return 1 - sum(self.busy) / whole if whole else 0.0


def simulate(micros: list[tuple[int, list[tuple[str, int]]]], config: PipeConfig = PipeConfig(), keep_events: bool = False, flush: bool = False, replicas: int = 1) -> Trace:
    """micros: (tokens, [(adapter, batch), ...]) in order; zero tokens is a no-op. flush: a batch waits for all of the one before.

    replicas: pipelines side by side that take microbatches in turn; a batch's gradients are summed over all of them,
    so that the next batch of the adapter waits for each.
    """
    n, s_max = len(micros), config.stages
    last: dict[tuple[str, int], dict[int, int]] = {}
    gates: list[list[int]] = [[] for _ in range(n)]
    barrier, current = -1, None
    for i, (_, keys) in enumerate(micros):
        gates[i] = sorted({g for a, j in keys for g in last.get((a, j - 1), {}).values()})
        if flush and keys:
            label = tuple(sorted(set(keys)))
            if label != current:
                barrier, current = i - 1, label
            gates[i] += range(max(0, barrier + 1 - replicas), barrier + 1)
        for k in keys:
            last.setdefault(k, {})[i % replicas] = i
    cost = [0.0 if not t else config.fixed + config.per_token * t for t, _ in micros]
    forward_done = [[-1.0] * n for _ in range(s_max)]
    backward_done = [[-1.0] * n for _ in range(s_max)]
    # Of each replica and stage: the next microbatch forward and backward, when it is free, and its work so far.
    next_f, next_b = ([[r] * s_max for r in range(replicas)] for _ in range(2))
    free, busy = ([[0.0] * s_max for _ in range(replicas)] for _ in range(2))
    events: list[tuple[int, int, str, float, float]] = []

    def option(r: int, s: int) -> tuple | None:
        best = None
        i = next_b[r][s]
        if i < next_f[r][s]:
            ready = forward_done[s][i] if s == s_max - 1 else backward_done[s + 1][i]
            if ready >= 0:
                best = (max(free[r][s], ready), 0, s, i, r)
        i = next_f[r][s]
        if i < n and (i - next_b[r][s]) // replicas < s_max - s:
            ready = forward_done[s - 1][i] if s else min((backward_done[0][g] for g in gates[i]), default=0.0)
            if ready >= 0:
                wait = config.sync if replicas > 1 and gates[i] else 0.0
                start = ready if s else max((backward_done[0][g] for g in gates[i]), default=0.0) + wait
                found = (max(free[r][s], start), 1, s, i, r)
                best = found if best is None or found < best else best
        return best

    # What each stage would do next; an event changes that of its own stage and of the neighbour it hands on to, and the
    # backward of a microbatch on the first stage that of replicas whose next one waits for it.
    following: list[set[int]] = [set() for _ in range(n)]
    for i, gs in enumerate(gates):
        for g in gs:
            following[g].add(i % replicas)
    nothing = (float("inf"),)
    best = [option(r, s) or nothing for r in range(replicas) for s in range(s_max)]
    for _ in range(2 * n * s_max):
        first = min(best)
        if first is nothing:
            raise RuntimeError("the pipeline waits for itself")
        start, kind, s, i, r = first
        took = cost[i] * (config.backward if kind == 0 else 1.0) * (1 + config.last_extra if s == s_max - 1 else 1.0)
        end = start + took
        free[r][s], busy[r][s] = end, busy[r][s] + took
        if kind == 0:
            backward_done[s][i] = end
            next_b[r][s] = i + replicas
        else:
            forward_done[s][i] = end
            next_f[r][s] = i + replicas
        at = r * s_max + s
        best[at] = option(r, s) or nothing
        if kind and s < s_max - 1:
            best[at + 1] = option(r, s + 1) or nothing
        elif not kind and s:
            best[at - 1] = option(r, s - 1) or nothing
        elif not kind:
            for other in following[i]:
                best[other * s_max] = option(other, 0) or nothing
        if keep_events:
            events.append((r * s_max + s, i, "backward" if kind == 0 else "forward", start, end))
    return Trace(max((t for per in free for t in per), default=0.0), [t for per in busy for t in per], events)


RESULT = "run_id string, makespan double, busy double, bubble double, microbatches bigint, tokens bigint"


def simulate_pipeline(runs: DataFrame, config: PipeConfig = PipeConfig(), flush: bool = False, replicas: int = 1) -> DataFrame:
    """One simulation per run_id, runs in parallel. runs: (run_id, pos, cost_tokens, real_tokens, keys, stages)

    keys: array of (adapter_id, batch); `stages` overrides the configuration's, and so do `per_token` and
    `last_extra` where the runs have them, one value per run.
    """
    own = [c for c in ("stages", "per_token", "last_extra") if c in runs.columns]
    dealt = spread(runs, "run_id")
    if not flush and replicas <= 64:
        # A key is the hash of its adapter, 62 bits, plus its batch, so that the batch before has the key before.
        key = F.transform("keys", lambda k: F.shiftright(F.xxhash64(k["adapter_id"]), 2) + k["batch"])
        rows = dealt.select("run_id", F.col("pos").cast("bigint").alias("pos"), "cost_tokens", "real_tokens", *own, F.posexplode_outer(key).alias("at", "key"))
        first = F.coalesce("at", F.lit(0)) == 0
        each = rows.groupBy("run_id").agg(
            F.collect_list(F.when(F.col("key").isNull(), -1 - F.col("pos")).otherwise(F.col("pos"))).alias("places"), F.collect_list(F.col("cost_tokens").cast("bigint")).alias("costs"),
            F.collect_list(F.coalesce("key", F.lit(0).cast("bigint"))).alias("keys"), F.count_if(first & (F.col("cost_tokens") > 0)).alias("microbatches"),
            F.sum(F.when(first, F.col("real_tokens"))).alias("tokens"), *[F.first(c).alias(c) for c in own],
        )
        value = lambda c, kind: (F.col(c) if c in own else F.lit(getattr(config, c))).cast(kind)
        prices, shares = F.array(F.lit(float(config.fixed)), value("per_token", "double")), F.array(F.lit(float(config.backward)), value("last_extra", "double"))
        done = kernel(runs.sparkSession, "Simulate", F.col("places"), F.col("costs"), F.col("keys"), value("stages", "int"), F.lit(replicas), prices, shares, F.lit(float(config.sync)))
        made = each.select("run_id", F.inline(F.array(done)), "microbatches", F.col("tokens").cast("bigint").alias("tokens"))
        return made.select(*[c.split()[0] for c in RESULT.split(", ")])

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pos")
        c = replace(config, **{k: pdf[k].iloc[0].item() for k in own})
        micros = [(int(t), [(k["adapter_id"], k["batch"]) for k in keys]) for t, keys in zip(pdf["cost_tokens"], pdf["keys"])]
        t = simulate(micros, c, flush=flush, replicas=replicas)
        return pd.DataFrame([(pdf["run_id"].iloc[0], t.makespan, sum(t.busy), t.bubble, int((pdf["cost_tokens"] > 0).sum()), int(pdf["real_tokens"].sum()))], columns=[c.split()[0] for c in RESULT.split(", ")])

    return dealt.groupBy("run_id").applyInPandas(one, RESULT)


def uniform_bubble(stages: int, microbatches: int) -> float:
    """Closed form for equal microbatches and one flush."""
    return (stages - 1) / (microbatches + stages - 1)
