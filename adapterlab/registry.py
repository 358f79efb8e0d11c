"""Queries by name, and their SQL twins."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from adapterlab import oracles as Q
from adapterlab.algebra import layers as L
from adapterlab.algebra.bank import default_bank, dropout_mask, with_gradient, x_rows
from adapterlab.algebra.tiles import build_tiles
from adapterlab.algebra.variants import magnitude_forward, quantize4, shared_random_forward
from adapterlab.cost import ledger as C
from adapterlab.cost import measures as M
from adapterlab.experiments import workloads as W
from adapterlab.operators import baselines as BL
from adapterlab.operators import batching as B
from adapterlab.operators import grouping as G
from adapterlab.operators import packing as P
from adapterlab.operators import schedule as S
from adapterlab.plans import planner
from adapterlab.plans.tuner import LAYOUTS, best_layout, profile_batches, profile_layouts, simulate_layouts
from adapterlab.samples import adapters_frame, clean_samples, het_adapters, layer_rows, order_microbatches, order_runs, oversize_counts, quarantine, token_samples
from adapterlab.session import broadcast_within, checkpointed
from adapterlab.simulate.pipeline import PipeConfig, simulate, simulate_pipeline
from adapterlab.simulate.sharded import simulate_dp, simulate_sharded, simulate_single
from adapterlab.sources.tables import load
from adapterlab.sources.weights import K, N, base_matrix, down_matrix, up_matrix

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
OPTIONS = planner.Options(capacity=Q.C, multiple=Q.P, nodes=1000)


def query(sql: str | None = None, name: str | None = None):
    def add(f: Query) -> Query:
        key = name or f.__name__
        QUERIES[key] = f
        if sql is not None:
            SQL[key] = sql
        return f

    return add


def samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_samples(spark, sf_dir, het_adapters(Q.G))


def batches(spark: SparkSession, sf_dir: str) -> DataFrame:
    return planner.global_batches(spark, samples(spark, sf_dir), het_adapters(Q.G), OPTIONS)


def stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return G.adapter_stats(samples(spark, sf_dir))


@query()
def flagship_schedule(spark, sf_dir):
    """All samples of four adapters on four datasets, scheduled by the full method."""
    return planner.plan_tables(spark, sf_dir, het_adapters(Q.G), OPTIONS).drop("merged")


# Sequences and batches

query(f"WITH {Q.SAMPLES} SELECT adapter_id, sample_id, dataset, CAST(tok_len AS BIGINT) AS tok_len, order_key FROM samples", "token_lengths")(samples)
query(f"""WITH {Q.SAMPLES} SELECT dataset, count(*) AS n, CAST(sum(tok_len) AS BIGINT) AS tokens, round(avg(tok_len), 6) AS mean, round(stddev_samp(tok_len), 4) AS sd,
  quantile_cont(tok_len, 0.5) AS p50, quantile_cont(tok_len, 0.95) AS p95, min(tok_len) AS shortest, max(tok_len) AS longest FROM samples GROUP BY 1""", "length_profile")(lambda s, d: B.length_profile(samples(s, d)))
query(f"WITH {Q.SAMPLES} SELECT dataset, tok_len // 128 AS bucket, count(*) AS n FROM samples GROUP BY 1, 2", "length_histogram")(lambda s, d: B.length_histogram(samples(s, d)))
query(f"WITH {Q.SAMPLES} SELECT adapter_id, CAST(sum(tok_len) AS BIGINT) AS real_tokens, CAST(sum({Q.pad('tok_len')}) AS BIGINT) AS padded_tokens FROM samples GROUP BY 1", "padded_lengths")(lambda s, d: B.padded_lengths(samples(s, d)))
query(f"""WITH {Q.SAMPLES} SELECT adapter_id, count(*) AS n_samples, count(*) FILTER (tok_len > {Q.C}) AS n_oversize, CAST(sum(tok_len) AS BIGINT) AS tokens,
  CAST(sum(greatest(tok_len - {Q.C}, 0)) AS BIGINT) AS lost_tokens FROM samples GROUP BY 1""", "oversize_counts")(lambda s, d: oversize_counts(samples(s, d), Q.C))
query(f"""WITH {Q.NUMBERED} SELECT adapter_id, rn // 4 AS mb, count(*) AS n, CAST(sum(tok_len) AS BIGINT) AS real_tokens, max(tok_len) * count(*) AS padded_tokens,
  CAST(max(tok_len) * count(*) - sum(tok_len) AS BIGINT) AS waste FROM numbered GROUP BY 1, 2""", "pad_batches")(lambda s, d: B.pad_batches(samples(s, d)))
PRESPLIT = f"""{Q.NUMBERED},
spread AS (SELECT *, CAST(sum(tok_len) OVER (PARTITION BY adapter_id ORDER BY rn) AS BIGINT) AS stop FROM numbered),
cut AS (SELECT adapter_id, stop - tok_len AS start, stop, unnest(generate_series((stop - tok_len) // 2048, (stop - 1) // 2048)) AS pack_id FROM spread),
prepacked AS (SELECT adapter_id, pack_id, count(*) AS n_samples, CAST(sum(least(stop, (pack_id + 1) * 2048) - greatest(start, pack_id * 2048)) AS BIGINT) AS tokens FROM cut GROUP BY 1, 2)"""
query(f"WITH {PRESPLIT} SELECT * FROM prepacked", "prepack_split")(lambda s, d: B.prepack_split(samples(s, d)))
query(f"""WITH RECURSIVE {Q.NUMBERED},
walk(adapter_id, shard, rn, pack_id, n_samples, tokens) AS (
  SELECT adapter_id, rn // 512, rn, CAST(0 AS BIGINT), CAST(1 AS BIGINT), least(tok_len, 2048) FROM numbered WHERE rn % 512 = 0
  UNION ALL
  SELECT w.adapter_id, w.shard, n.rn, CASE WHEN w.tokens + least(n.tok_len, 2048) > 2048 THEN w.pack_id + 1 ELSE w.pack_id END,
    CASE WHEN w.tokens + least(n.tok_len, 2048) > 2048 THEN 1 ELSE w.n_samples + 1 END,
    CASE WHEN w.tokens + least(n.tok_len, 2048) > 2048 THEN least(n.tok_len, 2048) ELSE w.tokens + least(n.tok_len, 2048) END
  FROM walk w JOIN numbered n ON n.adapter_id = w.adapter_id AND n.rn = w.rn + 1 AND n.rn // 512 = w.shard
)
SELECT adapter_id, CAST(shard AS BIGINT) AS shard, pack_id, max(n_samples) AS n_samples, CAST(max(tokens) AS BIGINT) AS tokens FROM walk GROUP BY 1, 2, 3""", "prepack_whole")(lambda s, d: B.prepack_whole(samples(s, d)))
query(f"""WITH {Q.NUMBERED},
spot AS (SELECT adapter_id, rn // 4 AS mb, rn, tok_len, CAST(coalesce(sum(tok_len) OVER (PARTITION BY adapter_id, rn // 4 ORDER BY rn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS o FROM numbered)
SELECT adapter_id, mb, CAST(sum(tok_len) AS BIGINT) AS tokens, string_agg(o::VARCHAR, ',' ORDER BY rn) AS offsets FROM spot GROUP BY 1, 2""", "pack_on_the_fly")(
    lambda s, d: B.pack_on_the_fly(samples(s, d)).withColumn("offsets", F.array_join(F.transform("offsets", lambda x: x.cast("string")), ",")))
query(f"""WITH {PRESPLIT},
batch AS (SELECT adapter_id, rn // 4 AS mb, count(*) AS n, sum(tok_len) AS real, max(tok_len) * count(*) AS padded FROM numbered GROUP BY 1, 2),
ways AS (SELECT 'padded' AS method, n, real, padded AS slots FROM batch UNION ALL SELECT 'prepacked', n_samples, tokens, 2048 FROM prepacked UNION ALL SELECT 'on_the_fly', n, real, real FROM batch)
SELECT method, count(*) AS batches, CAST(sum(real) AS BIGINT) AS real_tokens, CAST(sum(slots) AS BIGINT) AS slots, CAST((sum(slots) - sum(real)) * 1000 // sum(slots) AS BIGINT) AS waste_per_mille,
  min(n) AS min_samples, max(n) AS max_samples FROM ways GROUP BY 1""", "packing_compare")(lambda s, d: B.packing_report(samples(s, d)))
query(f"""WITH {Q.NUMBERED}, mb AS (SELECT adapter_id, rn // 4 AS mb, CAST(sum(tok_len) AS BIGINT) AS tokens FROM numbered GROUP BY 1, 2)
SELECT adapter_id, count(*) AS batches, max(tokens) AS max_tokens, CAST(max(tokens) * count(*) * 1000 // sum(tokens) AS BIGINT) AS max_over_mean_per_mille,
  round(stddev_pop(tokens) / avg(tokens), 6) AS variation FROM mb GROUP BY 1""", "microbatch_imbalance")(lambda s, d: B.imbalance(B.microbatch_tokens(samples(s, d)), ["adapter_id"]))
query("""SELECT 'short' AS dataset, count(*) AS n_samples, count(*) FILTER (coalesce(length(text), 0) = 0) AS n_quarantined FROM conversations
UNION ALL SELECT 'medium', count(*), count(*) FILTER (coalesce(length(text), 0) = 0) FROM documents UNION ALL SELECT 'long', count(*), count(*) FILTER (coalesce(length(html), 0) = 0) FROM pages
UNION ALL SELECT 'orders', count(*), count(*) FILTER (coalesce(q, 0) = 0) FROM orders LEFT JOIN (SELECT l_orderkey, sum(l_quantity) AS q FROM lineitem GROUP BY 1) ON o_orderkey = l_orderkey""", "quarantined")(lambda s, d: quarantine(s, d))
query("""WITH wd AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[ \\t\\n\\r]+'), lambda x: x <> '') AS w FROM documents),
wb AS (SELECT list_filter(regexp_split_to_array(lower(text), '[ \\t\\n\\r]+'), lambda x: x <> '') AS w FROM benchmark),
sd AS (SELECT doc_id, array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT doc_id, w, unnest(generate_series(1, len(w) - 7)) AS i FROM wd)),
sb AS (SELECT DISTINCT array_to_string(w[i:i + 7], ' ') AS s FROM (SELECT w, unnest(generate_series(1, len(w) - 7)) AS i FROM wb)),
leaked AS (SELECT DISTINCT doc_id FROM sd WHERE s IN (SELECT s FROM sb)),
firsts AS (SELECT min(doc_id) AS doc_id FROM documents GROUP BY md5(text))
SELECT d.doc_id, (length(text) + 3) // 4 AS tok_len FROM documents d WHERE doc_id IN (SELECT doc_id FROM labels WHERE quality = 1 AND toxic = 0)
  AND doc_id IN (SELECT doc_id FROM firsts) AND doc_id NOT IN (SELECT doc_id FROM leaked)""", "clean_samples")(lambda s, d: clean_samples(s, d))
query(f"""WITH {Q.SAMPLES}, r AS (SELECT adapter_id, sample_id, tok_len, row_number() OVER (PARTITION BY adapter_id ORDER BY tok_len DESC, sample_id) AS k FROM samples)
SELECT adapter_id, sample_id, CAST(tok_len AS BIGINT) AS tok_len, CAST(k AS INT) AS k FROM r WHERE k <= 10""", "topk_longest")(
    lambda s, d: samples(s, d).withColumn("k", F.expr("row_number() OVER (PARTITION BY adapter_id ORDER BY tok_len DESC, sample_id)")).where("k <= 10").select("adapter_id", "sample_id", "tok_len", "k"))

# Groups and global batches

query(f"WITH {Q.GROUPS} SELECT adapter_id, n_samples, tokens, mean_len FROM stats", "adapter_stats")(stats)
query(f"WITH {Q.GROUPS} SELECT adapter_id, mean_len, CAST(len_rank AS INT) AS len_rank, group_id FROM groups", "head_tail_groups")(lambda s, d: G.head_tail_groups(stats(s, d)))
query(f"""WITH {Q.GROUPS} SELECT 'pair' AS policy, adapter_id, group_id FROM groups UNION ALL SELECT 'singleton', adapter_id, CAST(len_rank - 1 AS INT) FROM groups
UNION ALL SELECT 'single', adapter_id, 0 FROM groups UNION ALL SELECT 'k_groups', adapter_id, group_id % 2 FROM groups""", "group_policies")(
    lambda s, d: _union([G.group_adapters(checkpointed(stats(s, d)), p).select(F.lit(p).alias("policy"), "adapter_id", "group_id") for p in ("pair", "singleton", "single", "k_groups")]))
query(f"WITH {Q.BATCHES} SELECT group_id, gb, adapter_id, sample_id, tok_len, rn FROM batches", "global_batches")(batches)
query(f"""WITH {Q.BATCHES}, full_ AS (SELECT adapter_id, gb FROM batches GROUP BY 1, 2 HAVING count(DISTINCT rn) = {Q.G})
SELECT adapter_id, count(DISTINCT rn) AS n FROM batches SEMI JOIN full_ USING (adapter_id, gb) GROUP BY 1""", "global_batches_drop_last")(
    lambda s, d: G.assign_global_batches(samples(s, d), adapters_frame(s, het_adapters(Q.G)), G.head_tail_groups(stats(s, d)), drop_last=True).groupBy("adapter_id").agg(F.count(F.lit(1)).alias("n")))


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# Packing

for _rule in P.RULES:
    query(f"{Q.greedy(_rule)} SELECT group_id, gb, bin, adapter_id, sample_id, tok_len FROM packed", f"greedy_{_rule}")(lambda s, d, rule=_rule: P.pack_greedy(batches(s, d), Q.C, Q.P, rule))
LOADS = f"""per AS (SELECT group_id, gb, bin, adapter_id, count(*) AS n, sum(tok_len) AS t FROM packed GROUP BY 1, 2, 3, 4),
loads AS (SELECT group_id, gb, bin, CAST(sum(n) AS BIGINT) AS n_samples, count(*) AS n_adapters, CAST(sum(t) AS BIGINT) AS real_tokens, CAST(sum({Q.pad('t')}) AS BIGINT) AS padded_tokens FROM per GROUP BY 1, 2, 3)"""
ffd = lambda s, d: P.pack_greedy(batches(s, d), Q.C, Q.P, "ffd")
query(f"{Q.greedy('ffd')}, {LOADS} SELECT * FROM loads", "greedy_loads")(lambda s, d: P.bin_loads(ffd(s, d), Q.P))
query(f"""{Q.greedy('ffd')}, {LOADS}, small AS (SELECT group_id, gb, min(padded_tokens) AS least FROM loads GROUP BY 1, 2),
f AS (SELECT group_id, CAST(sum(least) * 1000 // (count(*) * {Q.C}) AS BIGINT) AS smallest_fill FROM small GROUP BY 1)
SELECT group_id, count(*) AS microbatches, CAST((sum(padded_tokens) - sum(real_tokens)) * 1000 // sum(padded_tokens) AS BIGINT) AS waste,
  CAST(sum(padded_tokens) * 1000 // (count(*) * {Q.C}) AS BIGINT) AS fill, count(*) FILTER (padded_tokens < {Q.C} * 0.5) AS underfilled, any_value(smallest_fill) AS smallest_fill
FROM loads JOIN f USING (group_id) GROUP BY 1""", "packing_quality")(lambda s, d: M.packing_quality(P.bin_loads(ffd(s, d), Q.P), Q.C))


def packed(spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    return P.pack_batches(batches(spark, sf_dir), Q.C, Q.P, **({"nodes": 1000} | options))


@query(f"""{Q.greedy('ffd')},
have AS (SELECT group_id, gb, max(bin) + 1 AS greedy_bins FROM packed GROUP BY 1, 2),
vol AS (SELECT group_id, gb, adapter_id, sum(tok_len) AS t FROM batches GROUP BY 1, 2, 3),
low AS (SELECT group_id, gb, -(-sum({Q.pad('t')}) // {Q.C}) AS volume FROM vol GROUP BY 1, 2)
SELECT group_id, gb, true AS at_least_volume, true AS at_most_greedy FROM have JOIN low USING (group_id, gb)""")
def exact_bins_within_bounds(spark, sf_dir):
    """Number of microbatches of the exact path against the volume bound and the greedy count."""
    rows = checkpointed(batches(spark, sf_dir))
    exact = P.pack_batches(rows, Q.C, Q.P, nodes=400).groupBy("group_id", "gb").agg((F.max("bin") + 1).alias("n"))
    greedy = P.pack_greedy(rows, Q.C, Q.P).groupBy("group_id", "gb").agg((F.max("bin") + 1).alias("most"))
    total = rows.groupBy("group_id", "gb", "adapter_id").agg(F.sum("tok_len").alias("t")).groupBy("group_id", "gb").agg(F.ceil(F.expr(f"sum((t + {Q.P - 1}) div {Q.P} * {Q.P})") / Q.C).alias("least"))
    return exact.join(greedy, ["group_id", "gb"]).join(total, ["group_id", "gb"]).select("group_id", "gb", (F.col("n") >= F.col("least")).alias("at_least_volume"), (F.col("n") <= F.col("most")).alias("at_most_greedy"))


@query()
def exact_min_bins(spark, sf_dir):
    return packed(spark, sf_dir).groupBy("group_id", "gb").agg((F.max("bin") + 1).alias("bins"), F.max("stage1").alias("stage1"))


@query()
def exact_min_smallest(spark, sf_dir):
    rows = checkpointed(packed(spark, sf_dir))
    ends = rows.groupBy("group_id", "gb").agg(F.max("stage2").alias("stage2"), F.max("solver_path").alias("solver_path"))
    return P.bin_loads(rows, Q.P).groupBy("group_id", "gb").agg(F.min("padded_tokens").alias("smallest")).join(ends, ["group_id", "gb"])


query(None, "two_stage_choice")(lambda s, d: P.solver_report(packed(s, d)))
NO_PACK = "SELECT CAST(NULL AS VARCHAR) AS kind, CAST(NULL AS INT) AS group_id, CAST(NULL AS BIGINT) AS gb, CAST(NULL AS VARCHAR) AS detail WHERE 1 = 0"


@query(NO_PACK)
def packing_violations(spark, sf_dir):
    rows = checkpointed(batches(spark, sf_dir))
    return P.packing_violations(checkpointed(P.pack_batches(rows, Q.C, Q.P, nodes=1000)), rows, Q.C, Q.P)


# Schedule

POSITIONS = f"""{Q.greedy('ffd')}, order_ AS (SELECT group_id, gb, bin, row_number() OVER (ORDER BY gb, group_id, bin) - 1 AS pos FROM (SELECT DISTINCT group_id, gb, bin FROM packed))"""
query(f"{POSITIONS} SELECT group_id, gb, bin, pos FROM order_", "interleaved_schedule")(lambda s, d: S.interleaved_positions(ffd(s, d)).select("group_id", "gb", "bin", F.col("pos").cast("bigint").alias("pos")))
VIOLATIONS = f"""{POSITIONS}, spot AS (SELECT DISTINCT p.adapter_id, p.gb, o.pos FROM packed p JOIN order_ o USING (group_id, gb, bin)),
span AS (SELECT adapter_id, gb, min(pos) AS first_pos, max(pos) AS last_pos FROM spot GROUP BY 1, 2)
SELECT a.adapter_id, a.gb, a.first_pos, b.last_pos AS previous_last FROM span a JOIN span b ON a.adapter_id = b.adapter_id AND a.gb = b.gb + 1 WHERE a.first_pos - b.last_pos < {Q.GAP}"""


@query(VIOLATIONS)
def spacing_violations_before(spark, sf_dir):
    items = checkpointed(ffd(spark, sf_dir))
    at = items.join(S.interleaved_positions(items), ["group_id", "gb", "bin"]).select("adapter_id", "gb", F.col("pos").cast("bigint").alias("pos")).distinct()
    return G.spacing_violations(at, Q.GAP)


@query("SELECT CAST(NULL AS VARCHAR) AS adapter_id, CAST(NULL AS BIGINT) AS gb, CAST(NULL AS BIGINT) AS first_pos, CAST(NULL AS BIGINT) AS previous_last WHERE 1 = 0")
def spacing_violations_after(spark, sf_dir):
    return S.schedule_spacing(flagship_schedule(spark, sf_dir), Q.GAP)


@query(f"""WITH {Q.GROUPS} SELECT adapter_id, n_samples, CAST(sum(tok_len) AS BIGINT) AS tokens, (n_samples + {Q.G - 1}) // {Q.G} AS batches
FROM samples JOIN stats USING (adapter_id) GROUP BY 1, 2""")
def verify_and_fix(spark, sf_dir):
    """What the repaired schedule holds, by adapter."""
    rows = flagship_schedule(spark, sf_dir).where("NOT is_noop")
    return rows.groupBy("adapter_id").agg(F.count_distinct("sample_id").alias("n_samples"), F.sum("tok_len").alias("tokens"), F.count_distinct("batch").alias("batches"))


@query("SELECT CAST(NULL AS VARCHAR) AS kind, CAST(NULL AS VARCHAR) AS adapter_id, CAST(NULL AS BIGINT) AS gb, CAST(NULL AS VARCHAR) AS detail WHERE 1 = 0")
def lossless_check(spark, sf_dir):
    """The schedule against its batches, and its tokens against the samples as the tables have them."""
    rows = checkpointed(batches(spark, sf_dir))
    schedule = checkpointed(planner.schedule_batches(rows, OPTIONS))
    have = _whole(schedule.where("NOT is_noop"))
    cut = _whole(samples(spark, sf_dir)).exceptAll(have).select(F.lit("cut").alias("kind"), "adapter_id", F.lit(None).cast("bigint").alias("gb"), F.col("sample_id").cast("string").alias("detail"))
    return S.lossless_violations(schedule, rows).unionByName(cut)


def _whole(rows: DataFrame) -> DataFrame:
    return rows.groupBy("adapter_id", "sample_id").agg(F.sum("tok_len").alias("tok_len"))


@query(f"WITH {Q.BATCHES} SELECT adapter_id, gb, count(*) AS n, true AS in_order FROM batches GROUP BY 1, 2")
def boundary_table(spark, sf_dir):
    """Samples of each optimizer step, and whether steps of an adapter come one after the other."""
    rows = checkpointed(flagship_schedule(spark, sf_dir))
    ends = S.boundary_table(rows)
    n = rows.where("NOT is_noop").groupBy("adapter_id", F.col("batch").alias("gb")).agg(F.count(F.lit(1)).alias("n"))
    order = F.expr("coalesce(done_pos > lag(done_pos) OVER (PARTITION BY adapter_id ORDER BY gb), true)")
    return ends.withColumn("in_order", order).join(n, ["adapter_id", "gb"]).select("adapter_id", "gb", "n", "in_order")


query("SELECT CAST(NULL AS VARCHAR) AS adapter_id, CAST(NULL AS BIGINT) AS sample_id, CAST(NULL AS BIGINT) AS tok_len WHERE 1 = 0", "schedule_multiset_equal")(lambda s, d: _multiset(s, d))


def _multiset(spark, sf_dir):
    rows = checkpointed(batches(spark, sf_dir))
    have = _whole(planner.schedule_batches(rows, OPTIONS).where("NOT is_noop"))
    want = _whole(samples(spark, sf_dir))
    return have.exceptAll(want).unionByName(want.exceptAll(have))


query(None, "merge_pass")(W.merge_counts)
query(None, "simulate_segments")(lambda s, d: planner.simulate_schedule(flagship_schedule(s, d), 4))

# Baselines and simulators

MICRO = f"""{Q.BATCHES}, lo AS (SELECT adapter_id, gb, min(rn) AS lo FROM batches GROUP BY 1, 2),
micro AS (SELECT adapter_id, gb, CAST((rn - lo) // 4 AS BIGINT) AS mb, count(*) AS n, CAST(sum(tok_len) AS BIGINT) AS tokens, CAST({Q.pad('sum(tok_len)')} AS BIGINT) AS cost_tokens FROM batches JOIN lo USING (adapter_id, gb) GROUP BY 1, 2, 3)"""
micro = lambda s, d: BL.fixed_microbatches(batches(s, d))
query(f"WITH {MICRO} SELECT *, row_number() OVER (ORDER BY adapter_id, gb, mb) - 1 AS pos FROM micro", "baseline_pipeline")(lambda s, d: BL.baseline_pipeline(micro(s, d)).withColumn("pos", F.col("pos").cast("bigint")))
query(f"WITH {MICRO} SELECT *, row_number() OVER (ORDER BY gb, mb, adapter_id) - 1 AS pos FROM micro", "baseline_uniform_fill")(lambda s, d: BL.baseline_uniform_fill(micro(s, d)).withColumn("pos", F.col("pos").cast("bigint")))
query(f"""WITH {MICRO} SELECT adapter_id, gb, mb // 4 AS step, max(cost_tokens) AS step_tokens, CAST(max(cost_tokens) * 4 - sum(cost_tokens) AS BIGINT) AS lost_tokens FROM micro GROUP BY 1, 2, 3""", "baseline_sharded")(lambda s, d: BL.baseline_sharded(micro(s, d)))
query(f"""WITH {MICRO}, spot AS (SELECT *, row_number() OVER (ORDER BY adapter_id, gb, mb) - 1 AS pos FROM micro),
step AS (SELECT adapter_id AS run_id, pos // 4 AS step, max(cost_tokens * 3) AS slowest, sum(cost_tokens * 3) AS work, sum(cost_tokens) AS tokens FROM spot GROUP BY 1, 2)
SELECT run_id, CAST(sum(greatest(slowest, 3000)) AS BIGINT) AS makespan, CAST((4 * sum(slowest) - sum(work)) * 1000 // (4 * sum(slowest)) AS BIGINT) AS idle_per_mille, CAST(sum(tokens) AS BIGINT) AS tokens FROM step GROUP BY 1""", "simulate_sharded")(
    lambda s, d: simulate_sharded(BL.baseline_pipeline(micro(s, d)).select(F.col("adapter_id").alias("run_id"), "pos", F.col("cost_tokens").alias("tokens")), 4, comm=3000))
query(f"WITH {MICRO} SELECT adapter_id AS run_id, CAST(sum(cost_tokens) * 3 AS BIGINT) AS makespan, CAST(sum(cost_tokens) AS BIGINT) AS tokens FROM micro GROUP BY 1", "simulate_single")(
    lambda s, d: simulate_single(micro(s, d).select(F.col("adapter_id").alias("run_id"), F.col("cost_tokens").alias("tokens"))))
query(f"""WITH {MICRO} SELECT adapter_id AS run_id, CAST(sum(cost_tokens) AS BIGINT) AS tokens, CAST(sum(cost_tokens) * 3 AS BIGINT) AS makespan, round(sum(cost_tokens) * 1000.0 / (sum(cost_tokens) * 3), 6) AS rate FROM micro GROUP BY 1""", "throughput")(
    lambda s, d: M.throughput(simulate_single(micro(s, d).select(F.col("adapter_id").alias("run_id"), F.col("cost_tokens").alias("tokens")))))
query(f"WITH {Q.BATCHES} SELECT count(*) AS rows FROM batches", "spark_side_cost")(lambda s, d: _observed(s, batches(s, d)))
query(f"WITH {Q.RUNS_SQL} SELECT 'S' || s || '/M' || m AS run_id, round((s - 1.0) / (m + s - 1), 6) AS bubble, round(1 - (s - 1.0) / (m + s - 1), 6) AS utilization FROM (VALUES (1), (2), (4), (8)) a(s), runs", "bubble_of_trace")(lambda s, d: _traces(s, d))


def _observed(spark, df):
    """Rows of a frame, observed while it runs."""
    seen_df, seen = M.observe_cost(df)
    seen_df.write.format("noop").mode("overwrite").save()
    return spark.createDataFrame([(seen.get["rows"],)], "rows bigint")


def _traces(spark, sf_dir):
    """Bubble and utilization from the events of simulated runs, per number of stages; as many equal microbatches as orders have lines."""
    runs, out = checkpointed(order_runs(spark, sf_dir).select("m")), []
    for stages in (1, 2, 4, 8):

        def events(pdfs, stages=stages):
            for pdf in pdfs:
                for m in pdf["m"].tolist():
                    found = simulate([(100, [("a", 0)])] * m, PipeConfig(stages=stages), keep_events=True).events
                    yield pd.DataFrame([(f"S{stages}/M{m}", e[3], e[4]) for e in found], columns=["run_id", "start", "end"])

        out.append(M.utilization(M.bubble_ratio(runs.mapInPandas(events, "run_id string, start double, end double"), stages)))
    return _union(out)


query(f"""WITH {MICRO}, work AS (SELECT adapter_id AS run_id, gb, mb % 2 AS replica, sum(cost_tokens) AS w, max(cost_tokens) AS longest FROM micro GROUP BY 1, 2, 3),
step AS (SELECT run_id, gb, max(w + 3 * longest) AS took, sum(w) AS tokens FROM work GROUP BY 1, 2)
SELECT run_id, CAST(sum(took) * 3 AS BIGINT) AS makespan, CAST(sum(tokens) AS BIGINT) AS tokens FROM step GROUP BY 1""", "simulate_data_parallel")(
    lambda s, d: simulate_dp(micro(s, d).select(F.col("adapter_id").alias("run_id"), "gb", F.col("mb").alias("pos"), F.col("cost_tokens").alias("tokens")), 2, 4))


@query(f"""WITH {Q.RUNS_SQL} SELECT 'S' || s || '/M' || m AS run_id, CAST(m AS BIGINT) AS microbatches, round((s - 1.0) / (m + s - 1), 6) AS bubble, orders
FROM (VALUES (1), (2), (4), (8)) a(s), runs""")
def bubble_uniform(spark, sf_dir):
    """Equal microbatches with one flush, one for each line of an order, simulated once for each number; the closed form is (S - 1) / (M + S - 1)."""
    stages = spark.createDataFrame([(s,) for s in (1, 2, 4, 8)], "stages int")
    grid = checkpointed(order_runs(spark, sf_dir).crossJoin(F.broadcast(stages)).withColumn("run_id", F.format_string("S%d/M%d", "stages", "m")))
    key = F.array(F.struct(F.lit("a").alias("adapter_id"), F.lit(0).cast("bigint").alias("batch")))
    runs = grid.withColumn("pos", F.explode(F.sequence(F.lit(0), F.col("m") - 1))).select("run_id", "pos", F.lit(100).alias("cost_tokens"), F.lit(100).alias("real_tokens"), key.alias("keys"), "stages")
    return simulate_pipeline(runs).join(grid, "run_id").select("run_id", "microbatches", F.round("bubble", 6).alias("bubble"), "orders")


query(f"""WITH l AS (SELECT (length(text) + 3) // 4 AS t FROM documents WHERE length(text) > 0), mean AS (SELECT sum(t) // count(*) AS mean FROM l)
SELECT CAST(g AS INT) AS global_batch, CAST(g * mean * 4 * 1000 // ((g + 3) * mean * 3) AS BIGINT) AS pipeline_rate,
  CAST(g * mean * 1000 // (greatest(ceil(g / 4.0)::BIGINT * mean * 3, 2000) + 2000) AS BIGINT) AS sharded_rate FROM (VALUES (4), (8), (16), (32)) t(g), mean""", "ideal_vs_batch")(W.w4_ideal_batches)
query(None, "bubble_by_adapters")(W.w13_bubbles)
query(None, "simulate_end_to_end")(W.w8_end_to_end)
query(None, "practical_against_ideal")(W.w6_practical_against_ideal)


@query()
def speedup_cube(spark, sf_dir):
    runs = W.w8_end_to_end(spark, sf_dir)
    parts = F.split("workload", "/")
    return runs.select(parts[0].alias("model"), parts[1].alias("dataset"), "method", "speedup").cube("model", "dataset", "method").agg(F.round(F.avg("speedup"), 6).alias("mean"), F.max("speedup").alias("largest"))


LAYOUT_ROWS = ", ".join(f"('{k}', {d}, {c}, {f})" for k, d, c, f in LAYOUTS)
LAYOUT_SQL = f"""WITH l(kind, degree, lim, fixed) AS (VALUES {LAYOUT_ROWS}), c(capacity) AS (VALUES (1024), (2048), (4096), (8192)),
g AS (SELECT *, (capacity + fixed) * 3 AS step FROM l, c),
p AS (SELECT kind, degree, capacity, capacity <= lim AS feasible, CAST(floor(32.0 * capacity * CASE WHEN kind = 'single' THEN 1 ELSE degree END * 1000 /
  CASE kind WHEN 'pipeline' THEN (31 + degree) * step WHEN 'sharded' THEN ceil(32.0 / degree) * (step + 1600) * degree ELSE 32 * step END) AS BIGINT) AS rate FROM g)"""
query(f"{LAYOUT_SQL} SELECT * FROM p", "profile_layouts")(lambda s, d: profile_layouts(s))
query(f"""WITH {Q.ORDER_BATCHES.format(n=256)}, l(kind, degree, lim, fixed) AS (VALUES {LAYOUT_ROWS}), c(capacity) AS (VALUES (1024), (2048), (4096), (8192)),
g AS (SELECT *, (tokens + capacity - 1) // capacity AS n, (capacity + fixed) * 3 AS step FROM mbs, l, c WHERE capacity <= lim),
p AS (SELECT kind, degree, capacity, CAST(sum(tokens) * CASE WHEN kind = 'single' THEN 1 ELSE degree END * 1000 //
  sum(CASE kind WHEN 'pipeline' THEN (n + degree - 1) * step WHEN 'sharded' THEN ((n + degree - 1) // degree) * (step + 1600) * degree ELSE n * step END) AS BIGINT) AS rate FROM g GROUP BY kind, degree, capacity)
SELECT kind, degree, capacity, rate FROM p ORDER BY rate DESC, capacity DESC, kind DESC, degree DESC LIMIT 1""", "best_layout")(
    lambda s, d: best_layout(profile_batches(order_microbatches(s, d, 256))))
query(None, "tune")(W.tune_loop)
query(f"{LAYOUT_SQL} SELECT * FROM p", "simulate_layouts")(lambda s, d: simulate_layouts(s))
query(None, "tenant_jobs")(W.w19_tenants)
query(None, "scheduling_against_training")(W.w14_overlap)
query(None, "scaling_dp_vs_job")(W.w10_scaling)
query(None, "ablation_merge")(W.w15_ablation)
query(None, "ablation_solver")(W.w15_solver_paths)
query(None, "breakdown_six")(W.w16_breakdown)
query(None, "budgets")(W.w17_budgets)
query(None, "budgets_large")(lambda s, d: W.w17_budgets(s, d, (100_000,)))
query(None, "second_hardware")(W.w9_second_hardware)
query(None, "hyperparameter_jobs")(W.w19_tuning_jobs)
query(None, "scheduling_time")(W.w14_fit)


@query("""WITH t(samples, seconds) AS (VALUES (640, 15.74), (25600, 102.12)) SELECT round(regr_slope(seconds, samples) * 1000, 6) AS ms_per_sample,
  round(regr_intercept(seconds, samples), 6) AS fixed_seconds, round(regr_r2(seconds, samples), 6) AS r2 FROM t""")
def tuning_time_fit(spark, sf_dir):
    """The fit over the two published points."""
    return M.tuning_fit(spark.createDataFrame([(640, 15.74), (25600, 102.12)], "samples bigint, seconds double"))


@query("""WITH t AS (SELECT i AS gb, 40 + i * 7 % 30 AS schedule_time, 30 + i * 5 % 40 AS train_time FROM generate_series(0, 11) s(i))
SELECT gb, CAST(schedule_time AS BIGINT) AS schedule_time, CAST(train_time AS BIGINT) AS train_time, CAST(greatest(schedule_time - lag(train_time, 1, 0) OVER (ORDER BY gb), 0) AS BIGINT) AS exposed FROM t""")
def scheduling_overlap(spark, sf_dir):
    rows = spark.range(12).select(F.col("id").alias("gb"), (F.lit(40) + F.col("id") * 7 % 30).alias("schedule_time"), (F.lit(30) + F.col("id") * 5 % 40).alias("train_time"))
    return M.overlap(rows)


# Costs

shapes = lambda s: C.shapes_frame(s, Q.SHAPES)
layers = lambda s, d: C.layers_of(layer_rows(s, d), [x[1:] for x in Q.SHAPES])
query(f"""WITH {Q.SHAPES_SQL} SELECT 16 AS per_trainable, k, n, r, 16*n*k AS full_bytes, 2*n*k + 16*r*(n+k) AS adapter_bytes, 16*n*k*1000 // (2*n*k + 16*r*(n+k)) AS reduction_per_mille FROM shapes
UNION ALL SELECT 32, k, n, r, 16*n*k, 2*n*k + 32*r*(n+k), 16*n*k*1000 // (2*n*k + 32*r*(n+k)) FROM shapes""", "state_memory")(
    lambda s, d: _union([M.state_memory(shapes(s), c).select(F.lit(c).alias("per_trainable"), "*") for c in (16, 32)]))
query(f"WITH {Q.SHAPES_SQL} SELECT k, n, r, r*(n+k)*1000000 // (n*k) AS both_ppm, r*1000000 // n AS one_ppm FROM shapes", "param_ratio")(lambda s, d: M.param_ratio(shapes(s)))
query(f"""WITH {Q.LAYERS_SQL}, v AS (SELECT m, k, n, r, 1000*m*k*n // (m*k + k*n + m*n) AS base_thousandths, 1000*m*k*r // (m*k + k*r + m*r) AS down_thousandths, 1000*m*r*n // (m*r + r*n + m*n) AS up_thousandths FROM shapes)
SELECT *, base_thousandths < 295000 AS base_memory_bound, down_thousandths < 295000 AS down_memory_bound, up_thousandths < 295000 AS up_memory_bound FROM v""", "intensity")(lambda s, d: M.intensity(layers(s, d)))
query(f"WITH {Q.TOTALS_SQL} SELECT impl, direction, m, k, n, r, bytes, flops FROM totals", "traffic_ledger")(lambda s, d: C.traffic_totals(C.traffic_ledger(shapes(s))).where("impl IN ('frozen', 'naive', 'split')"))
query(f"""WITH {Q.TOTALS_SQL}, b AS (SELECT m, k, n, r, sum(bytes) FILTER (impl = 'frozen') AS f, sum(bytes) FILTER (impl = 'naive') AS a, sum(bytes) FILTER (impl = 'split') AS s FROM totals GROUP BY 1, 2, 3, 4)
SELECT m, k, n, r, CAST(a * 1000 // f AS BIGINT) AS naive_to_frozen, CAST(s * 1000 // f AS BIGINT) AS split_to_frozen, CAST(s * 1000 // a AS BIGINT) AS split_to_naive FROM b""", "traffic_ratio")(
    lambda s, d: C.traffic_ratio(C.traffic_ledger(shapes(s))).select("m", "k", "n", "r", "naive_to_frozen", "split_to_frozen", "split_to_naive"))
query(None, "traffic_calibrated")(W.w3_traffic)
query(f"""WITH {Q.SHAPES_SQL}, t AS (
  SELECT 'base' AS class, m, k, n, r, greatest(2*m*k*n, 295 * 2 * (m*k + k*n + m*n)) AS time FROM shapes
  UNION ALL SELECT 'adapter', m, k, n, r, greatest(2*m*k*r, 295 * 2 * (m*k + k*r + m*r)) + greatest(2*m*r*n, 295 * 2 * (m*r + r*n + m*n)) FROM shapes
  UNION ALL SELECT 'element', m, k, n, r, 295 * (5*m*k + 4*m*n + 6*m*n) FROM shapes),
u AS (SELECT 'forward' AS direction, * FROM t
  UNION ALL SELECT 'backward', 'base', m, k, n, r, greatest(2*m*k*n, 295 * 2 * (m*k + k*n + m*n)) FROM shapes
  UNION ALL SELECT 'backward', 'adapter', m, k, n, r, 2 * greatest(2*m*k*r, 295 * 2 * (m*k + k*r + m*r)) + 2 * greatest(2*m*r*n, 295 * 2 * (m*r + r*n + m*n)) FROM shapes
  UNION ALL SELECT 'backward', 'element', m, k, n, r, 295 * (4*m*n + 11*m*k) FROM shapes)
SELECT direction, class, m, k, n, r, CAST(time * 1000 // sum(time) OVER (PARTITION BY direction, m, k, n, r) AS BIGINT) AS per_mille FROM u""", "runtime_breakdown")(
    lambda s, d: C.runtime_breakdown(C.traffic_ledger(shapes(s))))
# Times of the whole layer from the totals by hand; forms of several operators are summed operator by operator.
LAYER_TIMES = f"""{{shapes}}, op AS (
  SELECT 'frozen' AS impl, 'forward' AS direction, *, greatest(2*m*k*n, 590*(m*k + k*n + m*n)) AS time FROM shapes
  UNION ALL SELECT 'frozen', 'backward', *, greatest(2*m*k*n, 590*(m*k + k*n + m*n)) FROM shapes
  UNION ALL SELECT 'naive', 'forward', *, greatest(2*m*k*n, 590*(m*k + k*n + m*n)) + greatest(2*m*k*r, 590*(m*k + k*r + m*r)) + greatest(2*m*r*n, 590*(m*r + r*n + m*n)) + 295*(5*m*k + 10*m*n) FROM shapes
  UNION ALL SELECT 'naive', 'backward', *, greatest(2*m*k*n, 590*(m*k + k*n + m*n)) + 2*greatest(2*m*k*r, 590*(m*k + k*r + m*r)) + 2*greatest(2*m*r*n, 590*(m*r + r*n + m*n)) + 295*(4*m*n + 11*m*k) FROM shapes
  UNION ALL SELECT 'split', 'forward', *, greatest(2*m*k*r, 295*(5*m*k + 2*k*r + 2*m*r)) + greatest(2*m*k*n + 2*m*r*n, 590*(m*k + k*n + m*r + r*n + m*n)) FROM shapes
  UNION ALL SELECT 'split', 'backward', *, greatest(4*m*r*n, 590*(m*n + 2*m*r + 2*r*n)) + greatest(2*m*k*r, 590*(m*k + k*r + m*r)) + greatest(2*m*k*n + 2*m*k*r, 295*(2*m*n + 2*k*n + 2*m*r + 2*k*r + 3*m*k)) FROM shapes)"""
query(f"""WITH {LAYER_TIMES.replace('{shapes}', Q.LAYERS_SQL)}, f AS (SELECT direction, m, k, n, r, time AS base FROM op WHERE impl = 'frozen')
SELECT impl, direction, m, k, n, r, CAST(base * 1000 // time AS BIGINT) AS speed_per_mille FROM op JOIN f USING (direction, m, k, n, r)""", "layer_speed_by_hand")(
    lambda s, d: C.layer_sweep(C.traffic_ledger(layers(s, d))).where("impl IN ('frozen', 'naive', 'split')"))
query(f"""WITH {LAYER_TIMES.replace('{shapes}', Q.SHAPES_SQL)}, f AS (SELECT direction, m, k, n, r, time AS base FROM op WHERE impl = 'naive')
SELECT impl, direction, m, k, n, r, CAST(base * 1000 // time AS BIGINT) AS speedup_per_mille FROM op JOIN f USING (direction, m, k, n, r) WHERE impl = 'split'""", "split_speed_by_hand")(
    lambda s, d: C.kernel_speedup(C.traffic_ledger(shapes(s))).where("impl = 'split'"))
query(None, "layer_slowdown")(W.w1_layer_slowdown)
query(None, "kernel_speedup")(W.w11_kernels)
query(None, "layer_speedup")(W.w12_layers)
query("""WITH m AS (SELECT mb, count(*) AS adapters FROM (SELECT DISTINCT o_orderkey // 16 AS mb, o_orderpriority FROM orders WHERE o_orderkey IS NOT NULL) GROUP BY 1),
t AS (SELECT count(*) AS microbatches, coalesce(sum(adapters), 0) AS adapters FROM m)
SELECT impl, microbatches, CAST(once * microbatches + each * adapters AS BIGINT) AS launches
FROM t, (VALUES ('frozen', 2, 0), ('naive', 14, 0), ('compiled', 12, 0), ('split', 5, 0), ('looped', 0, 5), ('routed', 5, 0), ('merged_launch', 14, 0)) f(impl, once, each)""", "launches")(
    lambda s, d: C.launches(load(s, d, "orders").where("o_orderkey IS NOT NULL").select(F.expr("o_orderkey div 16").alias("mb"), F.col("o_orderpriority").alias("adapter_id"))))

# Layer algebra in fixed point

x = x_rows
y_of = lambda df: L.cells(df, "y")
query(Q.FROZEN_FORWARD, "frozen_forward_fx")(lambda s, d: y_of(L.frozen_forward(x(s, d), base_matrix())))
query(Q.FROZEN_BACKWARD, "frozen_backward_fx")(lambda s, d: L.cells(L.frozen_backward(with_gradient(x(s, d)), base_matrix()), "dx"))
for _name, _f in {"naive": L.naive_forward, "compiled": L.compiled_forward, "split": L.split_forward, "routed": L.routed_forward, "looped": L.looped_forward, "recompute": L.fullfuse_recompute, "sync": L.fullfuse_sync}.items():
    query(Q.FORWARD, f"{_name}_forward_fx")(lambda s, d, f=_f: y_of(f(x(s, d), base_matrix(), default_bank())))
query(Q.GRAD_A, "grad_a_fx")(lambda s, d: L.routed_backward(with_gradient(x(s, d)), base_matrix(), default_bank())["da"])
query(Q.GRAD_B, "grad_b_fx")(lambda s, d: L.routed_backward(with_gradient(x(s, d)), base_matrix(), default_bank())["db"])
query(Q.GRAD_X, "grad_x_fx")(lambda s, d: L.cells(L.routed_backward(with_gradient(x(s, d)), base_matrix(), default_bank())["dx"], "dx"))
query(Q.GRAD_A, "naive_grad_a_fx")(lambda s, d: L.naive_backward(with_gradient(x(s, d)), base_matrix(), default_bank())["da"])
query(Q.GRAD_B, "naive_grad_b_fx")(lambda s, d: L.naive_backward(with_gradient(x(s, d)), base_matrix(), default_bank())["db"])
query(Q.GRAD_X, "naive_grad_x_fx")(lambda s, d: L.cells(L.naive_backward(with_gradient(x(s, d)), base_matrix(), default_bank())["dx"], "dx"))
query("SELECT * FROM (VALUES ('y', 0), ('dx', 0)) t(result, unequal)", "numerical_agreement")(lambda s, d: W.w18_agreement(s, d).select("result", F.col("unequal").cast("int").alias("unequal")))


@query(Q.MASK)
def dropout_masks(spark, sf_dir):
    bank = default_bank()
    p = F.element_at(F.create_map(*[v for a, w in bank.items() for v in (F.lit(a), F.lit(w.dropout))]), F.col("adapter_id"))
    seed = F.element_at(F.create_map(*[v for a, w in bank.items() for v in (F.lit(a), F.lit(w.seed))]), F.col("adapter_id"))
    cells = x(spark, sf_dir).select("row_id", "adapter_id", F.posexplode("x").alias("j", "v"))
    return cells.select("row_id", "j", dropout_mask(F.col("row_id"), F.col("j"), seed, p).alias("kept"))


query("""WITH r AS (SELECT 'a' || (label % 4)::VARCHAR AS adapter_id, vec_id, row_number() OVER (PARTITION BY label % 4 ORDER BY vec_id) - 1 AS rn FROM embeddings)
SELECT adapter_id, rn // 32 AS tile, min(vec_id) AS first_row, max(vec_id) AS last_row, count(*) AS n FROM r GROUP BY 1, 2""", "tile_table")(lambda s, d: build_tiles(x(s, d)))


@query(f"""WITH {Q.FX.split('bank(')[0].rstrip().rstrip(',')}, b AS (SELECT i, j, v, i // 16 AS block FROM w), sc AS (SELECT j, block, greatest(max(abs(v)), 1) AS scale FROM b GROUP BY 1, 2)
SELECT CAST(b.j AS INT) AS j, CAST(b.block AS INT) AS block, sc.scale, CAST(b.i AS INT) AS i, CAST(floor((14 * b.v + sc.scale) / (2.0 * sc.scale)) AS INT) AS code FROM b JOIN sc USING (j, block)""", "quantize4")
def _quantize4(spark, sf_dir):
    m = base_matrix()
    cells = spark.createDataFrame([(i, j, int(m[i, j])) for i in range(K) for j in range(N)], "i int, j int, v bigint")
    return quantize4(spark, cells)


query(None, "variant_magnitude")(lambda s, d: L.cells(magnitude_forward(x(s, d), base_matrix(), default_bank()), "y"))


@query(None, "variant_shared_random")
def _shared_random(spark, sf_dir):
    import numpy as np

    vectors = {f"a{a}": (np.arange(16) / 16 + a, np.arange(N) / N - a) for a in range(4)}
    return L.cells(shared_random_forward(x(spark, sf_dir), base_matrix().astype(float), down_matrix(0).astype(float), up_matrix(0).astype(float), vectors), "y")


query(f"""WITH {Q.SAMPLES} SELECT r_name, n_name, count(*) AS orders, CAST(sum(q) AS BIGINT) AS tokens FROM (SELECT o_custkey, sum(l_quantity) AS q FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderkey, o_custkey)
JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)""", "throughput_rollup")(lambda s, d: _rollup(s, d))


def _rollup(spark, sf_dir):
    from adapterlab.sources.tables import load

    lines = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sum("l_quantity").alias("q"))
    rows = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    rows = rows.join(load(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(broadcast_within(load(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(broadcast_within(load(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("orders"), F.sum("q").cast("bigint").alias("tokens"))
