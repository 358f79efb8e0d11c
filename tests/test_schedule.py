"""Merge, repair, simulators and the whole plan."""

import random
from itertools import product

import pytest
from pyspark.sql import functions as F

from adapterlab.errors import SchemaMismatch, Unsupported
from adapterlab.operators import baselines, grouping, numbering, schedule
from adapterlab.operators.schedule import Micro, merge_pass, order_micros, verify_and_fix
from adapterlab.plans.planner import Options, as_runs, global_batches, plan, schedule_batches, simulate_schedule
from adapterlab.samples import adapters_frame, equal_samples, het_adapters, oversize, token_samples
from adapterlab.schemas import SAMPLES, require
from adapterlab.simulate.pipeline import PipeConfig, simulate, simulate_pipeline, uniform_bubble
from adapterlab.simulate.sharded import simulate_tensor_parallel


def micro(gb, number, *parts):
    return Micro(0, gb, number, [(a, gb, s, n) for s, (a, n) in enumerate(parts, 10 * (gb * 10 + number))])


def test_spacing_needs_two_noops():
    fixed = verify_and_fix([micro(0, 0, ("a", 5)), micro(1, 0, ("a", 5))], 3)
    assert [m.noop for m in fixed] == [False, True, True, False]
    assert [m.noop for m in verify_and_fix(fixed, 3)] == [m.noop for m in fixed]


def test_merge_moves_only_what_fits_and_may():
    micros = [micro(0, 0, ("a", 8)), micro(0, 1, ("c", 3)), micro(1, 0, ("c", 9)), micro(1, 1, ("a", 4))]
    left, moves = merge_pass(micros, 10, 1, 1)
    assert moves == 1 and len(left) == 3
    assert sorted((a, n) for a, _, _, n in left[1].items) == [("a", 4), ("c", 3)]
    assert schedule_span_ok(verify_and_fix(left, 1), 1)


def schedule_span_ok(micros, gap):
    span = {}
    for pos, m in enumerate(micros):
        for a, j, *_ in m.items:
            lo, hi = span.get((a, j), (pos, pos))
            span[(a, j)] = (min(lo, pos), max(hi, pos))
    return all(lo - span[(a, j - 1)][1] >= gap for (a, j), (lo, _) in span.items() if (a, j - 1) in span)


def fewest_noops(micros, gap):
    for total in range(8):
        for put in product(range(total + 1), repeat=len(micros)):
            if sum(put) == total:
                out = []
                for k, m in zip(put, micros):
                    out += [Micro(0, 0, -1, [], True)] * k + [m]
                if schedule_span_ok(out, gap):
                    return total
    raise AssertionError


@pytest.mark.parametrize("seed", range(8))
def test_repair_uses_the_fewest_noops(seed):
    r = random.Random(seed)
    micros = [Micro(0, j, b, [(a, j, 100 * j + 10 * b + ord(a), 1) for a in r.sample("abc", r.randint(1, 2))]) for j in range(2) for b in range(r.randint(1, 2))]
    fixed = verify_and_fix(micros, 3)
    assert schedule_span_ok(fixed, 3) and sum(m.noop for m in fixed) == fewest_noops(micros, 3)


@pytest.mark.parametrize("scope", ["interleaved", "within_group"])
@pytest.mark.parametrize("seed", range(6))
def test_merge_loses_nothing(seed, scope):
    r = random.Random(seed)
    micros = [Micro(g, j, b, [(f"{a}{g}", j, 1000 * j + 100 * g + 10 * b + k, r.randint(1, 60)) for k, a in enumerate(r.choices("ab", k=2))]) for j in range(5) for g in range(2) for b in range(3)]
    before = sorted(x for m in micros for x in m.items)
    left, _ = merge_pass(order_micros(micros, 8), 128, 8, 3, scope)
    assert sorted(x for m in left for x in m.items) == before and len(left) <= 30
    assert all(m.load(8) <= 128 for m in left)
    assert schedule_span_ok(verify_and_fix(left, 3), 3)


def test_uniform_pipeline_meets_the_closed_form():
    for s, m in ((1, 5), (4, 4), (4, 16), (8, 3)):
        t = simulate([(10, [("a", 0)])] * m, PipeConfig(stages=s), keep_events=True)
        assert abs(t.bubble - uniform_bubble(s, m)) < 1e-9
        assert len(t.events) == 2 * s * m


def test_dependency_holds_in_the_trace():
    r = random.Random(1)
    micros = [(r.randint(1, 50), [(r.choice("ab"), j)]) for j in range(6) for _ in range(3)]
    t = simulate(micros, PipeConfig(stages=4), keep_events=True)
    begin = {(i, s): a for s, i, kind, a, _ in t.events if kind == "forward"}
    done = {(i, s): b for s, i, kind, _, b in t.events if kind == "backward"}
    for i, (_, keys) in enumerate(micros):
        for k, (_, others) in enumerate(micros[:i]):
            if any(a == b and j == c + 1 for a, j in keys for b, c in others):
                assert begin[(i, 0)] >= done[(k, 0)] - 1e-9
    for s in range(4):
        work = sorted((a, b) for st, _, _, a, b in t.events if st == s)
        assert all(x[1] <= y[0] + 1e-9 for x, y in zip(work, work[1:]))


def test_more_stages_never_shrink_the_bubble_and_noops_cost_nothing():
    micros = [(10, [("a", 0)])] * 12
    bubbles = [simulate(micros, PipeConfig(stages=s)).bubble for s in (1, 2, 4, 8)]
    assert bubbles == sorted(bubbles)
    assert simulate([*micros, (0, [])], PipeConfig(stages=4)).makespan == simulate(micros, PipeConfig(stages=4)).makespan


def test_numbering_equals_one_window(spark):
    df = spark.range(500).select((F.col("id") % 3).alias("k"), (F.col("id") * 7919 % 1009).alias("o"), (F.col("id") % 11).alias("v"))
    got = numbering.rank_within(df, ["k"], ["o"]).select("k", "o", F.col("rn").cast("int"))
    want = df.selectExpr("k", "o", "row_number() OVER (PARTITION BY k ORDER BY o) - 1 AS rn")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    total = numbering.running(df, [], ["k", "o"], "v", "t").orderBy("k", "o").select("v", "t").collect()
    assert all(b.t == a.t + a.v for a, b in zip(total, total[1:]))


def test_whole_plan(spark, sf_dir):
    a, o = het_adapters(8), Options(nodes=50)
    samples = token_samples(spark, sf_dir, a)
    batches = global_batches(spark, samples, a, o).cache()
    for options in (o, o.with_(merge=False), o.with_(segment=2), o.with_(policy="singleton"), o.with_(scope="within_group", guard=False)):
        made = schedule_batches(batches if options.policy == "pair" else global_batches(spark, samples, a, options), options).cache()
        assert schedule.lossless_violations(made, batches).count() == 0
        assert schedule.schedule_spacing(made, 3).count() == 0
        pos = [r.pos for r in made.select("pos").distinct().orderBy("pos").collect()]
        assert pos == list(range(len(pos)))
        assert schedule.microbatches(made, 64).where("padded_tokens > 2048").count() == 0
    assert made.count() >= samples.count()


def test_methods_rank_as_reported(spark):
    sf = "/root/testdata/sf0.01"
    a, o = het_adapters(16), Options(nodes=50)
    batches = global_batches(spark, token_samples(spark, sf, a), a, o).cache()
    micro_ = baselines.fixed_microbatches(batches).cache()
    run = lambda df: simulate_pipeline(df).first()
    seq = run(baselines.as_runs(baselines.baseline_pipeline(micro_), "s", 4))
    fill = run(baselines.as_runs(baselines.baseline_uniform_fill(micro_), "u", 4))
    ours = run(as_runs(schedule_batches(batches, o), "m", 4))
    assert ours.bubble < fill.bubble < seq.bubble and ours.tokens == fill.tokens == seq.tokens


def test_segments_bound_the_whole_run(spark, sf_dir):
    a = het_adapters(8)
    batches = global_batches(spark, token_samples(spark, sf_dir, a), a)
    one = schedule_batches(batches, Options(nodes=0, segment=None)).cache()
    whole, alone = simulate_pipeline(as_runs(one, "w", 4)).first(), simulate_schedule(one, 4).first()
    assert abs(whole.makespan - alone.makespan) < 1e-6 and whole.tokens == alone.tokens
    cut = schedule_batches(batches, Options(nodes=0, segment=4)).cache()
    parts = simulate_schedule(cut, 4).first()
    assert parts.makespan >= simulate_pipeline(as_runs(cut, "c", 4)).first().makespan - 1e-6 and parts.tokens == whole.tokens


def test_plan_does_not_depend_on_partitions_or_names(spark, sf_dir):
    a, o = het_adapters(8), Options(nodes=20)
    samples = token_samples(spark, sf_dir, a)
    key = ["pos", "adapter_id", "batch", "sample_id"]
    first = sorted(map(str, plan(spark, samples, a, o).select(*key).collect()))
    assert first == sorted(map(str, plan(spark, samples.repartition(7, "sample_id"), a, o).select(*key).collect()))


def test_schemas_oversize_and_unsupported(spark, sf_dir):
    samples = token_samples(spark, sf_dir, het_adapters(8))
    with pytest.raises(SchemaMismatch):
        require(samples.drop("tok_len"), SAMPLES)
    cut, counts = oversize(samples, 500, "truncate")
    assert cut.where("tok_len > 500").count() == 0 and counts.agg(F.sum("n_oversize")).first()[0] == samples.where("tok_len > 500").count()
    assert oversize(samples, 500, "quarantine")[0].count() == samples.where("tok_len <= 500").count()
    with pytest.raises(Exception, match="longer than the capacity"):
        oversize(samples, 500, "error")[0].agg(F.sum("tok_len")).collect()
    with pytest.raises(Unsupported):
        simulate_tensor_parallel()


def test_text_stays_in_the_scan(spark, sf_dir):
    a = het_adapters(8)
    rows = grouping.adapter_stats(token_samples(spark, sf_dir, a))
    text = rows._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" in text and not any("text" in line or "html" in line for line in text.splitlines() if "Exchange" in line)
    # Only statistics of adapters, a row each, ever meet in one partition.
    numbered = numbering.rank_within(token_samples(spark, sf_dir, a), ["adapter_id"], ["order_key", "sample_id"])
    assert "SinglePartition" not in numbered._jdf.queryExecution().executedPlan().toString()
    dim = adapters_frame(spark, a)
    assert dim.count() == 4


def test_long_samples_are_cut_into_pieces_of_one_batch(spark, sf_dir):
    a = het_adapters()
    samples = token_samples(spark, sf_dir, a)
    rows = global_batches(spark, samples, a, Options(capacity=512))
    assert rows.where("tok_len > 512 OR tok_len < 1").count() == 0
    whole = rows.groupBy("adapter_id", "sample_id").agg(F.sum("tok_len").alias("t"), F.count_distinct("gb").alias("batches"), F.count(F.lit(1)).alias("n"))
    assert whole.where("batches > 1 OR n <> ceil(t / 512)").count() == 0
    assert whole.select("adapter_id", "sample_id", "t").exceptAll(samples.select("adapter_id", "sample_id", "tok_len")).count() == 0
    assert whole.count() == samples.count()


def test_adapters_with_equally_many_samples(spark, sf_dir):
    n = [r["count"] for r in equal_samples(token_samples(spark, sf_dir, het_adapters())).groupBy("adapter_id").count().collect()]
    assert len(n) == 4 and len(set(n)) == 1


def plain_merge(micros, capacity, multiple, gap, scope):
    """The merge pass with every place counted anew for each batch."""
    batches = {}
    for m in micros:
        batches.setdefault((m.gb, m.group_id), []).append(m)
    order, moves = sorted(batches), 0
    for key in order:
        follower = next((k for k in order if k > key and (scope == "interleaved" or k[1] == key[1]) and batches[k]), None)
        if not batches[key] or follower is None:
            continue
        target, place, last = batches[key][-1], {}, {}
        for pos, m in enumerate(m for k in order for m in batches[k]):
            place[id(m)] = pos
            for a, j, *_ in m.items:
                last[(a, j)] = pos
        for source in sorted(batches[follower], key=lambda m: (m.load(multiple), -m.bin)):
            for item in sorted(source.items, key=lambda x: (-x[3], x[0], x[2])):
                target.items.append(item)
                if target.load(multiple) > capacity or place[id(target)] - last.get((item[0], item[1] - 1), -gap) < gap:
                    target.items.pop()
                else:
                    source.items.remove(item)
                    moves += 1
        batches[follower] = [m for m in batches[follower] if m.items]
    return [m for k in order for m in batches[k]], moves


@pytest.mark.parametrize("scope", ["interleaved", "within_group"])
def test_linear_merge_equals_the_plain_one(scope):
    r = random.Random(8)
    for trial in range(60):
        made = []
        for gb in range(r.randint(1, 8)):
            for g in range(r.randint(1, 3)):
                for b in range(r.randint(0, 3)):
                    made.append((g, gb, b, [(f"a{g}{r.randint(0, 1)}", gb, trial * 1000 + len(made) * 10 + k, r.randint(1, 300)) for k in range(r.randint(1, 3))]))
        sides = []
        for merge in (merge_pass, plain_merge):
            micros = order_micros([Micro(g, gb, b, list(x)) for g, gb, b, x in made], 64)
            left, moves = merge(micros, 1024, 64, trial % 4 + 1, scope)
            sides.append(([(m.group_id, m.gb, m.bin, m.items) for m in left], moves))
        assert sides[0] == sides[1]
