"""The functions of Kernels.java against the Python that says the same a step at a time."""

import random
from collections import Counter

from adapterlab import registry, surrounding  # noqa: F401
from adapterlab.experiments import workloads
from adapterlab.operators import packing as P
from adapterlab.operators.numbering import rank_within
from adapterlab.operators.schedule import Micro, build_schedule, merge_pass, order_micros, verify_and_fix
from adapterlab.plans.planner import global_batches
from adapterlab.samples import het_adapters, token_samples
from adapterlab.simulate.pipeline import PipeConfig, simulate, simulate_pipeline


def plan_of(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_packing_kernel_equals_pack_batch(spark):
    r, rows, batches = random.Random(5), [], {}
    for j in range(60):
        top = r.choice([100, 400, 1024])
        batches[j] = [(r.choice("abé"), k, r.randint(1, top)) for k in range(r.randint(1, 24))]
        batches[j] += [x for x in batches[j][:2]]  # pieces of one sample may be equal
        rows += [(0, j, k, *x) for k, x in enumerate(batches[j])]
    frame = spark.createDataFrame(rows, "group_id int, gb bigint, rn bigint, adapter_id string, sample_id bigint, tok_len bigint")
    for multiple, options in ((64, {"nodes": 3000}), (1, {"nodes": 300}), (64, {"nodes": 0}), (48, {"nodes": 40}), (64, {"exact": False})):
        packed = P.pack_batches(frame, 1056 if multiple == 48 else 1024, multiple, **options)
        assert "InArrow" not in plan_of(packed) and "InPandas" not in plan_of(packed)
        got = {}
        for x in packed.collect():
            got.setdefault(x.gb, []).append(x)
        for j, items in batches.items():
            want = P.pack_batch(items, 1056 if multiple == 48 else 1024, multiple, **options)
            assert sorted((x.bin, x.adapter_id, x.sample_id, x.tok_len) for x in got[j]) == sorted((k, *x) for k, b in enumerate(want.bins) for x in b.items)
            assert {(x.solver_path, x.stage1, x.stage2, x.nodes) for x in got[j]} == {(want.path, want.stage1, want.stage2, want.nodes)}


def test_merge_kernel_equals_the_python_walk(spark):
    r = random.Random(3)
    for trial in range(8):
        gap, scope, guard = r.choice([1, 3, 6]), r.choice(["interleaved", "within_group"]), trial % 2 == 0
        packed = [(g, j, b, f"a{g}{r.randint(0, 1)}", 100 * j + 10 * b + k, r.randint(1, 90)) for j in range(9) for g in range(2) for b in range(r.randint(0, 3)) for k in range(r.randint(1, 4))]
        items = spark.createDataFrame(packed, "group_id int, gb bigint, bin int, adapter_id string, sample_id bigint, tok_len bigint")
        made = build_schedule(items, 512, 8, 4, gap, scope=scope, segment=4, guard=guard)
        want = []
        for segment in sorted({j // 4 for _, j, *_ in packed}):
            bins = {}
            for g, j, b, a, s, n in packed:
                if j // 4 == segment:
                    bins.setdefault((g, j, b), []).append((a, j, s, n))
            fresh = lambda: order_micros([Micro(*k, sorted(x)) for k, x in bins.items()], 8)  # noqa: B023, E731
            plain, (left, moves) = verify_and_fix(fresh(), gap), merge_pass(fresh(), 512, 8, gap, scope)
            best = verify_and_fix(left, gap)
            cost = lambda ms: simulate([(m.load(8), [(a, j) for a, j, *_ in m.items]) for m in ms], PipeConfig(stages=4)).makespan
            if guard and moves and cost(best) > cost(plain):
                best, moves = plain, 0
            last = fresh()[-1].gb
            best = best + [Micro(-1, last, -1, [], True) for _ in range(gap - 1)]
            for slot, m in enumerate(best):
                want += [(segment, slot, m.group_id, m.gb, m.bin, None, None, None, 0, True, moves)] if m.noop else []
                want += [(segment, slot, m.group_id, m.gb, m.bin, a, j, s, n, False, moves) for a, j, s, n in m.items]
        assert sorted(map(str, want)) == sorted(str(tuple(x)) for x in made.drop("pos").collect())


def test_simulation_kernel_equals_the_python_events(spark):
    r = random.Random(2)
    for replicas, sync, extra in ((1, 0.0, 0.05), (2, 17.5, 0.0), (4, 3.0, 0.05)):
        rows, want = [], {}
        for k in range(12):
            stages, micros = r.choice([1, 2, 4]), []
            for j in range(r.randint(1, 9)):
                for _ in range(replicas * r.randint(1, 2)):
                    keys = sorted({(r.choice("abc"), j) for _ in range(r.randint(1, 3))})
                    micros.append((0, []) if r.random() < 0.1 else (r.randint(1, 99), keys))
            t = simulate(micros, PipeConfig(stages=stages, per_token=1.59, last_extra=extra, sync=sync), replicas=replicas)
            want[f"r{k}"] = (t.makespan, sum(t.busy), t.bubble, sum(n > 0 for n, _ in micros), sum(n + 1 for n, _ in micros))
            rows += [(f"r{k}", pos, n, n + 1, [{"adapter_id": a, "batch": j} for a, j in keys], stages) for pos, (n, keys) in enumerate(micros)]
        r.shuffle(rows)
        runs = spark.createDataFrame(rows, "run_id string, pos int, cost_tokens int, real_tokens int, keys array<struct<adapter_id string, batch bigint>>, stages int")
        done = simulate_pipeline(runs, PipeConfig(per_token=1.59, last_extra=extra, sync=sync), replicas=replicas)
        assert "InPandas" not in plan_of(done)
        assert {x.run_id: tuple(x)[1:] for x in done.collect()} == want


def test_ranked_samples_give_the_same_batches(spark, sf_dir):
    """The scaling study ranks samples once for all sizes of a batch."""
    adapters = het_adapters(8)
    samples = token_samples(spark, sf_dir, adapters)
    plain, kept = (sorted(map(tuple, global_batches(spark, s, adapters).collect())) for s in (samples, rank_within(samples, ["adapter_id"], ["order_key", "sample_id"])))
    assert plain and plain == kept


def test_cases_share_what_they_have_in_common(spark, sf_dir, monkeypatch):
    """Samples are made once for a set of adapters, and packed once for a capacity; rows are those of each case by itself."""
    calls = Counter()
    for name in ("equal_samples", "pack"):
        monkeypatch.setattr(workloads, name, lambda *a, name=name, f=getattr(workloads, name): (calls.update([name]), f(*a))[1])
    a = het_adapters()
    cases = [("het", a, "medium", "first"), ("het", a, "large", "first")]
    both = sorted(map(tuple, workloads.compare(spark, sf_dir, cases).collect()), key=str)
    assert calls == {"equal_samples": 1, "pack": 1}
    assert both == sorted((tuple(x) for case in cases for x in workloads.compare(spark, sf_dir, [case]).collect()), key=str)


def test_speedup_cube_runs_no_python_over_rows(spark, sf_dir, monkeypatch):
    """The cube is over every workload and method, and its simulations are plans without Python workers."""
    plans, inner = [], workloads.simulate_pipeline
    monkeypatch.setattr(workloads, "simulate_pipeline", lambda *a, **b: (plans.append(plan_of(out := inner(*a, **b))), out)[1])
    full = workloads.compare
    monkeypatch.setattr(workloads, "compare", lambda s, d, cases: full(s, d, [c for c in cases if c[0] == "short"]))
    rows = registry.QUERIES["speedup_cube"](spark, sf_dir).collect()
    assert len(plans) == 1 and "InPandas" not in plans[0] and "InArrow" not in plans[0]
    assert len(rows) == 4 * 2 * 5 and {r.dataset for r in rows} == {"short", None}  # three models, one dataset, four methods, and all of each
