"""Packing against exhaustive search, worked examples, and its invariants."""

import random

import pytest

from adapterlab.errors import Infeasible
from adapterlab.operators import packing as P


def items(lengths, adapter="a"):
    return [(adapter, i, n) for i, n in enumerate(lengths)]


def partitions(xs):
    if not xs:
        yield []
        return
    head, rest = xs[0], xs[1:]
    for p in partitions(rest):
        yield [[head], *p]
        for i in range(len(p)):
            yield [*p[:i], [head, *p[i]], *p[i + 1 :]]


def load(group, multiple):
    per = {}
    for a, _, n in group:
        per[a] = per.get(a, 0) + n
    return sum(-(-t // multiple) * multiple for t in per.values())


def exhaustive(xs, capacity, multiple):
    """(fewest bins, smallest load of the smallest bin at that count)"""
    fits = [p for p in partitions(xs) if all(load(g, multiple) <= capacity for g in p)]
    fewest = min(map(len, fits))
    return fewest, min(min(load(g, multiple) for g in p) for p in fits if len(p) == fewest)


def test_greedy_is_not_optimal_where_exact_is():
    xs = items([5, 4, 4, 3, 2, 2])
    assert [sum(n for *_, n in b.items) for b in P.greedy(xs, 10, 1)] == [9, 9, 2]
    p = P.pack_batch(xs, 10, 1)
    assert len(p.bins) == 2 and p.path == "exact" and p.stage1 == "bound"


def test_padding_edges():
    two = [("a", 0, 64), ("b", 1, 65)]
    assert len(P.greedy(two, 128, 64)) == 2 and len(P.greedy(two, 192, 64)) == 1
    same = [("a", 0, 32), ("a", 1, 32)]
    assert P.greedy(same, 128, 64)[0].load == 64


def test_second_stage_and_tie():
    p = P.pack_batch(items([6, 5, 3, 2, 2]), 10, 1)
    assert [b.load for b in p.bins] == [10, 8] and p.path == "exact"
    tie = P.pack_batch(items([7, 7]), 10, 1)
    assert tie.path == "greedy" and [b.load for b in tie.bins] == [7, 7]


def test_budget_zero_keeps_greedy_and_strict_drops_the_incumbent():
    xs = items([5, 4, 4, 3, 2, 2])
    p = P.pack_batch(xs, 10, 1, nodes=0)
    assert p.path == "greedy" and p.stage1 == "budget" and len(p.bins) == 3
    assert P.pack_batch(xs, 10, 1, nodes=2, strict=True).path == "greedy"


@pytest.mark.parametrize("multiple", [1, 4])
@pytest.mark.parametrize("seed", range(12))
def test_both_stages_equal_exhaustive_search(seed, multiple):
    r = random.Random(seed)
    xs = [(r.choice("ab"), i, r.randint(1, 16)) for i in range(r.randint(3, 7))]
    want, least = exhaustive(xs, 24, multiple)
    bins, status = P.min_bins(xs, 24, multiple, P.Budget(10**6))
    assert len(bins) == want and status in ("optimal", "bound")
    assert P.bin_lower_bound(xs, 24, multiple) <= want
    if want > 1:
        best, status = P.min_smallest(xs, want, 24, multiple, P.Budget(10**6))
        assert status == "optimal" and min(b.load for b in best) == least
    chosen = P.pack_batch(xs, 24, multiple, nodes=10**6)
    assert len(chosen.bins) == want and min(b.load for b in chosen.bins) == least
    assert sorted(x for b in chosen.bins for x in b.items) == sorted(xs)
    assert all(b.load == load(b.items, multiple) <= 24 for b in chosen.bins)


@pytest.mark.parametrize("rule", P.RULES)
def test_greedy_rules_hold_the_constraints(rule):
    r = random.Random(3)
    xs = [(r.choice("abc"), i, r.randint(1, 500)) for i in range(60)]
    bins = P.greedy(xs, 1024, 64, rule)
    assert sorted(x for b in bins for x in b.items) == sorted(xs)
    assert all(b.load == load(b.items, 64) <= 1024 for b in bins)
    assert len(bins) >= P.bin_lower_bound(xs, 1024, 64)


def test_choice():
    small, large = P.greedy(items([4]), 10, 1), P.greedy(items([9, 9]), 10, 1)
    assert P.choose(large, small) == "exact" and P.choose(small, large) == "greedy"
    assert P.choose(small, small) == "greedy" and P.choose(small, None) == "greedy"
    assert P.choose(P.greedy(items([9, 5]), 10, 1), P.greedy(items([9, 4]), 10, 1)) == "exact"


def test_infeasible():
    with pytest.raises(Infeasible):
        P.greedy(items([11]), 10, 1)
    with pytest.raises(Infeasible):
        P.greedy(items([1]), 10, 64)


def test_report_of_broken_packings(spark):
    schema = "group_id int, gb bigint, bin int, adapter_id string, sample_id bigint, tok_len bigint"
    batches = spark.createDataFrame([(0, 0, "a", 1, 5, 0), (0, 0, "a", 2, 6, 1)], "group_id int, gb bigint, adapter_id string, sample_id bigint, tok_len bigint, rn bigint")
    good = P.pack_batches(batches, 10, 1).select("group_id", "gb", "bin", "adapter_id", "sample_id", "tok_len")
    assert P.packing_violations(good, batches, 10, 1).count() == 0
    bad = spark.createDataFrame([(0, 0, 0, "a", 1, 5), (0, 0, 0, "a", 1, 5), (0, 0, 2, "a", 3, 11)], schema)
    kinds = {r.kind for r in P.packing_violations(bad, batches, 10, 1).collect()}
    assert kinds == {"repeated", "lost", "invented", "overfull", "hole"}


def test_the_search_takes_batches_of_many_samples():
    """A batch of long samples has thousands of pieces, more than calls can be nested."""
    items = [("a", i, 100) for i in range(1500)] + [("b", 5000 + i, 30) for i in range(900)]
    found = P.pack_batch(items, 128, 1, nodes=20_000)
    assert sorted(x for b in found.bins for x in b.items) == sorted(items)
    assert all(b.load <= 128 for b in found.bins) and found.nodes <= 20_002  # each stage notes the node it no longer visits


def test_small_batches_are_packed_in_several_tasks(spark):
    from pyspark.sql import functions as F

    rows = [(0, j, i, "a", 10 * j + i, 100 + i) for j in range(40) for i in range(4)]
    batches = spark.createDataFrame(rows, "group_id int, gb bigint, rn bigint, adapter_id string, sample_id bigint, tok_len bigint")
    packed = P.pack_batches(batches, 256, 64, nodes=10)
    assert packed.select(F.spark_partition_id().alias("p")).distinct().count() > 2
