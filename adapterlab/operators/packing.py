"""Packing of one global batch into microbatches: greedy rules, exact search in two stages, choice, checks.

An item is (adapter, sample, tokens). A bin's load is the sum over adapters of their tokens rounded up to the
padding multiple; it may not exceed the capacity. Batches are independent and are packed in parallel.
"""

from __future__ import annotations

import time
from bisect import bisect_left, insort
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.errors import Infeasible
from adapterlab.functions.tokens import pad_to, padded
from adapterlab.jvm import kernel, whole
from adapterlab.session import checkpointed, spread

Item = tuple[str, int, int]
RULES = ("next_fit", "first_fit", "ffd", "bfd")


class Bin:
    __slots__ = ("items", "tokens", "load")

    def __init__(self):
        self.items: list[Item] = []
        self.tokens: dict[str, int] = {}
        self.load = 0

    def after(self, item: Item, multiple: int) -> int:
        have = self.tokens.get(item[0], 0)
        return self.load - padded(have, multiple) + padded(have + item[2], multiple)

    def add(self, item: Item, multiple: int) -> None:
        self.load = self.after(item, multiple)
        self.tokens[item[0]] = self.tokens.get(item[0], 0) + item[2]
        self.items.append(item)

    def drop(self, multiple: int) -> None:
        a, _, n = self.items.pop()
        have = self.tokens[a]
        self.load += padded(have - n, multiple) - padded(have, multiple)
        self.tokens[a] = have - n
        if have == n:
            del self.tokens[a]

    def state(self) -> tuple:
        return tuple(sorted(self.tokens.items()))


def longest_first(items: list[Item]) -> list[Item]:
    return sorted(items, key=lambda x: (-x[2], x[0], x[1]))


def check_fit(items: list[Item], capacity: int, multiple: int) -> None:
    if multiple > capacity:
        raise Infeasible(f"padding to {multiple} exceeds the capacity {capacity}")
    for a, s, n in items:
        if padded(n, multiple) > capacity:
            raise Infeasible(f"sample {s} of {a} has {n} tokens; the capacity is {capacity}")


def greedy(items: list[Item], capacity: int, multiple: int, rule: str = "ffd") -> list[Bin]:
    """next_fit and first_fit keep the order given; ffd and bfd take the longest first."""
    check_fit(items, capacity, multiple)
    if rule in ("ffd", "bfd"):
        items = longest_first(items)
    bins: list[Bin] = []
    for x in items:
        open_ = bins[-1:] if rule == "next_fit" else bins
        fitting = [(b.after(x, multiple), i) for i, b in enumerate(open_)]
        fitting = [(load, i) for load, i in fitting if load <= capacity]
        if not fitting:
            bins.append(Bin())
            bins[-1].add(x, multiple)
        elif rule == "bfd":
            open_[max(fitting, key=lambda f: (f[0], -f[1]))[1]].add(x, multiple)
        else:
            open_[fitting[0][1]].add(x, multiple)
    return bins


@dataclass
class Budget:
    """Search limit: nodes make results repeatable, seconds do not."""

    nodes: int = 20_000
    seconds: float | None = None

    def __post_init__(self):
        self.used, self.began = 0, time.monotonic()

    def spend(self) -> bool:
        self.used += 1
        return self.used <= self.nodes and (self.seconds is None or time.monotonic() - self.began <= self.seconds)


def bin_lower_bound(items: list[Item], capacity: int, multiple: int) -> int:
    """Largest of: padded volume, items above half the capacity, and a dual-feasible count."""
    if not items:
        return 0
    total: dict[str, int] = defaultdict(int)
    for a, _, n in items:
        total[a] += n
    volume = -(-sum(padded(t, multiple) for t in total.values()) // capacity)
    big = sum(2 * n > capacity for _, _, n in items)
    best = max(volume, big, 1)
    sizes = [n for _, _, n in items]
    for t in {n for n in sizes if 2 * n <= capacity}:
        # Items above capacity - t fill a bin; those below t count nothing, the rest by their size.
        full = sum(n > capacity - t for n in sizes)
        best = max(best, full + -(-sum(n for n in sizes if t <= n <= capacity - t) // capacity))
    return best


class Search:
    """Bins of a depth-first search as plain numbers: a bin's load, and its tokens of all adapters in one integer.

    `live` has the bins by load, the fullest first, then by number; `candidates` skips those too full for any item of that size.
    """

    def __init__(self, items: list[Item], count: int, capacity: int, multiple: int):
        self.items, self.count, self.capacity, self.multiple = items, count, capacity, multiple
        width = sum(n for *_, n in items).bit_length() + 1
        at = {a: width * k for k, a in enumerate(dict.fromkeys(a for a, *_ in items))}
        self.shift, self.mask = [at[a] for a, *_ in items], (1 << width) - 1
        self.size = [n for *_, n in items]
        # What a bin has padded of an adapter is below the multiple, so an item adds at least so much to any bin's load.
        self.adds = [max(0, padded(n - multiple + 1, multiple)) if n >= multiple else 0 for n in self.size]
        self.load, self.state, self.place = [0] * count, [0] * count, [-1] * len(items)
        self.live = [capacity * count + k for k in range(count)]  # load and number in one key: (capacity - load) * count + number

    def candidates(self, i: int) -> list[tuple[int, int]]:
        """(bin, load with the item) of the bins that item i fits into, in order, one of those with equal contents."""
        n, shift, mask, multiple, capacity, count = self.size[i], self.shift[i], self.mask, self.multiple, self.capacity, self.count
        found, tried = [], set()
        for key in self.live[bisect_left(self.live, self.adds[i] * count) :]:
            k = key % count
            state = self.state[k]
            if state in tried:
                continue
            have = (state >> shift) & mask
            after = self.load[k] - (have + multiple - 1) // multiple * multiple + (have + n + multiple - 1) // multiple * multiple
            if after <= capacity:
                tried.add(state)
                found.append((k, after))
        return found

    def put(self, i: int, k: int, load: int) -> None:
        self._move(k, load)
        self.state[k] += self.size[i] << self.shift[i]
        self.place[i] = k

    def take(self, i: int, k: int, load: int) -> None:
        self._move(k, load)
        self.state[k] -= self.size[i] << self.shift[i]

    def _move(self, k: int, load: int) -> None:
        if load != self.load[k]:
            del self.live[bisect_left(self.live, (self.capacity - self.load[k]) * self.count + k)]
            insort(self.live, (self.capacity - load) * self.count + k)
            self.load[k] = load

    def bins(self, place: list[int], count: int) -> list[Bin]:
        out = [Bin() for _ in range(count)]
        for x, k in zip(self.items, place):
            out[k].add(x, self.multiple)
        return out


def _fit_into(items: list[Item], count: int, capacity: int, multiple: int, budget: Budget) -> list[Bin] | None | bool:
    """Bins if all items fit into `count`; None if they cannot; False if the budget ran out."""
    search = Search(items, count, capacity, multiple)
    too_much = sum(n for *_, n in items) > count * capacity  # what is left against what is free, the same at every node
    path: list[tuple] = []  # of each item placed: its bin, the bin's load before, and the candidates left
    i = 0
    while True:
        if i == len(items):
            return search.bins(search.place, count)
        if not budget.spend():
            return False
        left = iter(() if too_much else search.candidates(i))
        while (step := next(left, None)) is None:
            if not path:
                return None
            i -= 1
            k, load, left = path.pop()
            search.take(i, k, load)
        path.append((step[0], search.load[step[0]], left))
        search.put(i, *step)
        i += 1


def min_bins(items: list[Item], capacity: int, multiple: int, budget: Budget, start: list[Bin] | None = None) -> tuple[list[Bin], str]:
    """Stage 1: a packing into the fewest bins, and optimal, bound or budget."""
    items = longest_first(items)
    best = start if start is not None else greedy(items, capacity, multiple)
    bound = bin_lower_bound(items, capacity, multiple)
    while len(best) > bound:
        found = _fit_into(items, len(best) - 1, capacity, multiple, budget)
        if found is False:
            return best, "budget"
        if found is None:
            return best, "optimal"
        best = [b for b in found if b.items]
    return best, "bound"


def min_smallest(items: list[Item], count: int, capacity: int, multiple: int, budget: Budget, incumbent: int | None = None) -> tuple[list[Bin] | None, str]:
    """Stage 2: with `count` bins, the smallest possible load of one designated bin, if below `incumbent`.

    Bins are interchangeable, so the smallest bin of a packing may be called the designated one.
    """
    items = longest_first(items)
    least = capacity + 1 if incumbent is None else incumbent
    best: list[int] | None = None
    search, special = Search(items, count - 1, capacity, multiple), Bin()
    # What neither fits into the ordinary bins nor is placed yet must go into the designated one: the same at every node.
    forced = sum(n for *_, n in items) - (count - 1) * capacity
    path: list[tuple] = []
    i, ended = 0, True
    while True:
        if not budget.spend():
            ended = False
            break
        left: Iterator = iter(())
        if max(special.load, forced) < least:
            if i == len(items):
                least, best = special.load, list(search.place)
            else:
                ways = search.candidates(i)
                after = special.after(items[i], multiple)
                left = iter(ways if after > capacity else [*ways, (-1, after)])
        if least == 0:
            break
        while (step := next(left, None)) is None:
            if not path:
                break
            i -= 1
            k, load, left = path.pop()
            if k < 0:
                special.drop(multiple)
            else:
                search.take(i, k, load)
        if step is None:
            break
        k, load = step
        path.append((k, special.load if k < 0 else search.load[k], left))
        if k < 0:
            special.add(items[i], multiple)
            search.place[i] = -1
        else:
            search.put(i, k, load)
        i += 1
    if best is None:
        return None, "optimal" if ended else "budget"
    return search.bins([k % count for k in best], count), "optimal" if ended else "budget"


@dataclass
class Packing:
    bins: list[Bin]
    path: str
    stage1: str
    stage2: str
    nodes: int


def choose(greedy_bins: list[Bin], exact_bins: list[Bin] | None) -> str:
    """exact if it has fewer bins, or as many and a strictly smaller smallest bin; else greedy."""
    if exact_bins is None:
        return "greedy"
    least = lambda bins: min((b.load for b in bins), default=0)
    if len(exact_bins) != len(greedy_bins):
        return "exact" if len(exact_bins) < len(greedy_bins) else "greedy"
    return "exact" if least(exact_bins) < least(greedy_bins) else "greedy"


def pack_batch(items: list[Item], capacity: int, multiple: int, nodes: int = 20_000, seconds: float | None = None, exact: bool = True, strict: bool = False, rule: str = "ffd") -> Packing:
    """Greedy, then both stages, then the choice; bins come largest first, so that the emptiest is the last.

    strict: a stage that runs out of budget gives its result up altogether.
    """
    first = greedy(items, capacity, multiple, rule)
    budget = Budget(nodes, seconds)
    stage1 = stage2 = "skipped"
    best: list[Bin] | None = None
    if exact and nodes > 0 and items:
        best, stage1 = min_bins(items, capacity, multiple, budget, first)
        if not (strict and stage1 == "budget"):
            least = min(b.load for b in best)
            better, stage2 = min_smallest(items, len(best), capacity, multiple, budget, least) if len(best) > 1 else (None, "skipped")
            if better is not None and not (strict and stage2 == "budget"):
                best = better
                if any(not b.items for b in best):  # stage 1 had stopped early; one bin fewer will do
                    best, stage2 = [b for b in best if b.items], "stage2_found_fewer"
        else:
            best = None
    elif exact and items:
        stage1 = stage2 = "budget"
    path = choose(first, best)
    bins = best if path == "exact" else first
    return Packing(sorted(bins, key=lambda b: -b.load), path, stage1, stage2, budget.used)


PACKED = "group_id int, gb bigint, bin int, adapter_id string, sample_id bigint, tok_len bigint, solver_path string, stage1 string, stage2 string, nodes bigint"


def pack_batches(batches: DataFrame, capacity: int, multiple: int, **options) -> DataFrame:
    """Packs every (group_id, gb) of `batches`; a task holds one global batch at a time. options: those of `pack_batch`."""
    rows = spread(batches.select("group_id", "gb", "rn", "adapter_id", "sample_id", "tok_len"), "group_id", "gb")
    names = [c.split()[0] for c in PACKED.split(", ")]
    if set(options) <= {"nodes", "exact"}:
        each = rows.groupBy("group_id", "gb").agg(F.collect_list(F.struct("adapter_id", "sample_id", "tok_len")).alias("items"))
        limits = whole(capacity), whole(multiple), whole(options.get("nodes", 20_000)), F.lit(options.get("exact", True))
        found = kernel(batches.sparkSession, "Pack", *[F.col("items")[c] for c in ("adapter_id", "sample_id", "tok_len")], *limits)
        return each.select("group_id", "gb", F.inline(found)).select(*names)

    def run(table: pa.Table) -> pa.Table:
        cols = [table.column(c).to_pylist() for c in ("rn", "adapter_id", "sample_id", "tok_len")]
        items = [x[1:] for x in sorted(zip(*cols))]
        found = pack_batch(items, capacity, multiple, **options)
        g, j = table.column("group_id")[0].as_py(), table.column("gb")[0].as_py()
        rows = [(g, j, k, *x, found.path, found.stage1, found.stage2, found.nodes) for k, b in enumerate(found.bins) for x in b.items]
        kinds = [pa.int32(), pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64()]
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names)

    return rows.groupBy("group_id", "gb").applyInArrow(run, PACKED)


def pack_greedy(batches: DataFrame, capacity: int, multiple: int, rule: str = "ffd") -> DataFrame:
    """Greedy only, bins numbered in the order they were opened: (group_id, gb, bin, adapter_id, sample_id, tok_len)."""

    def run(table: pa.Table) -> pa.Table:
        cols = [table.column(c).to_pylist() for c in ("adapter_id", "rn", "sample_id", "tok_len")]
        items = [(a, s, n) for a, _, s, n in sorted(zip(*cols))]
        g, j = table.column("group_id")[0].as_py(), table.column("gb")[0].as_py()
        rows = [(g, j, k, *x) for k, b in enumerate(greedy(items, capacity, multiple, rule)) for x in b.items]
        kinds = [pa.int32(), pa.int64(), pa.int32(), pa.string(), pa.int64(), pa.int64()]
        return pa.Table.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=["group_id", "gb", "bin", "adapter_id", "sample_id", "tok_len"])

    schema = "group_id int, gb bigint, bin int, adapter_id string, sample_id bigint, tok_len bigint"
    return batches.select("group_id", "gb", "rn", "adapter_id", "sample_id", "tok_len").groupBy("group_id", "gb").applyInArrow(run, schema)


def bin_loads(items: DataFrame, multiple: int) -> DataFrame:
    """(group_id, gb, bin, n_samples, n_adapters, real_tokens, padded_tokens)"""
    per = items.groupBy("group_id", "gb", "bin", "adapter_id").agg(F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("t"))
    return per.groupBy("group_id", "gb", "bin").agg(
        F.sum("n").alias("n_samples"), F.count(F.lit(1)).alias("n_adapters"), F.sum("t").alias("real_tokens"), F.sum(pad_to(F.col("t"), multiple)).alias("padded_tokens")
    )


def packing_violations(items: DataFrame, batches: DataFrame, capacity: int, multiple: int) -> DataFrame:
    """(kind, group_id, gb, detail) of every broken constraint; none for a right packing."""
    key = ["group_id", "gb", "adapter_id", "sample_id"]
    have, want = items.select(*key, "tok_len"), batches.select(*key, "tok_len")  # a long sample has several rows
    lost = want.exceptAll(have).select(F.lit("lost").alias("kind"), "group_id", "gb", F.col("sample_id").cast("string").alias("detail"))
    extra = have.exceptAll(want).join(want.select(*key).distinct().withColumn("known", F.lit(True)), key, "left")
    made = extra.select(F.when(F.col("known"), "repeated").otherwise("invented"), "group_id", "gb", F.col("sample_id").cast("string"))
    loads = bin_loads(items, multiple)
    over = loads.where(F.col("padded_tokens") > capacity).select(F.lit("overfull"), "group_id", "gb", F.col("bin").cast("string"))
    holes = loads.groupBy("group_id", "gb").agg(F.max("bin").alias("last"), F.count(F.lit(1)).alias("n")).where("last + 1 <> n").select(F.lit("hole"), "group_id", "gb", F.col("n").cast("string"))
    return lost.union(made).union(over).union(holes)


def solver_report(items: DataFrame) -> DataFrame:
    """Share of global batches by solver path and end of both stages (per mille)."""
    batches = checkpointed(items.select("group_id", "gb", "solver_path", "stage1", "stage2").distinct())  # read twice, searched once
    total = batches.agg(F.count(F.lit(1)).alias("total"))
    return batches.groupBy("solver_path", "stage1", "stage2").agg(F.count(F.lit(1)).alias("batches")).join(F.broadcast(total)).select(
        "solver_path", "stage1", "stage2", "batches", F.expr("batches * 1000 div total").alias("per_mille")
    )
