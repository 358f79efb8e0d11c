"""From packed batches to a schedule: order, merge across batches, verify with no-ops, positions, checks.

Merging and verifying walk microbatches in order, so they run on segments of consecutive global batches; at a
segment's end enough no-ops stand that the rule holds across the seam. With one segment nothing is added.
"""

from __future__ import annotations

from collections import defaultdict

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.functions.tokens import padded
from adapterlab.jvm import kernel, whole
from adapterlab.operators.grouping import spacing_violations
from adapterlab.operators.numbering import rank_within, running
from adapterlab.operators.packing import Bin
from adapterlab.session import checkpointed, spread

ROWS = "segment bigint, slot bigint, group_id int, gb bigint, bin int, adapter_id string, batch bigint, sample_id bigint, tok_len bigint, is_noop boolean, merged bigint"
NAMES = [c.split()[0] for c in ROWS.split(", ")]


class Micro:
    """A microbatch on its way; items are (adapter, batch, sample, tokens)."""

    __slots__ = ("group_id", "gb", "bin", "items", "noop")

    def __init__(self, group_id: int, gb: int, number: int, items: list, noop: bool = False):
        self.group_id, self.gb, self.bin, self.items, self.noop = group_id, gb, number, items, noop

    def load(self, multiple: int) -> int:
        per: dict[str, int] = defaultdict(int)
        for a, _, _, n in self.items:
            per[a] += n
        return sum(padded(t, multiple) for t in per.values())


def merge_pass(micros: list[Micro], capacity: int, multiple: int, gap: int, scope: str = "interleaved") -> tuple[list[Micro], int]:
    """Moves samples of the following batch into the last microbatch of each batch where capacity and spacing allow.

    scope: the batch that follows in schedule order (interleaved), or the next one of the same group (within_group).
    The smallest microbatch is drained first, its longest samples first. Returns the microbatches left and the moves.
    """
    gap = max(1, gap)
    batches: dict[tuple[int, int], list[Micro]] = defaultdict(list)
    for m in micros:
        batches[(m.gb, m.group_id)].append(m)
    order = sorted(batches)
    after: list[int | None] = [None] * len(order)  # the batch that may follow, in order or of the same group
    latest: dict[int, int] = {}
    for i in range(len(order) - 1, -1, -1):
        key = 0 if scope == "interleaved" else order[i][1]
        after[i], latest[key] = latest.get(key), i

    def follower(i: int) -> int | None:
        """Batches that were emptied are passed over, once and for all."""
        k = after[i]
        while k is not None and not batches[order[k]]:
            k = after[k]
        after[i] = k
        return k

    moves = base = 0  # base: microbatches of earlier batches, which no longer change
    last: dict[tuple[str, int], int] = {}
    for i, key in enumerate(order):
        bins = batches[key]
        if not bins:
            continue
        for pos, m in enumerate(bins, base):
            for a, j, *_ in m.items:
                last[(a, j)] = max(pos, last.get((a, j), pos))
        base += len(bins)
        if (k := follower(i)) is None:
            continue
        target, box = bins[-1], Bin()
        for a, _, s, n in target.items:
            box.add((a, s, n), multiple)
        for source in sorted(batches[order[k]], key=lambda m: (m.load(multiple), -m.bin)):
            for item in sorted(source.items, key=lambda x: (-x[3], x[0], x[2])):
                a, j, s, n = item
                if box.after((a, s, n), multiple) > capacity:
                    continue
                if base - 1 - last.get((a, j - 1), -gap) < gap:
                    continue
                box.add((a, s, n), multiple)
                source.items.remove(item)
                target.items.append(item)
                last[(a, j)] = base - 1
                moves += 1
        batches[order[k]] = [m for m in batches[order[k]] if m.items]
    return [m for k in order for m in batches[k]], moves


def verify_and_fix(micros: list[Micro], gap: int) -> list[Micro]:
    """Inserts no-ops so that an adapter's batch starts `gap` slots after its previous one ended; as few as can be."""
    out: list[Micro] = []
    last: dict[tuple[str, int], int] = {}
    for m in micros:
        earliest = max((last[(a, j - 1)] + gap for a, j, *_ in m.items if (a, j - 1) in last), default=0)
        while len(out) < earliest:
            out.append(Micro(m.group_id, m.gb, -1, [], True))
        for a, j, *_ in m.items:
            last[(a, j)] = len(out)
        out.append(m)
    return out


def order_micros(micros: list[Micro], multiple: int) -> list[Micro]:
    """By batch, then group, the emptiest microbatch of a batch last."""
    return sorted(micros, key=lambda m: (m.gb, m.group_id, -m.load(multiple), m.bin))


def build_schedule(items: DataFrame, capacity: int, multiple: int, stages: int = 4, gap: int | None = None, merge: bool = True, scope: str = "interleaved", segment: int | None = 64, guard: bool = True) -> DataFrame:
    """Scheduled items (pos, segment, slot, group_id, gb, bin, adapter_id, batch, sample_id, tok_len, is_noop, merged).

    gap: S - 1 unless given. segment: global batches walked at once, None for all. guard: a segment's merge is
    kept only if it does not simulate slower. A no-op is one row without sample.
    """
    spacing = max(0, stages - 1) if gap is None else gap

    part = F.lit(0).cast("bigint") if segment is None else F.floor(F.col("gb") / segment).cast("bigint")
    walked = spread(items.select("group_id", "gb", "bin", "adapter_id", "sample_id", "tok_len", part.alias("segment")), "segment")
    each = walked.groupBy("segment").agg(F.collect_list(F.struct("group_id", "gb", "bin", "adapter_id", "sample_id", "tok_len")).alias("items"))
    seam = max(0, spacing - 1) if segment is not None else 0
    limits = whole(capacity), whole(multiple), whole(stages), whole(spacing), F.lit(merge), F.lit(scope == "interleaved"), F.lit(guard), whole(seam)
    slots = kernel(items.sparkSession, "Merge", *[F.col("items")[c] for c in ("group_id", "gb", "bin", "adapter_id", "sample_id", "tok_len")], *limits)
    walked = each.select("segment", F.inline(slots)).select(*NAMES)
    return with_positions(walked)


def with_positions(walked: DataFrame) -> DataFrame:
    """Positions over all segments, from the number of slots of each segment."""
    walked = checkpointed(walked)
    slots = walked.groupBy("segment").agg((F.max("slot") + 1).alias("slots"))
    base = running(slots, [], ["segment"], "slots", "base").select("segment", "base")
    return walked.join(base, "segment").select((F.col("base") + F.col("slot")).alias("pos"), *NAMES)


def microbatches(schedule: DataFrame, multiple: int) -> DataFrame:
    """(pos, group_id, gb, bin, is_noop, n_samples, real_tokens, padded_tokens), one row per position."""
    per = schedule.groupBy("pos", "group_id", "gb", "bin", "is_noop", "adapter_id").agg(F.count("sample_id").alias("n"), F.sum("tok_len").alias("t"))
    padding = F.expr(f"(t + {multiple - 1}) div {multiple} * {multiple}")
    return per.groupBy("pos", "group_id", "gb", "bin", "is_noop").agg(F.sum("n").alias("n_samples"), F.sum("t").alias("real_tokens"), F.sum(padding).alias("padded_tokens"))


def schedule_spacing(schedule: DataFrame, gap: int) -> DataFrame:
    rows = schedule.where("NOT is_noop").select("adapter_id", F.col("batch").alias("gb"), "pos").distinct()
    return spacing_violations(rows, gap)


def interleaved_positions(items: DataFrame) -> DataFrame:
    """Positions before merge and repair: (pos, group_id, gb, bin), by batch, group and bin."""
    return rank_within(items.select("group_id", "gb", "bin").distinct(), [], ["gb", "group_id", "bin"], "pos")


def boundary_table(schedule: DataFrame) -> DataFrame:
    """(adapter_id, gb, done_pos): where an adapter's batch is complete and its optimizer step may run."""
    return schedule.where("NOT is_noop").groupBy("adapter_id", F.col("batch").alias("gb")).agg(F.max("pos").alias("done_pos"))


def lossless_violations(schedule: DataFrame, batches: DataFrame) -> DataFrame:
    """(kind, adapter_id, gb, detail): samples lost, repeated or in another batch, and batches out of order."""
    have = schedule.where("NOT is_noop").select("adapter_id", F.col("batch").alias("gb"), "sample_id", "tok_len")
    want = batches.select("adapter_id", "gb", "sample_id", "tok_len")
    lost = want.exceptAll(have).select(F.lit("lost").alias("kind"), "adapter_id", "gb", F.col("sample_id").cast("string").alias("detail"))
    extra = have.exceptAll(want).select(F.lit("extra"), "adapter_id", "gb", F.col("sample_id").cast("string"))
    span = schedule.where("NOT is_noop").groupBy("adapter_id", "batch").agg(F.min("pos").alias("lo"), F.max("pos").alias("hi"))
    after = span.select("adapter_id", (F.col("batch") - 1).alias("batch"), F.col("lo").alias("next_lo"))
    mixed = span.join(after, ["adapter_id", "batch"]).where("next_lo <= hi").select(F.lit("order"), "adapter_id", "batch", F.col("hi").cast("string"))
    return lost.union(extra).union(mixed)


def schedule_counts(schedule: DataFrame) -> DataFrame:
    slots = schedule.groupBy("pos", "is_noop").agg(F.max("segment").alias("segment"), F.max("merged").alias("merged"))
    merged = slots.groupBy("segment").agg(F.max("merged").alias("merged")).agg(F.sum("merged").alias("merged"))
    return slots.agg(F.count_if(~F.col("is_noop")).alias("microbatches"), F.count_if("is_noop").alias("noops")).join(F.broadcast(merged))
