"""Batch formation: padding to the longest, pre-packing, on-the-fly packing, and what they waste."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.functions.tokens import pad_to
from adapterlab.operators.numbering import rank_within, running


def numbered(samples: DataFrame) -> DataFrame:
    """Samples with their ordinal `rn` in the adapter's shuffled order."""
    return rank_within(samples, ["adapter_id"], ["order_key", "sample_id"])


def pad_batches(samples: DataFrame, micro_batch_size: int = 4) -> DataFrame:
    """Each microbatch padded to its longest sample: (adapter_id, mb, n, real_tokens, padded_tokens, waste)."""
    mb = F.floor(F.col("rn") / micro_batch_size).cast("bigint")
    return (
        numbered(samples).groupBy("adapter_id", mb.alias("mb"))
        .agg(F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("real_tokens"), (F.max("tok_len") * F.count(F.lit(1))).alias("padded_tokens"))
        .withColumn("waste", F.col("padded_tokens") - F.col("real_tokens"))
    )


def prepack_split(samples: DataFrame, length: int = 2048) -> DataFrame:
    """Dataset packed into sequences of fixed length, samples may be cut: (adapter_id, pack_id, n_samples, tokens)."""
    at = running(samples, ["adapter_id"], ["order_key", "sample_id"], "tok_len", "start")
    end = F.col("start") + F.col("tok_len")
    first, last = F.floor(F.col("start") / length), F.floor((end - 1) / length)
    cut = at.withColumn("pack_id", F.explode(F.sequence(first.cast("bigint"), last.cast("bigint"))))
    part = F.least(F.col("start") + F.col("tok_len"), (F.col("pack_id") + 1) * length) - F.greatest("start", F.col("pack_id") * length)
    return cut.groupBy("adapter_id", "pack_id").agg(F.count(F.lit(1)).alias("n_samples"), F.sum(part).alias("tokens"))


def prepack_whole(samples: DataFrame, length: int = 2048, shard: int = 512) -> DataFrame:
    """Next-fit of whole samples into fixed length; each shard of consecutive samples is packed by itself.

    (adapter_id, shard, pack_id, n_samples, tokens). Samples beyond the length are truncated to it.
    """
    import pyarrow as pa

    def pack(table: pa.Table) -> pa.Table:
        rows = sorted(zip(table.column("rn").to_pylist(), table.column("tok_len").to_pylist()))
        packs: list[list[int]] = []
        for _, n in rows:
            n = min(n, length)
            if not packs or packs[-1][1] + n > length:
                packs.append([0, 0])
            packs[-1][0] += 1
            packs[-1][1] += n
        a, s = table.column("adapter_id")[0].as_py(), table.column("shard")[0].as_py()
        return pa.table({"adapter_id": [a] * len(packs), "shard": [s] * len(packs), "pack_id": list(range(len(packs))), "n_samples": [p[0] for p in packs], "tokens": [p[1] for p in packs]})

    rows = numbered(samples).select("adapter_id", F.floor(F.col("rn") / shard).cast("bigint").alias("shard"), "rn", "tok_len")
    return rows.groupBy("adapter_id", "shard").applyInArrow(pack, "adapter_id string, shard bigint, pack_id bigint, n_samples bigint, tokens bigint")


def pack_on_the_fly(samples: DataFrame, micro_batch_size: int = 4) -> DataFrame:
    """Samples of a microbatch laid end to end: (adapter_id, mb, tokens, offsets); the sample set per batch is fixed."""
    mb = F.floor(F.col("rn") / micro_batch_size).cast("bigint")
    packed = numbered(samples).groupBy("adapter_id", mb.alias("mb")).agg(
        F.sum("tok_len").alias("tokens"), F.array_sort(F.collect_list(F.struct("rn", "tok_len"))).alias("items")
    )
    sizes = F.transform("items", lambda x: x["tok_len"])
    offsets = F.transform(sizes, lambda _, i: F.aggregate(F.slice(sizes, 1, i), F.lit(0).cast("bigint"), lambda a, b: a + b))
    return packed.select("adapter_id", "mb", "tokens", offsets.alias("offsets"))


def packing_report(samples: DataFrame, micro_batch_size: int = 4, length: int = 2048) -> DataFrame:
    """(method, batches, real_tokens, slots, waste_per_mille, min_samples, max_samples) of the three ways."""
    padded = pad_batches(samples, micro_batch_size).select(F.lit("padded").alias("method"), "n", "real_tokens", F.col("padded_tokens").alias("slots"))
    pre = prepack_split(samples, length).select(F.lit("prepacked"), "n_samples", "tokens", F.lit(length).cast("bigint"))
    fly = microbatch_tokens(samples, micro_batch_size).select(F.lit("on_the_fly"), "n", "tokens", "tokens")
    return padded.union(pre).union(fly).groupBy("method").agg(
        F.count(F.lit(1)).alias("batches"), F.sum("real_tokens").alias("real_tokens"), F.sum("slots").alias("slots"),
        F.expr("(sum(slots) - sum(real_tokens)) * 1000 div sum(slots)").alias("waste_per_mille"),
        F.min("n").alias("min_samples"), F.max("n").alias("max_samples"),
    )


def microbatch_tokens(samples: DataFrame, micro_batch_size: int = 4) -> DataFrame:
    """Tokens of microbatches of a fixed number of samples (adapter_id, mb, n, tokens)."""
    mb = F.floor(F.col("rn") / micro_batch_size).cast("bigint")
    return numbered(samples).groupBy("adapter_id", mb.alias("mb")).agg(F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("tokens"))


def imbalance(microbatches: DataFrame, by: list[str], tokens: str = "tokens") -> DataFrame:
    """Largest over mean load (per mille) and coefficient of variation (per mille)."""
    return microbatches.groupBy(*by).agg(
        F.count(F.lit(1)).alias("batches"), F.max(tokens).alias("max_tokens"),
        F.expr(f"max({tokens}) * count(1) * 1000 div sum({tokens})").alias("max_over_mean_per_mille"),
        F.round(F.stddev_pop(tokens) / F.avg(tokens), 6).alias("variation"),
    )


def length_profile(samples: DataFrame, by: str = "dataset") -> DataFrame:
    """Count, mean, deviation, exact quantiles and extremes of lengths."""
    return samples.groupBy(by).agg(
        F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("tokens"), F.round(F.avg("tok_len"), 6).alias("mean"), F.round(F.stddev_samp("tok_len"), 4).alias("sd"),
        F.expr("percentile(tok_len, 0.5)").alias("p50"), F.expr("percentile(tok_len, 0.95)").alias("p95"), F.min("tok_len").alias("shortest"), F.max("tok_len").alias("longest"),
    )


def length_histogram(samples: DataFrame, width: int = 128, by: str = "dataset") -> DataFrame:
    return samples.groupBy(by, F.floor(F.col("tok_len") / width).cast("bigint").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def padded_lengths(samples: DataFrame, multiple: int = 64) -> DataFrame:
    return samples.groupBy("adapter_id").agg(F.sum("tok_len").alias("real_tokens"), F.sum(pad_to(F.col("tok_len"), multiple)).alias("padded_tokens"))
