"""Samples of adapters: stand-ins for the three datasets, mixtures, lengths, and cleaning.

short: turns of conversations, medium: documents, long: html of pages; mixed: all three; orders: line quantities.
Only lengths leave the scan of a text column.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from adapterlab.functions.tokens import MODELS, order_key
from adapterlab.operators.numbering import rank_within
from adapterlab.schemas import ADAPTERS, SAMPLES, require
from adapterlab.session import broadcast_within, checkpointed
from adapterlab.sources.tables import load

DATASETS = ("short", "medium", "long")
TURNS = 65_536  # turns of a conversation stay below this


@dataclass(frozen=True)
class Adapter:
    adapter_id: str
    dataset: str
    rank: int
    alpha: float
    dropout: float
    global_batch_size: int
    seed: int


def het_adapters(g: int = 16) -> list[Adapter]:
    """One adapter on each of short, medium, long and mixed."""
    return [
        Adapter("a0", "short", 16, 16.0, 0.0, g, 11),
        Adapter("a1", "medium", 16, 32.0, 0.5, g, 12),
        Adapter("a2", "long", 32, 16.0, 0.0, g, 13),
        Adapter("a3", "mixed", 8, 8.0, 0.5, g, 14),
    ]


def homogeneous_adapters(dataset: str, g: int = 16, n: int = 4) -> list[Adapter]:
    """Adapters on one dataset, each with its own shuffle."""
    return [Adapter(f"a{i}", dataset, 16, 16.0, 0.0, g, 21 + i) for i in range(n)]


def adapters_frame(spark: SparkSession, adapters: list[Adapter]) -> DataFrame:
    return spark.createDataFrame([tuple(vars(a).values()) for a in adapters], ADAPTERS)


def dataset_lengths(spark: SparkSession, sf_dir: str, dataset: str, model: str = "chars4") -> DataFrame:
    """(sample_id, tok_len) of a dataset; null texts have length null."""
    length = MODELS[model]
    if dataset == "short":
        key = F.col("conv_id") * TURNS + F.col("turn")
        return load(spark, sf_dir, "conversations").select(key.alias("sample_id"), length(F.col("text")).alias("tok_len"))
    if dataset == "medium":
        return load(spark, sf_dir, "documents").select(F.col("doc_id").alias("sample_id"), length(F.col("text")).alias("tok_len"))
    if dataset == "long":
        return load(spark, sf_dir, "pages").select(F.col("page_id").alias("sample_id"), length(F.col("html")).alias("tok_len"))
    if dataset == "mixed":
        parts = [dataset_lengths(spark, sf_dir, d, model).select((F.col("sample_id") * len(DATASETS) + k).alias("sample_id"), "tok_len") for k, d in enumerate(DATASETS)]
        return parts[0].unionByName(parts[1]).unionByName(parts[2])
    if dataset == "orders":
        lines = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sum("l_quantity").cast("bigint").alias("tok_len"))
        orders = load(spark, sf_dir, "orders").select("o_orderkey")
        return orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left").select(F.col("o_orderkey").alias("sample_id"), "tok_len")
    raise ValueError(f"unknown dataset {dataset}")


def order_microbatches(spark: SparkSession, sf_dir: str, orders: int = 16) -> DataFrame:
    """(mb, tokens): so many consecutive order keys as one microbatch, its tokens the quantities of their lines."""
    lines = load(spark, sf_dir, "lineitem").where("l_orderkey IS NOT NULL")
    made = lines.groupBy(F.expr(f"l_orderkey div {orders}").alias("mb")).agg(F.floor(F.sum("l_quantity")).cast("bigint").alias("tokens"))
    return made.where("tokens > 0")


def layer_rows(spark: SparkSession, sf_dir: str, multiple: int = 64) -> DataFrame:
    """(m): the distinct padded lengths of the orders' microbatches, as many as fit under the longest."""
    return order_microbatches(spark, sf_dir).select(F.expr(f"(tokens + {multiple - 1}) div {multiple} * {multiple}").alias("m")).distinct()


def order_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(m, orders): numbers of lines that orders have, each line a microbatch of its order, and how many orders have it."""
    lines = load(spark, sf_dir, "lineitem").where("l_orderkey IS NOT NULL")
    each = lines.groupBy("l_orderkey").agg(F.count(F.lit(1)).cast("int").alias("m"))
    return each.groupBy("m").agg(F.count(F.lit(1)).alias("orders"))


def token_samples(spark: SparkSession, sf_dir: str, adapters: list[Adapter], model: str = "chars4") -> DataFrame:
    """Samples of all adapters; null and zero lengths are left to `quarantine`."""
    parts = []
    for a in adapters:
        rows = dataset_lengths(spark, sf_dir, a.dataset, model).where("tok_len > 0")
        parts.append(rows.select(
            F.lit(a.adapter_id).alias("adapter_id"), F.col("sample_id").cast("bigint").alias("sample_id"), F.lit(a.dataset).alias("dataset"),
            F.col("tok_len").cast("bigint").alias("tok_len"), order_key(a.seed, F.lit(a.dataset), F.col("sample_id")).alias("order_key"),
        ))
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return require(out, SAMPLES, "samples")


def quarantine(spark: SparkSession, sf_dir: str, datasets: tuple[str, ...] = (*DATASETS, "orders")) -> DataFrame:
    """(dataset, n_samples, n_quarantined): rows of length null or zero, which cannot be trained on."""
    out = None
    for d in datasets:
        bad = F.coalesce(F.col("tok_len"), F.lit(0)) <= 0
        rows = dataset_lengths(spark, sf_dir, d).agg(F.count(F.lit(1)).alias("n_samples"), F.count_if(bad).alias("n_quarantined")).select(F.lit(d).alias("dataset"), "n_samples", "n_quarantined")
        out = rows if out is None else out.unionByName(rows)
    return out


def oversize(samples: DataFrame, capacity: int, mode: str = "split") -> tuple[DataFrame, DataFrame]:
    """(samples to assign, counts per adapter of those beyond the capacity).

    mode: split (nothing is lost: `pieces` cuts them once they have a batch), truncate, quarantine or error.
    """
    counts = samples.groupBy("adapter_id").agg(F.count_if(F.col("tok_len") > capacity).alias("n_oversize"))
    if mode == "split":
        return samples, counts
    if mode == "truncate":
        return samples.withColumn("tok_len", F.least(F.col("tok_len"), F.lit(capacity).cast("bigint"))), counts
    if mode == "quarantine":
        return samples.where(F.col("tok_len") <= capacity), counts
    if mode == "error":
        check = F.when(F.col("tok_len") > capacity, F.raise_error(F.concat(F.lit("sample longer than the capacity: "), F.col("sample_id").cast("string")))).otherwise(F.col("tok_len"))
        return samples.withColumn("tok_len", check.cast("bigint")), counts
    raise ValueError(f"unknown mode {mode}")


def pieces(batches: DataFrame, capacity: int) -> DataFrame:
    """Rows longer than the capacity as several of at most that many tokens, in the same batch: all tokens stay."""
    cut = F.transform(F.sequence(F.lit(0), F.floor((F.col("tok_len") - 1) / capacity)), lambda k: F.least(F.lit(capacity).cast("bigint"), F.col("tok_len") - k * capacity))
    return batches.withColumn("tok_len", F.explode(cut))


def equal_samples(samples: DataFrame) -> DataFrame:
    """As many samples of each adapter as the smallest has, the first by their order."""
    ranked = checkpointed(rank_within(samples, ["adapter_id"], ["order_key", "sample_id"], "__rank"))
    least = ranked.groupBy("adapter_id").agg(F.count(F.lit(1)).alias("n")).agg(F.min("n").alias("__least"))  # one row
    return ranked.join(F.broadcast(least), F.col("__rank") < F.col("__least")).drop("__rank", "__least")


def oversize_counts(samples: DataFrame, capacity: int) -> DataFrame:
    """(adapter_id, n_samples, n_oversize, tokens, lost_tokens): what truncation to the capacity takes from each adapter."""
    return samples.groupBy("adapter_id").agg(
        F.count(F.lit(1)).alias("n_samples"), F.count_if(F.col("tok_len") > capacity).alias("n_oversize"), F.sum("tok_len").alias("tokens"),
        F.sum(F.greatest(F.col("tok_len") - capacity, F.lit(0).cast("bigint"))).alias("lost_tokens"),
    )


def clean_samples(spark: SparkSession, sf_dir: str, width: int = 8) -> DataFrame:
    """Documents with a good label, no earlier exact copy and no benchmark window of `width` words: (doc_id, tok_len)."""
    docs = load(spark, sf_dir, "documents").where(F.col("text").isNotNull())
    good = load(spark, sf_dir, "labels").where("quality = 1 AND toxic = 0").select("doc_id").distinct()
    first = docs.groupBy(F.md5("text").alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id")

    def hashed(df: DataFrame, key: str) -> DataFrame:
        """A row for each window; 64 bits of it travel instead of its words."""
        # The words are a column of their own: inside the lambda they would be split again for each window.
        w = df.select(key, F.filter(F.split(F.lower("text"), r"[ \t\n\r]+"), lambda x: x != "").alias("w")).where(F.size("w") >= width)
        at = F.transform(F.sequence(F.lit(1), F.size("w") - width + 1), lambda i: F.struct(F.xxhash64(F.slice("w", i, width)).alias("h"), i.alias("i")))
        return w.select(key, "w", F.explode(at).alias("s")).select(key, F.col("s.h").alias("h"), F.slice("w", F.col("s.i"), width).alias("words"))

    items = hashed(load(spark, sf_dir, "benchmark"), "item_id").select(F.col("h").alias("b_h"), F.col("words").alias("b_words")).distinct()
    hits = hashed(docs, "doc_id").join(broadcast_within(checkpointed(items)), (F.col("h") == F.col("b_h")) & (F.col("words") == F.col("b_words")), "left_semi")
    leaked = hits.select("doc_id").distinct()
    kept = docs.join(good, "doc_id", "left_semi").join(first, "doc_id", "left_semi").join(leaked, "doc_id", "left_anti")
    return kept.select("doc_id", MODELS["chars4"](F.col("text")).alias("tok_len"))
