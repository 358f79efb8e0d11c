"""Arrivals of jobs and samples as streams; every transformation also runs on a batch, its twin.

events.ts carries no time zone; it becomes a timestamp at the source, since watermarks need one.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.window import Window

from adapterlab.operators.packing import greedy
from adapterlab.sources.tables import load

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def _timed(df: DataFrame) -> DataFrame:
    return df.withColumn("ts", F.col("ts").cast("timestamp"))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _timed(load(spark, sf_dir, "events"))


def arrivals(spark: SparkSession, folder: str, late: str = "1 day", files_per_trigger: int = 1) -> DataFrame:
    """Stream of the event files in a folder, with a watermark."""
    rows = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return _timed(rows).withWatermark("ts", late)


def job_arrivals(rows: DataFrame, tenants: int = 4) -> DataFrame:
    """(tenant, job_id, ts, kind, tok_len) of events."""
    return rows.select((F.col("user_id") % tenants).alias("tenant"), F.col("event_id").alias("job_id"), "ts", F.col("event_type").alias("kind"), (F.col("event_id") % 97 + 1).alias("tok_len"))


def tumbling(rows: DataFrame, width: str) -> DataFrame:
    w = rows.groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.unix_micros("window.start").alias("start_us"), "event_type", "n")


def sliding(rows: DataFrame, width: str, step: str) -> DataFrame:
    w = rows.groupBy(F.window("ts", width, step)).agg(F.count(F.lit(1)).alias("n"))
    return w.select(F.unix_micros("window.start").alias("start_us"), "n")


def sessions(rows: DataFrame, gap: str) -> DataFrame:
    w = rows.groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return w.select("user_id", F.unix_micros("session_window.start").alias("start_us"), "n")


def with_segment(rows: DataFrame, customer: DataFrame) -> DataFrame:
    return rows.join(customer.select("c_custkey", "c_mktsegment"), F.col("user_id") == F.col("c_custkey"))


def signup_to_purchase(rows: DataFrame, within: str = "1 day") -> DataFrame:
    """Both sides keep state for `within` and the watermark only."""
    a = rows.where("event_type = 'signup'").select(F.col("event_id").alias("signup_id"), F.col("user_id").alias("a_user"), F.col("ts").alias("a_ts"))
    b = rows.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("b_user"), F.col("ts").alias("b_ts"))
    near = (F.col("a_user") == F.col("b_user")) & (F.col("b_ts") >= F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, near).select("signup_id", "purchase_id")


def latest_configuration(rows: DataFrame) -> DataFrame:
    """As-of join: the tenant's latest signup at or before each purchase: (event_id, cfg)."""
    us = F.unix_micros("ts")
    cfg = rows.where("event_type = 'signup'").groupBy("user_id", us.alias("us")).agg(F.max("event_id").alias("cfg"))
    left = rows.where("event_type = 'purchase'").select("user_id", us.alias("us"), F.lit(None).cast("bigint").alias("cfg"), "event_id")
    both = left.unionByName(cfg.withColumn("event_id", F.lit(None).cast("bigint")))
    order = Window.partitionBy("user_id").orderBy("us", F.col("event_id").isNotNull(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("cfg", F.last("cfg", ignorenulls=True).over(order)).where("event_id IS NOT NULL").select("event_id", "cfg")


def batches_of(jobs: DataFrame, size: int = 16) -> DataFrame:
    """Twin of `fill_batches`: global batches of each tenant in order of arrival, the last may be short."""
    rn = F.row_number().over(Window.partitionBy("tenant").orderBy("ts", "job_id")) - 1
    return jobs.withColumn("rn", rn).groupBy("tenant", F.floor(F.col("rn") / size).alias("batch")).agg(F.count(F.lit(1)).alias("n"), F.sum("tok_len").alias("tokens"))


FILLED = "tenant bigint, batch bigint, n bigint, tokens bigint, closed string"


def fill_batches(jobs: DataFrame, size: int = 16, patience_ms: int = 3_600_000) -> DataFrame:
    """Keyed state: a tenant's open batch, at most `size` samples; a batch is given out when it is full.

    A tenant that stays silent past the watermark by `patience_ms` gets its tail out.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        number, n, tokens, latest = state.get if state.exists else (0, 0, 0, 0)
        out = []
        if state.hasTimedOut:
            if n:
                out.append((key[0], number, n, tokens, "tail"))
                number, n, tokens = number + 1, 0, 0
            state.update((number, n, tokens, latest))
        else:
            rows = pd.concat(list(frames)).sort_values(["ts", "job_id"])
            for t in rows["tok_len"]:
                n, tokens = n + 1, tokens + int(t)
                if n == size:
                    out.append((key[0], number, n, tokens, "full"))
                    number, n, tokens = number + 1, 0, 0
            latest = max(latest, int(rows["ts"].max().timestamp() * 1000))
            state.update((number, n, tokens, latest))
            state.setTimeoutTimestamp(max(latest, state.getCurrentWatermarkMs()) + patience_ms)
        yield pd.DataFrame(out, columns=["tenant", "batch", "n", "tokens", "closed"])

    return jobs.groupBy("tenant").applyInPandasWithState(step, FILLED, "number bigint, n bigint, tokens bigint, latest bigint", "append", GroupStateTimeout.EventTimeTimeout)


def pack_on_arrival(stream: DataFrame, sink: str, checkpoint: str, capacity: int = 512, multiple: int = 16, size: int = 32):
    """Each trigger's arrivals are packed per tenant and written under the trigger's number, so that a repeated one overwrites itself."""

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = pdf.sort_values(["ts", "job_id"])
        out = []
        for lo in range(0, len(rows), size):  # one global batch at a time
            part = rows.iloc[lo : lo + size]
            items = [(str(t), int(j), int(n)) for t, j, n in zip(part["tenant"], part["job_id"], part["tok_len"])]
            for k, b in enumerate(greedy(items, capacity, multiple)):
                out += [(int(a), lo // size, k, s, n) for a, s, n in b.items]
        return pd.DataFrame(out, columns=["tenant", "batch", "bin", "job_id", "tok_len"])

    def write(df: DataFrame, trigger: int) -> None:
        df.groupBy("tenant").applyInPandas(pack, "tenant bigint, batch bigint, bin int, job_id bigint, tok_len bigint").write.mode("overwrite").parquet(f"{sink}/trigger={trigger}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
