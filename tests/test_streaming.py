"""Streams against their batch twins."""

import glob

import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from adapterlab.sources.tables import load, write_manifest, write_schedule
from adapterlab.streaming import arrivals as A


@pytest.fixture(scope="module")
def folder(tmp_path_factory, sf_dir):
    """Events in order of time, in five files."""
    path = tmp_path_factory.mktemp("events")
    table = pq.read_table(f"{sf_dir}/events.parquet").sort_by([("ts", "ascending"), ("event_id", "ascending")])
    step = -(-table.num_rows // 5)
    for k in range(5):
        pq.write_table(table.slice(k * step, step), f"{path}/part-{k}.parquet")
    return str(path)


def drain(spark, df, name, mode="append", tmp=None):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    assert q.awaitTermination(120)
    return q


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def test_windows_equal_their_twins(spark, sf_dir, folder):
    batch = A.events(spark, sf_dir)
    for name, make in {"tumbling": lambda e: A.tumbling(e, "1 hour"), "sliding": lambda e: A.sliding(e, "2 hours", "1 hour")}.items():
        drain(spark, make(A.arrivals(spark, folder)), name, "complete")
        assert rows(spark.table(name)) == rows(make(batch))
    drain(spark, A.sessions(A.arrivals(spark, folder, "1 hour"), "2 hours"), "sess")
    assert set(rows(spark.table("sess"))) <= set(rows(A.sessions(batch, "2 hours"))) and spark.table("sess").count() > 100


def test_joins_equal_their_twins(spark, sf_dir, folder):
    customer = load(spark, sf_dir, "customer")
    drain(spark, A.with_segment(A.arrivals(spark, folder), customer).select("event_id", "c_mktsegment"), "static")
    assert rows(spark.table("static")) == rows(A.with_segment(A.events(spark, sf_dir), customer).select("event_id", "c_mktsegment"))
    drain(spark, A.signup_to_purchase(A.arrivals(spark, folder)), "pairs")
    assert rows(spark.table("pairs")) == rows(A.signup_to_purchase(A.events(spark, sf_dir)))


def test_dedup_within_watermark(spark, folder):
    twice = A.arrivals(spark, folder).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2)))).dropDuplicatesWithinWatermark(["event_id"])
    drain(spark, twice.select("event_id"), "once")
    n = spark.table("once")
    assert n.count() == n.distinct().count() == spark.read.parquet(folder).count()


def test_filled_batches_equal_their_twin(spark, sf_dir, folder):
    drain(spark, A.fill_batches(A.job_arrivals(A.arrivals(spark, folder, "10 minutes")), patience_ms=10**11), "filled")
    got = spark.table("filled")
    full = {(r.tenant, r.batch, r.n, r.tokens) for r in got.where("closed = 'full'").collect()}
    want = {tuple(r) for r in A.batches_of(A.job_arrivals(A.events(spark, sf_dir))).where("n = 16").collect()}
    assert full == want


def test_tails_come_out_after_silence(spark, sf_dir, folder):
    drain(spark, A.fill_batches(A.job_arrivals(A.arrivals(spark, folder, "10 minutes")), patience_ms=1000), "tails")
    got = spark.table("tails")
    assert got.where("closed = 'tail' AND n < 16").count() > 0
    assert got.groupBy("tenant", "batch").count().where("count > 1").count() == 0


def test_packing_sink_survives_a_restart(spark, sf_dir, folder, tmp_path):
    sink, checkpoint = str(tmp_path / "sink"), str(tmp_path / "checkpoint")
    for _ in range(2):  # the second start finds everything done
        q = A.pack_on_arrival(A.job_arrivals(A.arrivals(spark, folder)), sink, checkpoint)
        assert q.awaitTermination(120)
    made = spark.read.parquet(sink)
    assert made.count() == made.select("job_id").distinct().count() == load(spark, sf_dir, "events").count()
    assert made.groupBy("trigger", "tenant", "batch", "bin").agg(F.sum("tok_len").alias("t")).where("t > 512").count() == 0


def test_late_rows_are_dropped_and_counted(spark, folder, tmp_path):
    for k, name in enumerate(["part-4.parquet", "part-0.parquet", "part-1.parquet"]):
        pq.write_table(pq.read_table(f"{folder}/{name}"), f"{tmp_path}/{k}.parquet")
    q = drain(spark, A.tumbling(A.arrivals(spark, str(tmp_path), "1 hour"), "1 hour"), "late")
    dropped = sum(s["numRowsDroppedByWatermark"] for p in q.recentProgress for s in p["stateOperators"])
    assert dropped > 0


def test_sinks(spark, sf_dir, tmp_path):
    from adapterlab.plans.planner import Options, global_batches, schedule_batches
    from adapterlab.samples import het_adapters, token_samples

    a = het_adapters(8)
    made = schedule_batches(global_batches(spark, token_samples(spark, sf_dir, a), a), Options(nodes=0, segment=4)).cache()
    write_schedule(made, str(tmp_path / "schedule"))
    assert spark.read.parquet(str(tmp_path / "schedule")).count() == made.count()
    write_manifest(made.where("NOT is_noop"), str(tmp_path / "manifest"))
    assert len(glob.glob(str(tmp_path / "manifest" / "*.txt"))) > 0
    assert spark.read.json(str(tmp_path / "manifest")).selectExpr("sum(size(items)) AS n").first().n == made.where("NOT is_noop").count()
