"""Queries of costs and layouts read the orders' tables."""

import pytest

import __spark_entry__

from adapterlab.samples import order_microbatches

READ = {n: "lineitem" for n in ("best_layout", "bubble_of_trace", "bubble_uniform", "intensity", "kernel_speedup", "layer_slowdown", "layer_speed_by_hand", "layer_speedup", "op_grid_join")} | {"launches": "orders"}


@pytest.mark.parametrize("name", sorted(READ))
def test_rows_follow_the_table(spark, sf_dir, tmp_path, name):
    """Half the orders give other rows, so what is read decides; the tables are read by Spark."""
    halves = str(tmp_path)
    for t, key in (("lineitem", "l_orderkey"), ("orders", "o_orderkey")):
        spark.read.parquet(f"{sf_dir}/{t}.parquet").where(f"{key} < 40").write.parquet(f"{halves}/{t}.parquet")
    run = __spark_entry__.queries()[name]
    whole, part = (sorted(map(str, run(spark, d).collect())) for d in (sf_dir, halves))
    assert whole and part and whole != part


def test_microbatches_hold_all_lines(spark, sf_dir):
    want = spark.read.parquet(f"{sf_dir}/lineitem.parquet").selectExpr("sum(l_quantity)").first()[0]
    assert order_microbatches(spark, sf_dir).selectExpr("sum(tokens)").first()[0] == want
