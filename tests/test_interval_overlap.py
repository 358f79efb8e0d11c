"""The interval query reads its table."""

import __spark_entry__


def test_interval_overlap_reads_events(spark):
    df = __spark_entry__.queries()["op_interval_overlap"](spark, "/root/testdata/sf0.001")
    assert any("events.parquet" in f for f in df.inputFiles())
