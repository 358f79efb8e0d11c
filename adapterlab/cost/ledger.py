"""Traffic ledger of the adapter layer: what each operator of each implementation reads and writes.

Tensor sizes in elements: X, Xh (dropped X), dX: m k; Y, dY: m n; S, dS: m r; W: k n; A: k r; B: r n; M (mask): one byte
for each element of X. Times come from a roofline with the peak set to one operation per unit.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# Fixed values: (pass, operator, class, reads and writes, multiply-adds). Classes: base, adapter, element.
FROZEN = [("forward", "base", "base", "rX rW wY", "mkn"), ("backward", "base", "base", "rdY rW wdX", "mkn")]
NAIVE = [
    ("forward", "drop", "element", "rX wXh wM", ""), ("forward", "down", "adapter", "rXh rA wS", "mkr"), ("forward", "base", "base", "rX rW wY", "mkn"),
    ("forward", "up", "adapter", "rS rB wY", "mrn"), ("forward", "scale", "element", "rY wY", ""), ("forward", "add", "element", "rY rY wY", ""),
    ("backward", "scale", "element", "rdY wdY", ""), ("backward", "ds", "adapter", "rdY rB wdS", "mrn"), ("backward", "db", "adapter", "rS rdY wB", "mrn"),
    ("backward", "da", "adapter", "rXh rdS wA", "mkr"), ("backward", "dxh", "adapter", "rdS rA wdX", "mkr"), ("backward", "mask", "element", "rdX rM wdX", ""),
    ("backward", "base", "base", "rdY rW wdX", "mkn"), ("backward", "add", "element", "rdX rdX wdX", ""),
]
SPLIT = [
    ("forward", "drop_down", "adapter", "rX rA wXh wM wS", "mkr"), ("forward", "base_up", "base", "rX rW rS rB wY", "mkn mrn"),
    ("backward", "ds_db", "adapter", "rdY rS rB wdS wB", "mrn mrn"), ("backward", "da", "adapter", "rXh rdS wA", "mkr"), ("backward", "dx", "base", "rdY rW rdS rA rM wdX", "mkn mkr"),
]
COMPILED = [x for x in NAIVE if x[1] not in ("scale", "add", "mask")] + [
    ("forward", "scale_add", "element", "rY rY wY", ""), ("backward", "scale", "element", "rdY wdY", ""), ("backward", "mask_add", "element", "rdX rM rdX wdX", "")
]
IMPLEMENTATIONS = {"frozen": FROZEN, "naive": NAIVE, "compiled": COMPILED, "split": SPLIT}
SIZES = {"X": "m*k", "Xh": "m*k", "dX": "m*k", "Y": "m*n", "dY": "m*n", "S": "m*r", "dS": "m*r", "W": "k*n", "A": "k*r", "B": "r*n", "M": "m*k"}
FLOPS = {"mkn": "2*m*k*n", "mkr": "2*m*k*r", "mrn": "2*m*r*n"}
BALANCE = 295
SHAPE = "m bigint, k bigint, n bigint, r bigint"


def shapes_frame(spark: SparkSession, shapes: list[tuple[int, int, int, int]]) -> DataFrame:
    return spark.createDataFrame(shapes, SHAPE)


def layers_of(rows: DataFrame, layers: list[tuple[int, int, int]]) -> DataFrame:
    """Shapes of given layers (k, n, r) under the rows (m) that batches have."""
    fixed = rows.sparkSession.createDataFrame(layers, SHAPE.removeprefix("m bigint, "))
    return rows.crossJoin(F.broadcast(fixed))


def _operators(spark: SparkSession, adapters: int, m_tile: int, n_tile: int) -> DataFrame:
    rows = []
    for impl, ops in IMPLEMENTATIONS.items():
        for direction, op, kind, touches, flops in ops:
            rows += [(impl, direction, op, kind, t[1:], t[0], 1) for t in touches.split()]
            rows += [(impl, direction, op, kind, f, "f", 1) for f in flops.split()]
    # The recomputing form has no first pass; each output tile reads X and A again and computes S again.
    for direction, op, kind, touches, flops in SPLIT:
        for impl in ("recompute", "sync", "routed"):
            if impl == "recompute" and op == "drop_down":
                continue
            rows += [(impl, direction, op, kind, t[1:], t[0], 1) for t in touches.split()]
            rows += [(impl, direction, op, kind, f, "f", 1) for f in flops.split()]
    rows += [("recompute", "forward", "base_up", "base", t, rw, -1) for t, rw in (("A/tile", "r"), ("mkr/tile", "f"), ("M", "w"), ("Xh", "w"))]
    rows += [("routed", d, "route", "adapter", "tiles", "r", 1) for d in ("forward", "backward")]
    rows += [("routed", "backward", "accumulate", "adapter", t, rw, adapters) for t in ("A", "B") for rw in "rw"]
    schema = "impl string, direction string, op string, class string, tensor string, rw string, times int"
    return spark.createDataFrame(rows, schema)


def traffic_ledger(shapes: DataFrame, adapters: int = 4, element: int = 2, m_tile: int = 128, n_tile: int = 128, gemm_reread: float = 0.0) -> DataFrame:
    """(impl, direction, op, class, tensor, rw, m, k, n, r, bytes, flops), ideal single touch.

    gemm_reread: further passes over X that the frozen product makes, in both directions together; with 7.8 it makes
    12.8 in all and the stock layer moves 2.64 times its bytes, as was measured.
    """
    ops = _operators(shapes.sparkSession, adapters, m_tile, n_tile)
    rows = ops.join(F.broadcast(shapes))  # fixed operators times given shapes
    size = F.lit(0).cast("bigint")
    for t, e in SIZES.items():
        size = F.when(F.col("tensor") == t, F.expr(e) * (1 if t == "M" else element) * F.abs("times")).otherwise(size)
    size = F.when(F.col("tensor") == "A/tile", F.expr(f"ceil(m / {m_tile}) * ceil(n / {n_tile}) * k * r") * element).otherwise(size)
    size = F.when(F.col("tensor") == "tiles", F.expr(f"ceil(m / {m_tile}) * 16")).otherwise(size)
    if gemm_reread:
        size = size + F.when((F.col("op").isin("base", "base_up", "dx")) & F.col("tensor").isin("X", "dY") & (F.col("rw") == "r"), F.expr("m*k") * element * (gemm_reread / 2)).otherwise(0)
    flops = F.lit(0).cast("bigint")
    for t, e in FLOPS.items():
        flops = F.when(F.col("tensor") == t, F.expr(e)).otherwise(flops)
    flops = F.when(F.col("tensor") == "mkr/tile", F.expr(f"2*m*k*r*ceil(n / {n_tile})")).otherwise(flops)
    return rows.select("impl", "direction", "op", "class", "tensor", "rw", "m", "k", "n", "r", size.cast("bigint").alias("bytes"), flops.cast("bigint").alias("flops"))


def traffic_totals(ledger: DataFrame) -> DataFrame:
    return ledger.groupBy("impl", "direction", "m", "k", "n", "r").agg(F.sum("bytes").alias("bytes"), F.sum("flops").alias("flops"))


def traffic_ratio(ledger: DataFrame) -> DataFrame:
    """Both directions together, per mille of frozen and of naive."""
    total = ledger.groupBy("m", "k", "n", "r").pivot("impl", [*IMPLEMENTATIONS, "recompute", "sync", "routed"]).agg(F.sum("bytes"))
    cols = [F.expr(f"{i} * 1000 div frozen").alias(f"{i}_to_frozen") for i in ("naive", "compiled", "split", "recompute", "sync", "routed")]
    return total.select("m", "k", "n", "r", *cols, *[F.expr(f"{i} * 1000 div naive").alias(f"{i}_to_naive") for i in ("split", "routed")])


def roofline(ledger: DataFrame, balance: int = BALANCE) -> DataFrame:
    """Time of each operator: the longer of its operations and its bytes times the machine balance."""
    op = ledger.groupBy("impl", "direction", "op", "class", "m", "k", "n", "r").agg(F.sum("bytes").alias("bytes"), F.sum("flops").alias("flops"))
    return op.withColumn("time", F.greatest(F.col("flops"), F.col("bytes") * balance))


def runtime_breakdown(ledger: DataFrame, impl: str = "naive", balance: int = BALANCE) -> DataFrame:
    """Share of frozen product, adapter products and element-wise operators in each direction, per mille."""
    t = roofline(ledger, balance).where(F.col("impl") == impl)
    by_class = t.groupBy("direction", "class", "m", "k", "n", "r").agg(F.sum("time").alias("time"))
    total = t.groupBy("direction", "m", "k", "n", "r").agg(F.sum("time").alias("total"))
    return by_class.join(total, ["direction", "m", "k", "n", "r"]).select("direction", "class", "m", "k", "n", "r", F.expr("time * 1000 div total").alias("per_mille"))


def layer_sweep(ledger: DataFrame, balance: int = BALANCE) -> DataFrame:
    """Throughput of each implementation relative to frozen, per mille, by direction and shape."""
    t = roofline(ledger, balance).groupBy("impl", "direction", "m", "k", "n", "r").agg(F.sum("time").alias("time"))
    base = t.where("impl = 'frozen'").select("direction", "m", "k", "n", "r", F.col("time").alias("frozen_time"))
    return t.join(base, ["direction", "m", "k", "n", "r"]).select("impl", "direction", "m", "k", "n", "r", F.expr("frozen_time * 1000 div time").alias("speed_per_mille"))


def kernel_speedup(ledger: DataFrame, balance: int = BALANCE) -> DataFrame:
    """Speed of the fused and compiled layers over the naive one, per mille."""
    t = roofline(ledger, balance).groupBy("impl", "direction", "m", "k", "n", "r").agg(F.sum("time").alias("time"))
    base = t.where("impl = 'naive'").select("direction", "m", "k", "n", "r", F.col("time").alias("naive_time"))
    rows = t.where("impl IN ('compiled', 'recompute', 'sync', 'split', 'routed')").join(base, ["direction", "m", "k", "n", "r"])
    return rows.select("impl", "direction", "m", "k", "n", "r", F.expr("naive_time * 1000 div time").alias("speedup_per_mille"))


def kernel_factors(spark: SparkSession, shape: tuple[int, int, int, int] = (8192, 4096, 4096, 16), adapters: int = 4) -> dict[str, float]:
    """Time of both passes of each implementation relative to the frozen layer, as the roofline has it; one row each."""
    t = roofline(traffic_ledger(shapes_frame(spark, [shape]), adapters)).groupBy("impl").agg(F.sum("time").alias("time"))
    times = {r["impl"]: r["time"] for r in t.collect()}
    return {k: v / times["frozen"] for k, v in times.items()}


def launches(microbatches: DataFrame) -> DataFrame:
    """Kernel launches of a layer over all microbatches by implementation; only the looped one launches for each adapter of a microbatch.

    microbatches: (mb, adapter_id), a row for each sample. Merging launches of several adapters leaves the traffic as it was.
    """
    n = {i: len(ops) for i, ops in IMPLEMENTATIONS.items()}
    rows = [("frozen", n["frozen"], 0), ("naive", n["naive"], 0), ("compiled", n["compiled"], 0), ("split", n["split"], 0), ("looped", 0, n["split"]), ("routed", n["split"], 0), ("merged_launch", n["naive"], 0)]
    fixed = microbatches.sparkSession.createDataFrame(rows, "impl string, once int, each int")
    met = microbatches.select("mb", "adapter_id").distinct().groupBy("mb").agg(F.count(F.lit(1)).alias("adapters"))
    total = met.agg(F.count(F.lit(1)).alias("microbatches"), F.coalesce(F.sum("adapters"), F.lit(0)).alias("adapters"))  # one row
    return total.crossJoin(F.broadcast(fixed)).select("impl", "microbatches", (F.col("once") * F.col("microbatches") + F.col("each") * F.col("adapters")).alias("launches"))
