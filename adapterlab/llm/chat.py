"""Chat formatting by perspective rotation.

Each participant in turn is the assistant: that speaker's turns are rendered as assistant messages and carry
the loss mask, all other speakers become named users, instructions stay system messages. A dialogue is kept
as ordered segments with their character offsets, so that a conversation of any length is spread over
tasks; `assemble` joins the segments of conversations that are known to be short.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from adapterlab.llm.common import checkpointed

OPEN, CLOSE = "<|start|>", "<|end|>\n"
SYSTEM_ROLES = ("system",)


def _safe(c: Column) -> Column:
    """Control markers inside a text or a name are broken up, so that a text can't forge a turn."""
    return F.replace(c, F.lit("<|"), F.lit("< |"))


def _head(c: Column) -> Column:
    return _safe(F.regexp_replace(c, r"[\r\n]", " "))


def _header(system_roles: tuple[str, ...]) -> Column:
    return (
        F.when(F.col("speaker") == F.col("perspective"), F.lit(f"{OPEN}assistant\n"))
        .when(F.col("speaker").isin(*system_roles), F.lit(f"{OPEN}system\n"))
        .otherwise(F.concat(F.lit(f"{OPEN}user name="), _head(F.col("speaker")), F.lit("\n")))
    )


def rotate_perspectives(turns: DataFrame, system_roles: tuple[str, ...] = SYSTEM_ROLES, partitions: int | None = None) -> DataFrame:
    """Segments (conv_id, perspective, position, turn, speaker, segment, mask_start, mask_end, start).

    `perspective`: the participant rendered as assistant. `position`: 0, 1, ... within the dialogue. `start`:
    the segment's first character in the dialogue. Characters mask_start <= i < mask_end of the segment (the
    reply and its end marker) count for the loss; both are 0 where another one speaks.

    Turns come in the order of turn (null first), then speaker, then text; equal rows stay repeated. A null
    role is the speaker `unknown`, a null text is empty, a null conv_id is a conversation of its own. A
    conversation without participants (only instructions) gives no row. Other columns are not read.
    """
    spark = turns.sparkSession
    n = partitions or int(spark.conf.get("spark.sql.shuffle.partitions"))
    speaker = F.coalesce(F.col("role"), F.lit("unknown"))
    rows = turns.select(
        "conv_id", "turn", speaker.alias("speaker"), F.coalesce("text", F.lit("")).alias("text"), F.xxhash64("conv_id").alias("ck")
    ).withColumn("uid", F.monotonically_increasing_id())
    order = ["ck", "conv_id", "turn", "speaker", "text", "uid"]
    # Ranges cut one long conversation anywhere. Sorted ranges give every turn a number in the order of all turns; they
    # are written out once, since range bounds are sampled.
    sorted_rows = rows.repartitionByRange(n, *order).sortWithinPartitions(*order)
    rows = checkpointed(sorted_rows.drop("uid").withColumn("seq", F.monotonically_increasing_id()))

    # Places are found on lengths alone; texts are joined at the end, by number.
    plain = F.length(_safe(F.col("text"))) + F.lit(len(CLOSE))
    slim = rows.select("seq", "ck", "conv_id", "speaker", plain.cast("long").alias("body"), F.hash("ck").alias("k"))
    who = rows.where(~F.col("speaker").isin(*system_roles)).select("ck", "conv_id", F.col("speaker").alias("perspective")).distinct()
    who = who.withColumn("k", F.hash("ck"))
    views = slim.alias("r").join(who.alias("w"), (F.col("r.k") == F.col("w.k")) & F.col("r.conv_id").eqNullSafe(F.col("w.conv_id"))).select(
        "seq", "r.ck", "r.conv_id", "perspective", "body", _header(system_roles).alias("header"), F.shiftright("seq", 33).alias("range")
    )
    views = views.withColumn("chars", F.length("header") + F.col("body"))

    keys = ["ck", "conv_id", "perspective", "range"]
    local = Window.partitionBy(*keys).orderBy("seq")
    views = views.withColumns({
        "at": F.row_number().over(local).cast("long") - 1,
        "before": F.coalesce(F.sum("chars").over(local.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)),
    })
    # One row per dialogue and range; a dialogue has at most as many as there are ranges.
    parts = views.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"), F.sum("chars").alias("c"))
    earlier = Window.partitionBy("ck", "conv_id", "perspective").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    base = parts.select(
        *(F.col(k).alias(f"b_{k}") for k in keys), F.coalesce(F.sum("n").over(earlier), F.lit(0)).alias("b_n"), F.coalesce(F.sum("c").over(earlier), F.lit(0)).alias("b_c")
    )
    on = [F.col(k).eqNullSafe(F.col(f"b_{k}")) if k == "conv_id" else F.col(k) == F.col(f"b_{k}") for k in keys]
    placed = views.join(base, on).select(
        F.col("seq").alias("p_seq"), "perspective", "header", (F.col("at") + F.col("b_n")).alias("position"), (F.col("before") + F.col("b_c")).alias("start")
    )
    own = F.col("speaker") == F.col("perspective")
    return rows.join(placed, F.col("seq") == F.col("p_seq")).withColumn("segment", F.concat("header", _safe(F.col("text")), F.lit(CLOSE))).select(
        "conv_id", "perspective", "position", "turn", "speaker", "segment",
        F.when(own, F.length("header")).otherwise(0).alias("mask_start"), F.when(own, F.length("segment")).otherwise(0).alias("mask_end"), "start",
    )


def assemble(segments: DataFrame, max_segments: int = 4096) -> DataFrame:
    """(conv_id, perspective, text, spans) of dialogues with up to `max_segments` segments.

    Longer dialogues are not built as one string; they stay available as segments.
    """
    short = segments.groupBy("conv_id", "perspective").agg(F.max("position").alias("last")).where(F.col("last") < max_segments)
    short = short.select(F.col("conv_id").alias("s_conv"), F.col("perspective").alias("s_who"))
    rows = segments.join(short, F.col("conv_id").eqNullSafe(F.col("s_conv")) & (F.col("perspective") == F.col("s_who")), "left_semi")
    item = F.struct("position", "segment", (F.col("start") + F.col("mask_start")).alias("a"), (F.col("start") + F.col("mask_end")).alias("b"))
    packed = rows.groupBy("conv_id", "perspective").agg(F.array_sort(F.collect_list(item)).alias("items"))
    return packed.select(
        "conv_id", "perspective",
        F.array_join(F.transform("items", lambda x: x["segment"]), "").alias("text"),
        F.transform(F.filter("items", lambda x: x["b"] > x["a"]), lambda x: F.struct(x["a"].alias("start"), x["b"].alias("end"))).alias("spans"),
    )


CHAT_SQL = r"""
WITH rows AS (
  SELECT conv_id, turn, coalesce(role, 'unknown') AS speaker, coalesce(text, '') AS text FROM conversations
), who AS (
  SELECT DISTINCT conv_id, speaker AS perspective FROM rows WHERE speaker <> 'system'
), views AS (
  SELECT r.conv_id, w.perspective, r.turn, r.speaker, r.text,
    CASE WHEN r.speaker = w.perspective THEN '<|start|>assistant' || chr(10)
         WHEN r.speaker = 'system' THEN '<|start|>system' || chr(10)
         ELSE '<|start|>user name=' || replace(regexp_replace(r.speaker, '[\r\n]', ' ', 'g'), '<|', '< |') || chr(10) END AS header
  FROM rows r JOIN who w ON r.conv_id IS NOT DISTINCT FROM w.conv_id
), segs AS (
  SELECT *, header || replace(text, '<|', '< |') || '<|end|>' || chr(10) AS segment FROM views
)
SELECT conv_id, perspective,
  CAST(row_number() OVER (PARTITION BY conv_id, perspective ORDER BY turn NULLS FIRST, speaker, text) - 1 AS BIGINT) AS position,
  turn, speaker, segment,
  CAST(CASE WHEN speaker = perspective THEN length(header) ELSE 0 END AS INT) AS mask_start,
  CAST(CASE WHEN speaker = perspective THEN length(segment) ELSE 0 END AS INT) AS mask_end,
  CAST(coalesce(sum(length(segment)) OVER (PARTITION BY conv_id, perspective ORDER BY turn NULLS FIRST, speaker, text
    ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start
FROM segs
"""
