"""Tiles of rows with one adapter each, and launches by implementation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from adapterlab.operators.numbering import rank_within


def build_tiles(x: DataFrame, m_tile: int = 32) -> DataFrame:
    """(adapter_id, tile, first_row, last_row, n): each adapter's rows in order, `m_tile` at a time; the last may be short."""
    at = rank_within(x.select("adapter_id", "row_id"), ["adapter_id"], ["row_id"])
    tile = F.floor(F.col("rn") / m_tile).cast("bigint")
    return at.groupBy("adapter_id", tile.alias("tile")).agg(F.min("row_id").alias("first_row"), F.max("row_id").alias("last_row"), F.count(F.lit(1)).alias("n"))


def padded_tiles(tiles: DataFrame, m_tile: int = 32) -> DataFrame:
    """(adapter_id, tiles, rows, padded_rows)"""
    return tiles.groupBy("adapter_id").agg(F.count(F.lit(1)).alias("tiles"), F.sum("n").alias("rows"), (F.count(F.lit(1)) * m_tile).alias("padded_rows"))
