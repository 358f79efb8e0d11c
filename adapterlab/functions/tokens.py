"""Token length models and padding, as columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def chars4(text: Column) -> Column:
    """A token for every four characters begun."""
    return F.floor((F.length(text) + 3) / 4).cast("bigint")


def words(text: Column) -> Column:
    return F.size(F.filter(F.split(text, r"[ \t\n\r]+"), lambda w: w != "")).cast("bigint")


MODELS = {"chars4": chars4, "words": words}


def pad_to(tokens: Column, multiple: int | Column) -> Column:
    """Rounded up to a multiple (B6)."""
    m = F.lit(multiple) if isinstance(multiple, int) else multiple
    return (F.ceil(tokens / m) * m).cast("bigint")


def padded(tokens: int, multiple: int) -> int:
    return -(-tokens // multiple) * multiple


def order_key(seed: Column | int, dataset: Column, sample_id: Column) -> Column:
    """Deterministic shuffle (G7): hex digest, compared bytewise, the same in any engine."""
    s = F.lit(seed) if isinstance(seed, int) else seed
    return F.md5(F.concat_ws("-", s.cast("string"), dataset, sample_id.cast("string")))
