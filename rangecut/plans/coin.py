"""Draws that depend on a row's own values only: the same in every rerun, whatever the partitions."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

RANGE = 1 << 32


def draw(columns: Sequence[str], seed: int, stream: int | str, portable: bool = True) -> Column:
    """A draw in 0..2^32-1. ``portable`` is the beginning of an md5, which other engines can repeat; else xxhash64."""
    parts = [F.lit(str(seed)), F.lit(str(stream)), *(F.col(c).cast("string") for c in columns)]
    if portable:
        return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("long")
    return F.shiftrightunsigned(F.xxhash64(*parts), 32)


def draw_sql(columns: Sequence[str], seed: int, stream: int | str) -> str:
    """The portable draw in DuckDB's SQL."""
    text = " || '|' || ".join([f"'{seed}|{stream}'", *(f"{c}::VARCHAR" for c in columns)])
    return f"('0x' || substr(md5({text}), 1, 8))::BIGINT"


def threshold(numerator: int, denominator: int) -> int:
    """Draws below it have the probability numerator / denominator."""
    return RANGE if numerator >= denominator else numerator * RANGE // denominator
