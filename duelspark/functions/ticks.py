"""Numeric ground rules: values as integer ticks, and a persistent coin that any SQL engine can repeat."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

SCALE = 1_000_000
COIN_RANGE = 1 << 32


def ticks(value: Column) -> Column:
    """A double as whole millionths; all comparisons are made on these."""
    return F.floor(value.cast("double") * SCALE).cast("long")


def coin(seed: int, *keys: Column) -> Column:
    """A number from 0 to 2**32 - 1 that depends on the seed and the keys alone: asking again gives the same."""
    text = F.concat_ws("|", F.lit(str(seed)), *(k.cast("string") for k in keys))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long")


def coin_sql(seed: int, *keys: str) -> str:
    """The same for DuckDB."""
    return f"CAST('0x' || substr(md5(concat_ws('|', '{seed}', {', '.join(keys)})), 1, 8) AS BIGINT)"


def threshold(probability: float) -> int:
    """A coin below this falls with the given probability."""
    return int(probability * COIN_RANGE)
