"""Samples and heats by hashes: the same rows in every run, on any cluster."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ticks import COIN_RANGE, coin

GAMMA = 2


def rounds_for(purpose: str, n: int, k: int = 1, delta: float = 0.1) -> int:
    """Repetitions t the analysis asks for; experiments use 1."""
    n, k = max(2, n), max(1, k)
    value = {"max": 2 * math.log(2 / delta), "kcenter_band": math.log(2 * k / delta), "kcenter_coin": math.log(n / delta), "linkage": 2 * math.log(n / delta), "experiment": 1}[purpose]
    return max(1, math.ceil(value))


def share(column: Column) -> Column:
    return column / float(COIN_RANGE)


def drawn(size: int, n: int, seed: int) -> Column:
    """Whether `size` draws with replacement would hold the record: true with probability 1 - (1 - 1/n)**size."""
    kept = 1 - (1 - 1 / max(1, n)) ** size
    return coin(seed, F.lit("draw"), F.col("id")) < int(kept * COIN_RANGE)


def draw(df: DataFrame, size: int, n: int, seed: int) -> DataFrame:
    """The records that draws with replacement would hold, each once, by a map alone."""
    return df.where(drawn(size, n, seed))


def draw_slots(df: DataFrame, size: int, n: int, seed: int) -> DataFrame:
    """Exactly `size` draws with replacement: (slot, id, val), where df has a dense column `at` from 0 to n - 1."""
    slots = df.sparkSession.range(size).select(F.col("id").alias("slot"), F.pmod(coin(seed, F.lit("slot"), F.col("id")), F.lit(n)).alias("at"))
    return slots.join(df, "at").drop("at")


def thin(df: DataFrame, m: int, n: int, delta: float = 0.1, gamma: float = GAMMA, seed: int = 7) -> DataFrame:
    """Keeps a record with probability gamma ln(n / delta) / m, at most 1; m is the size of the smallest cluster."""
    kept = min(1.0, gamma * math.log(max(2, n) / delta) / max(1, m))
    return df.where(coin(seed, F.lit("thin"), F.col("id")) < int(kept * COIN_RANGE))


def stratified(df: DataFrame, by: str, per_stratum: int, seed: int) -> DataFrame:
    """At most so many rows of each stratum, lowest coins first."""
    from pyspark.sql import Window as W

    order = W.partitionBy(by).orderBy(coin(seed, F.lit("stratum"), F.col("id")), "id")
    return df.withColumn("__n", F.row_number().over(order)).where(F.col("__n") <= per_stratum).drop("__n")


def deal_heats(df: DataFrame, heats: int, rounds: int, seed: int, marked: Column | None = None) -> DataFrame:
    """Every record once in each round, in one of `heats` parts of nearly equal size: round, heat, pos, id, val, and the mark (in the first round)."""
    dealt = df.select("id", "val", (F.lit(False) if marked is None else marked).alias("mark"), F.explode(F.sequence(F.lit(1), F.lit(rounds))).alias("round"))
    pos = coin(seed, F.lit("heat"), F.col("round"), F.col("id"))
    return dealt.select("round", F.pmod(pos, F.lit(heats)).alias("heat"), pos.alias("pos"), "id", "val", (F.col("mark") & (F.col("round") == 1)).alias("mark"))
