"""Win scores: how many opponents a record is believed to be above."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ticks import coin
from .judges import Judge, item

BROADCAST_ROWS = 20_000
Beats = Callable[[Column, Column], Column]


def opponents(pool: DataFrame, against: DataFrame, apart: Column, how: str = "inner", rows: int | None = None) -> DataFrame:
    """pool joined with `against` where `apart` holds. `against` is broadcast up to BROADCAST_ROWS rows, and dealt to a grid of cells beyond."""
    rows = against.count() if rows is None else rows
    if rows <= BROADCAST_ROWS:
        return pool.join(F.broadcast(against), apart, how)
    cells = math.ceil(rows / BROADCAST_ROWS)
    spread = pool.withColumn("__cell", F.explode(F.sequence(F.lit(0), F.lit(cells - 1))))  # each record meets every cell once
    dealt = against.withColumn("__part", F.pmod(F.xxhash64(*against.columns), F.lit(cells)).cast("int"))
    return spread.join(dealt, (F.col("__cell") == F.col("__part")) & apart, how).drop("__cell", "__part")


def _scores(pool: DataFrame, against: DataFrame, said: Column, name: str, rows: int | None) -> DataFrame:
    other = against.select(F.col("id").alias("o_id"), F.col("val").alias("o_val"))
    asked = opponents(pool.select("id", "val"), other, F.col("id") != F.col("o_id"), "left", rows)
    return asked.groupBy("id").agg(F.coalesce(F.sum(F.when(F.col("o_id").isNotNull(), said.cast("long"))), F.lit(0)).cast("long").alias(name))


def win_scores(pool: DataFrame, against: DataFrame, judge: Judge, rows: int | None = None) -> DataFrame:
    """id, wins: for each record of pool the records of `against` it is judged above; itself is skipped. `rows` is the size of `against`, if known."""
    return _scores(pool, against, judge.beats(item(F.col("id"), F.col("val")), item(F.col("o_id"), F.col("o_val"))), "wins", rows)


def loss_scores(pool: DataFrame, against: DataFrame, judge: Judge, rows: int | None = None) -> DataFrame:
    """For minimum problems: the records it is judged at most."""
    return _scores(pool, against, judge.at_most(item(F.col("id"), F.col("val")), item(F.col("o_id"), F.col("o_val"))), "wins", rows)


def win_scores_by(df: DataFrame, by: str, judge: Judge) -> DataFrame:
    """by, id, wins: win scores of the records (by, id, val) inside every group. Each pair is asked once; an equi-join on the group deals the pairs."""
    entry = lambda name: df.select(by, item(F.col("id"), F.col("val")).alias(name))
    said = entry("x").join(entry("y"), by).where("x.id < y.id").select(by, "x", "y", judge.beats(F.col("x"), F.col("y")).alias("won"))
    credit = said.select(by, F.explode(F.array(F.struct("x.id", F.col("won").cast("long").alias("w")), F.struct("y.id", (~F.col("won")).cast("long").alias("w")))).alias("c")).select(by, "c.*")
    return credit.unionByName(df.select(by, "id", F.lit(0).cast("long").alias("w"))).groupBy(by, "id").agg(F.sum("w").alias("wins"))


def round_robin(pool: DataFrame, judge: Judge | None, grid: int | None = None, beats: Beats | None = None) -> DataFrame:
    """id, val, wins. Each pair is asked once and both ends are credited; beats(x, y), if given, compares two entries in the judge's place.

    With `grid` the pool is hashed to so many blocks and every pair of blocks is a cell of an equi-join, so that a pool too
    large to broadcast is spread evenly; without it one side is broadcast.
    """
    if grid:
        part = F.pmod(F.xxhash64("id"), F.lit(grid)).cast("int")
        cells = lambda own: F.explode(F.transform(F.sequence(F.lit(0), F.lit(grid - 1)), lambda o: F.struct(*((F.col("part").alias("r"), o.alias("c")) if own else (o.alias("r"), F.col("part").alias("c"))))))
        parted = pool.select("id", "val", part.alias("part"))
        left = parted.select(F.col("id").alias("a"), F.col("val").alias("x"), cells(True).alias("cell"))
        right = parted.select(F.col("id").alias("b"), F.col("val").alias("y"), cells(False).alias("cell"))
        both = left.join(right, (left["cell"] == right["cell"]) & (F.col("a") < F.col("b")))
    else:
        left = pool.select(F.col("id").alias("a"), F.col("val").alias("x"))
        right = F.broadcast(pool.select(F.col("id").alias("b"), F.col("val").alias("y")))
        both = left.join(right, F.col("a") < F.col("b"))
    entry = lambda id_, val: F.struct(F.col(id_).alias("id"), F.col(val).alias("val"))
    won = beats(entry("a", "x"), entry("b", "y")) if beats else judge.beats(item(F.col("a"), F.col("x")), item(F.col("b"), F.col("y")))
    said = both.select("a", "b", won.alias("won"))
    credit = said.select(F.explode(F.array(F.struct(F.col("a").alias("id"), F.col("won").cast("long").alias("w")), F.struct(F.col("b").alias("id"), (~F.col("won")).cast("long").alias("w")))).alias("c")).select("c.*")
    wins = credit.groupBy("id").agg(F.sum("w").alias("wins"))
    return pool.select("id", "val").join(wins, "id", "left").withColumn("wins", F.coalesce("wins", F.lit(0)))


def pick(scored: DataFrame, seed: int = 7) -> DataFrame:
    """The row with the highest score; ties by a coin, then by id."""
    return scored.orderBy(F.desc("wins"), coin(seed, F.lit("tie"), F.col("id")), "id").limit(1)
