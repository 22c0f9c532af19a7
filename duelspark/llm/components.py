"""Connected components of a graph given as an edge table, by alternating star contractions.

Each round replaces edges by edges to smaller ids, first for larger neighbours of every node, then for smaller ones, with one
aggregation and one join each; nothing is collected, so a node may have any number of neighbours. Rounds are written to the
shared folder. The number of rounds grows with the logarithm of the diameter.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise, unmaterialise


def _round(edges: DataFrame) -> DataFrame:
    """edges (a > b): a large star, then a small star."""
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    large = both.where("v > u").join(least, "u").select(F.col("v").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
    least = large.groupBy("a").agg(F.min("b").alias("m"))
    small = large.join(least, "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e")).select("e.a", "e.b")
    return small.where("a <> b").distinct()


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """links (a, b) -> (id, component): the smallest id that each linked id reaches. Loops and repeated links are no matter; nulls are left out."""
    edges = materialise(links.where("a <> b").select(F.greatest("a", "b").cast("long").alias("a"), F.least("a", "b").cast("long").alias("b")).distinct(), "edges")
    state = None
    for _ in range(rounds):
        after = materialise(_round(edges), "edges")
        unmaterialise(edges)
        edges, before = after, state
        # every node but the roots has one edge, to a root, when nothing changes any more
        state = after.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if state == before or not state[0]:
            break
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    return edges.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct())
