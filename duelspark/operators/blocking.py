"""Blocking: tokens choose candidate pairs, so that not all pairs are asked about."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.ticks import COIN_RANGE, coin


def tokens(text: Column) -> Column:
    return F.array_distinct(F.filter(F.split(F.lower(text), "[^a-z0-9]+"), lambda t: t != ""))


def token_pairs(df: DataFrame, text_column: str, min_common: int = 1) -> DataFrame:
    """a, b, common for all pairs of records (id, text) that share at least min_common tokens: nothing is capped.

    Tokens are ordered from the rarest to the most frequent. Two records that share min_common of them share one among all but
    the min_common - 1 most frequent of each, so only these prefixes are joined, and the most frequent tokens hardly open a pair.
    Equal token sets are one class: a pair of classes is compared once, however many records each has.
    """
    sets = df.select("id", F.array_sort(tokens(F.col(text_column))).alias("tokens")).where(F.size("tokens") >= min_common)
    classes = sets.groupBy("tokens").agg(F.min("id").alias("rep"), F.count("*").alias("n"))
    exploded = classes.select("rep", "n", F.explode("tokens").alias("token"))
    frequency = exploded.groupBy("token").agg(F.sum("n").alias("df"))
    ranked = exploded.join(frequency, "token").groupBy("rep").agg(F.array_sort(F.collect_list(F.struct("df", "token"))).alias("t"))
    ordered = ranked.select("rep", F.transform("t", lambda x: x["token"]).alias("tokens"))
    prefix = ordered.select("rep", "tokens", F.explode(F.slice("tokens", 1, F.size("tokens") - (min_common - 1))).alias("token"))
    one, two = prefix.withColumnsRenamed({"rep": "x", "tokens": "p"}), prefix.withColumnsRenamed({"rep": "y", "tokens": "q"})
    shared = F.array_intersect("p", "q")
    first = F.col("token") == F.get(F.filter(shared, lambda s: F.array_contains(F.slice("p", 1, F.size("p") - (min_common - 1)), s) & F.array_contains(F.slice("q", 1, F.size("q") - (min_common - 1)), s)), F.lit(0))
    met = one.join(two, "token").where((F.col("x") <= F.col("y")) & (F.size(shared) >= min_common) & first).select("x", "y", F.size(shared).cast("long").alias("common"))
    member = sets.join(classes.select("tokens", "rep"), "tokens").select("rep", "id")
    pairs = met.join(member.withColumnsRenamed({"rep": "x", "id": "u"}), "x").join(member.withColumnsRenamed({"rep": "y", "id": "v"}), "y")
    return pairs.where((F.col("x") != F.col("y")) | (F.col("u") < F.col("v"))).select(F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b"), "common")


def drawn_partners(df: DataFrame, text_column: str, names: tuple[str, ...], min_common: int = 2, seed: int = 7) -> DataFrame:
    """id, and for each name a struct (b, common): a record drawn at random, all alike, from those that token_pairs pairs with it; records without one are left out.

    Records of equal token sets are one class, and have the same candidates but for themselves: a place among them is drawn and found
    again, so the pairs, whose number grows with the square of a class, are never written out. Candidates of a class are those
    of its pairs of classes; no candidate is left out.
    """
    from pyspark.sql import Window as W

    sets = df.select("id", F.array_sort(tokens(F.col(text_column))).alias("tokens")).where(F.size("tokens") >= min_common)
    classes = sets.groupBy("tokens").agg(F.min("id").alias("rep"), F.count("*").alias("n"))
    one = classes.select(F.col("rep").alias("id"), F.concat_ws(" ", "tokens").alias("t"))
    met = token_pairs(one, "t", min_common)  # pairs of different classes
    both = met.unionByName(met.select(F.col("b").alias("a"), F.col("a").alias("b"), "common"))
    own = classes.select(F.col("rep").alias("a"), F.col("rep").alias("b"), F.size("tokens").cast("long").alias("common"))
    near = both.unionByName(own).join(classes.select(F.col("rep").alias("b"), F.col("n").alias("size")), "b")
    order = W.partitionBy("a").orderBy("b")
    spans = near.withColumn("end", F.sum("size").over(order.rowsBetween(W.unboundedPreceding, 0))).withColumn("begin", F.col("end") - F.col("size"))
    total = near.groupBy("a").agg(F.sum("size").alias("total"))
    placed = sets.join(classes.select("tokens", "rep"), "tokens").select("id", "rep", (F.row_number().over(W.partitionBy("rep").orderBy("id")) - 1).cast("long").alias("place"))
    mine = spans.where("a = b").select(F.col("a").alias("rep"), F.col("begin").alias("first"))
    asked = placed.join(mine, "rep").join(total.withColumnRenamed("a", "rep"), "rep").where("total > 1").withColumn("self", F.col("first") + F.col("place"))
    slot = lambda name: F.floor(coin(seed, F.lit(name), F.col("id")) * (F.col("total") - 1) / float(COIN_RANGE)).cast("long")
    tossed = asked.select("id", "rep", "self", F.explode(F.array(*(F.struct(F.lit(n).alias("name"), slot(n).alias("slot")) for n in names))).alias("d")).select("id", "rep", "d.name", (F.col("d.slot") + (F.col("d.slot") >= F.col("self")).cast("long")).alias("slot"))
    found = tossed.join(spans.withColumnRenamed("a", "rep"), "rep").where("slot >= begin AND slot < end").select("id", "name", "common", F.col("b").alias("of"), (F.col("slot") - F.col("begin")).alias("place"))
    named = found.join(placed.select(F.col("rep").alias("of"), "place", F.col("id").alias("b")), ["of", "place"])
    return named.groupBy("id").agg(*(F.first(F.when(F.col("name") == n, F.struct("b", "common")), ignorenulls=True).alias(n) for n in names))
