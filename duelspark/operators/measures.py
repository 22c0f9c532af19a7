"""Measures of accuracy and cost. They see the true values; the methods do not."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

QUESTION_PRICE = 0.06  # fixed value: dollars for a crowd question, majority of three


def rank_of(df: DataFrame, winner: DataFrame) -> DataFrame:
    """winner with `rank` (1 is the largest) in descending order of true values, without a window over all rows."""
    above = df.crossJoin(F.broadcast(winner.select(F.col("winner_val").alias("__w")))).agg(F.sum((F.col("val") > F.col("__w")).cast("long")).alias("__n"))
    return winner.crossJoin(above).withColumn("rank", F.coalesce("__n", F.lit(0)) + 1).drop("__n")


def against_best(df: DataFrame, winner: DataFrame, want: str = "max") -> DataFrame:
    """winner with best_val, ratio (at least 1) and gap to the optimum."""
    best = df.agg((F.max("val") if want == "max" else F.min("val")).alias("best_val"))
    ratio = F.col("best_val") / F.col("winner_val") if want == "max" else F.col("winner_val") / F.col("best_val")
    return winner.crossJoin(best).withColumn("ratio", F.round(ratio, 6)).withColumn("gap", F.abs(F.col("best_val") - F.col("winner_val")))


def confusion_set(df: DataFrame, mu: float) -> DataFrame:
    """n, confused (records within 1 + mu of the maximum, itself included), share."""
    best = F.broadcast(df.agg(F.max("val").alias("best")))
    near = (F.col("best").cast("decimal(38,0)") * 1000 <= F.col("val").cast("decimal(38,0)") * (1000 + round(mu * 1000))).cast("long")
    return df.crossJoin(best).agg(F.count("*").alias("n"), F.sum(near).alias("confused")).withColumn("share", F.round(F.col("confused") / F.col("n"), 6))


def objective(assignment: DataFrame) -> DataFrame:
    """radius: the largest distance of a record to its center."""
    return assignment.agg(F.max("dist").alias("radius"))


def assignment_quality(assignment: DataFrame, df: DataFrame, centers: list, metric) -> DataFrame:
    """worst: the largest ratio of the assigned to the nearest center's distance (by row)."""
    from .kcenter import literal

    nearest = F.least(*(metric(F.col("payload"), literal(c["payload"])) for c in centers), F.lit(1 << 62))
    both = assignment.join(df.select("id", nearest.alias("near")), "id")
    return both.agg(F.round(F.max(F.when(F.col("near") > 0, F.col("dist") / F.col("near")).otherwise(F.when(F.col("dist") == 0, 1.0))), 6).alias("worst"))


def pair_fscores(assignment: DataFrame, truth: DataFrame, by: list[str], of: list[str]) -> DataFrame:
    """by, pairs_same, pairs_said, pairs_both, precision, recall, fscore over pairs in one cluster for each of many assignments (by, id, center_id).

    truth: (of, id, truth), where `of` are those of `by` that name the set. Contingency tables, no pair join; a share of no pairs is null.
    """
    pairs = F.sum(F.col("n") * (F.col("n") - 1) / 2).cast("long")
    cells = assignment.select(*by, "id", "center_id").join(truth.select(*of, "id", "truth"), [*of, "id"]).groupBy(*by, "truth", "center_id").agg(F.count("*").alias("n"))
    both = cells.groupBy(*by).agg(pairs.alias("pairs_both"))
    whole = lambda c, name: cells.groupBy(*by, c).agg(F.sum("n").alias("n")).groupBy(*by).agg(pairs.alias(name))
    same, said = whole("truth", "pairs_same"), whole("center_id", "pairs_said")
    out = both.join(same, by).join(said, by) if by else both.crossJoin(same).crossJoin(said)
    precision, recall = F.try_divide("pairs_both", "pairs_said"), F.try_divide("pairs_both", "pairs_same")
    return out.withColumn("precision", F.round(precision, 6)).withColumn("recall", F.round(recall, 6)).withColumn("fscore", F.round(F.try_divide(2 * precision * recall, precision + recall), 6))


def pair_fscore(assignment: DataFrame, truth: DataFrame) -> DataFrame:
    """pairs_both, pairs_same, pairs_said, precision, recall, fscore of one assignment."""
    return pair_fscores(assignment, truth, [], [])


def class_pairs(df: DataFrame) -> DataFrame:
    """x, y, n: all pairs of rows, as pairs of classes of equal rows (structs x, y) and the number n of their pairs. No pair is left out; classes meet instead of rows."""
    classes = df.groupBy(*df.columns).agg(F.count("*").alias("m")).select(F.struct(*df.columns).alias("x"), "m")
    met = classes.crossJoin(classes.select(F.col("x").alias("y"), F.col("m").alias("k"))).where(F.col("x") <= F.col("y"))
    return met.select("x", "y", F.when(F.col("x") == F.col("y"), F.shiftright(F.col("m") * (F.col("m") - 1), 1)).otherwise(F.col("m") * F.col("k")).alias("n"))


def pair_answers_fscore(pairs: DataFrame) -> DataFrame:
    """The same for direct yes/no answers: columns truth and yes, and n if a row stands for that many pairs."""
    n = F.col("n") if "n" in pairs.columns else F.lit(1)
    hit, said, same = (F.sum(c.cast("long") * n) for c in (F.col("truth") & F.col("yes"), F.col("yes"), F.col("truth")))
    return pairs.agg(said.alias("pairs_said"), same.alias("pairs_same"), hit.alias("pairs_both"), F.round(hit / said, 6).alias("precision"), F.round(hit / same, 6).alias("recall"), F.round(2 * hit / (said + same), 6).alias("fscore"))


def core_purity(core: list, truth: DataFrame, center: int) -> DataFrame:
    """members, purity: the share of a core (rows with an id) that has the center's true cluster."""
    of = truth.where(F.col("id").isin([c["id"] for c in core]))
    own = truth.where(F.col("id") == center).select(F.col("truth").alias("own"))
    return of.crossJoin(F.broadcast(own)).agg(F.count("*").alias("members"), F.round(F.avg((F.col("truth") == F.col("own")).cast("double")), 6).alias("purity"))


def merged_distance(merges: DataFrame) -> DataFrame:
    """step, running mean of the distances merged so far, and the change to the step before."""
    from pyspark.sql import Window as W

    order = W.partitionBy("block").orderBy("step")
    out = merges.withColumn("mean_dist", F.avg("link_dist").over(order.rowsBetween(W.unboundedPreceding, 0)))
    return out.select("block", "step", F.round("mean_dist", 3).alias("mean_dist"), F.round(F.col("mean_dist") - F.lag("mean_dist").over(order), 3).alias("change"))


def per_merge_ratio(merges: DataFrame) -> DataFrame:
    """worst, mean: each merged distance over the best that was available at that step (column best_dist of a measured hierarchy)."""
    ratio = F.when(F.col("best_dist") > 0, F.col("link_dist") / F.col("best_dist")).when(F.col("link_dist") == 0, 1.0)
    return merges.agg(F.round(F.max(ratio), 6).alias("worst"), F.round(F.avg(ratio), 6).alias("mean"))


def _over(ours: Column, best: Column) -> Column:
    """ours / best; 1 where both are 0, null where only the best is."""
    return F.round(F.when(best != 0, F.try_divide(ours, best)).when(ours == 0, 1.0), 6)


def by_iteration(merges: DataFrame, exact: DataFrame) -> DataFrame:
    """block, step, mean distance merged until then over that of the exact hierarchy at the same step."""
    from pyspark.sql import Window as W

    so_far = W.partitionBy("block").orderBy("step").rowsBetween(W.unboundedPreceding, 0)
    mean = lambda df, name: df.select("block", "step", F.avg("link_dist").over(so_far).alias(name))
    return mean(merges, "ours").join(mean(exact, "best"), ["block", "step"]).select("block", "step", _over(F.col("ours"), F.col("best")).alias("ratio"))


def merge_ratio(merges: DataFrame, exact: DataFrame) -> DataFrame:
    """Mean merged distance over that of the exact hierarchy (which is 1)."""
    mean = lambda df, name: df.agg(F.avg("link_dist").alias(name))
    return mean(merges, "ours").crossJoin(mean(exact, "best")).select(_over(F.col("ours"), F.col("best")).alias("ratio"))


def kcenter_bound(mu: float) -> float:
    """2 alpha beta**2 with a frontier within (1 + mu)**5 and an assignment within (1 + mu)**2."""
    return 2 * (1 + mu) ** 9


def cost(questions: int, price: float = QUESTION_PRICE) -> float:
    return round(questions * price, 2)
