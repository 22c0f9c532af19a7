"""The baselines the methods are compared with."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.metrics import Metric
from ..functions.ticks import coin
from ..plans.lineage import cut
from . import extremum, kcenter, linkage, sampling
from .judges import Judge, grade


def knockout(df: DataFrame, judge: Judge, want: str = "max", seed: int = 7) -> DataFrame:
    """A binary tournament over all records: winner_id, winner_val, questions.

    Heats of sqrt(n) records play in parallel, then their winners do; each record is asked about once a level.
    """
    directed = judge.reversed() if want == "min" else judge
    n = df.count()
    first = extremum.heat_winners(df, directed, max(1, math.isqrt(n)), 1, seed).select("id", "val")
    last = extremum.heat_winners(first, directed, 1, 1, seed + 1)
    return last.select(F.col("id").alias("winner_id"), F.col("val").alias("winner_val"), F.lit(max(0, n - 1)).cast("long").alias("questions"))


def sampled_round_robin(df: DataFrame, judge: Judge, want: str = "max", seed: int = 7) -> DataFrame:
    """sqrt(n) records, all pairs of them."""
    n = df.count()
    return extremum.round_robin(sampling.draw(df, max(1, math.ceil(math.sqrt(n))), n, seed), judge, want, seed)


def truth(df: DataFrame, want: str = "max") -> DataFrame:
    """The true optimum; ties to the smaller id."""
    best = F.max(F.struct("val", (-F.col("id")).alias("n"))) if want == "max" else F.min(F.struct("val", F.col("id").alias("n")))
    return df.agg(best.alias("w")).where(F.col("w").isNotNull()).select(F.abs("w.n").alias("winner_id"), F.col("w.val").alias("winner_val"))


def kcenter_knockout(df: DataFrame, k: int, metric: Metric, judge: Judge, **more) -> tuple[DataFrame, list[int]]:
    return kcenter.band(df, k, metric, judge, frontier="knockout", assign="incumbent", **more)


def kcenter_sampled(df: DataFrame, k: int, metric: Metric, judge: Judge, seed: int = 7, first: int | None = None) -> tuple[DataFrame, list[int]]:
    """Greedy on k ln n sampled records; then every record meets every pair of centers."""
    n = df.count()
    sample = sampling.draw(df, max(k, math.ceil(k * math.log(max(2, n)))), n, seed)
    if first is not None:
        sample = sample.unionByName(df.where(F.col("id") == first)).dropDuplicates(["id"])
    _, ids = kcenter.band(cut(sample), k, metric, judge, first=first, seed=seed)
    centers = [kcenter._center(df, c) for c in ids]
    return kcenter.finish(kcenter.assign_duels(df, centers, metric, judge), ids), ids


def feature_greedy(df: DataFrame, k: int, similarity: Callable[[Column, Column], Column], first: int | None = None) -> tuple[DataFrame, list[int]]:
    """k-center on an automatic distance, without any question."""
    from ..functions.metrics import one_minus

    return kcenter.exact_greedy(df, k, one_minus(similarity), first)


def graded_greedy(df: DataFrame, k: int, metric: Metric, same: Callable[[Column, Column], Column], first: int | None = None, seed: int = 7) -> tuple[DataFrame, list[int]]:
    """Greedy k-center on distance grades in place of comparisons: each record's grade to a center is off as the judge of grades errs.

    payload is a struct that holds `id`, by which a grade persists; same(a, b) says whether two payloads are one entity.
    """
    graded = lambda a, b: grade(metric(a, b), a["id"], b["id"], same(a, b), seed=seed)
    return kcenter.exact_greedy(df, k, graded, first, seed)


def same_cluster_pairs(df: DataFrame, pairs: int = 150, seed: int = 7) -> DataFrame:
    """a, b: at most so many different pairs of records drawn at random, each end by its own coin."""
    n = df.count()
    ranked = extremum.leaves(df.select("id", F.lit(0).alias("val")), n, seed).select("id", "pos")
    end = lambda s: F.pmod(coin(seed, F.lit("end"), F.lit(s), F.col("slot")), F.lit(max(1, n)))
    slots = df.sparkSession.range(2 * pairs).select(F.col("id").alias("slot"), end("a").alias("x"), end("b").alias("y")).where("x <> y")
    named = slots.join(ranked.withColumnsRenamed({"id": "u", "pos": "x"}), "x").join(ranked.withColumnsRenamed({"id": "v", "pos": "y"}), "y")
    both = named.select("slot", F.least("u", "v").alias("a"), F.greatest("u", "v").alias("b")).groupBy("a", "b").agg(F.min("slot").alias("slot"))
    return both.orderBy("slot").limit(pairs).select("a", "b")


def clusters_of_yes(df: DataFrame, yes: DataFrame) -> DataFrame:
    """id, center_id: components of the pairs (a, b) answered yes. Labels and the labels of labels are taken down until none moves; records in no pair wait outside."""
    both = cut(yes.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(yes.select(F.col("b").alias("u"), F.col("a").alias("v"))))
    label = both.select(F.col("u").alias("id"), F.col("u").alias("center_id")).distinct()
    while True:
        low = both.join(label.withColumnRenamed("id", "v"), "v").groupBy(F.col("u").alias("id")).agg(F.min("center_id").alias("low"))
        lowered = label.join(low, "id", "left").select("id", F.col("center_id").alias("old"), F.least("center_id", F.coalesce("low", "center_id")).alias("now"))
        up = label.select(F.col("id").alias("now"), F.col("center_id").alias("up"))  # a label's own label, one hop on
        after = cut(lowered.join(up, "now", "left").select("id", "old", F.least("now", F.coalesce("up", "now")).alias("center_id")))
        label = after.select("id", "center_id")
        if after.where("old <> center_id").isEmpty():
            return df.select("id").join(label, "id", "left").select("id", F.coalesce("center_id", "id").alias("center_id"))


def linkage_knockout(df: DataFrame, metric: linkage.PyMetric, judge: Judge, link: str = "single", **more) -> DataFrame:
    """The closest pair of clusters by a knockout over all pairs at every step."""
    return linkage.hierarchy(df, metric, judge, link, search="knockout", naive=True, **more)


def linkage_sampled(df: DataFrame, metric: linkage.PyMetric, judge: Judge, link: str = "single", **more) -> DataFrame:
    return linkage.hierarchy(df, metric, judge, link, search="sampled", naive=True, **more)


def linkage_exact(df: DataFrame, metric: linkage.PyMetric, link: str = "single", **more) -> DataFrame:
    """By true distances: every step merges the closest pair. On a line that is one of neighbours, so no other pair is looked at."""
    return linkage.hierarchy(df, metric, Judge.exact(), link, search="ordered" if metric is linkage.line else "robust", naive=False, **more)
