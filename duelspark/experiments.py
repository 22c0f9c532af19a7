"""The experiments with all sets, settings and baselines, and what they are expected to show, as conditions that can fail.

A query `x` gives the measured numbers; `x_claims` gives a row (claim, held) for each thing the experiment shows.
"""

from __future__ import annotations

import functools
import math
import operator
from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import metrics
from .functions.metric_arrays import stepped
from .functions.ticks import COIN_RANGE, coin, ticks
from .operators import baselines, blocking, centers, extremum, kcenter, linkage, measures, noisefit, proximity, scores, votes
from .operators.judges import Judge, grade, item, pair_id
from .plans.lineage import cut
from .sources import tables
from .workloads import DELTA, HELD, REGIONS, SEED, WON, _around_sql, _won, around, held, query, winner

MUS, PS, RUNS = (0.0, 0.3, 0.5, 1.0, 2.0), (0.0, 0.1, 0.2, 0.3), 20


def claims(names: list[str]) -> str:
    return "SELECT * FROM (VALUES " + ", ".join(f"('{n}', TRUE)" for n in names) + ") AS v(claim, held)"


def claim(df: DataFrame, **conditions: Column) -> DataFrame:
    """claim, held: each condition over all rows; null does not hold."""
    row = df.agg(*(F.coalesce(F.bool_and(F.coalesce(c, F.lit(False))), F.lit(False)).alias(n) for n, c in conditions.items()))
    return row.select(F.explode(F.array(*(F.struct(F.lit(n).alias("claim"), F.col(n).alias("held")) for n in conditions))).alias("c")).select("c.*")


def stacked(parts: list[DataFrame]) -> DataFrame:
    return functools.reduce(DataFrame.unionByName, parts)


def event_line(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Event values as positions on a line: few are far from the first event."""
    return tables.values_skewed(spark, sf_dir).select("id", F.col("val").alias("payload"))


def middle(df: DataFrame) -> int:
    """The record in the middle of a line, where records are dense."""
    at = df.agg(F.percentile_approx("payload", 0.5, 1000)).first()[0]
    return df.where(F.col("payload") == at).agg(F.min("id")).first()[0]


VALUE_SETS = {"flat": tables.values_flat, "skewed": tables.values_skewed, "embeddings": lambda spark, sf_dir: proximity.distances(tables.vectors(spark, sf_dir), 0, metrics.euclid)}


# --- maximum and minimum over seeds


def over_seeds(spark: SparkSession, sf_dir: str, want: str, kind: str) -> DataFrame:
    """data, setting, method, runs, mean ratio to the optimum, share of runs within the bound, mean questions; all runs of a setting in one plan."""
    out = []
    for name, load in VALUE_SETS.items():
        df = load(spark, sf_dir)
        n, best = df.count(), df.agg((F.max("val") if want == "max" else F.min("val")).alias("best"))
        many = extremum.runs_of(df, RUNS)
        for x in MUS if kind == "band" else PS:
            judge = (Judge.band(x, "worst", seed=SEED) if kind == "band" else Judge.coin(x, seed=SEED)).on_pairs()
            bound = (1 + x) ** 3
            ours = extremum.robust_band_by(many, "run", judge, n, 1, want=want, seed=SEED) if kind == "band" else extremum.robust_coin_by(many, judge, want=want, seed=SEED)
            runs = {"ours": ours.select("run", "winner_val", "questions"), "knockout": knockouts(many, judge, n, want), "sampler": samplers(many, judge, n, want)}
            for method, found in runs.items():
                out.append(_success(found, best, want, bound).select(F.lit(name).alias("data"), F.lit(x).alias(kind), F.lit(method).alias("method"), "runs", "ratio", "within", "questions"))
    return stacked(out)


def knockouts(many: DataFrame, judge: Judge, n: int, want: str) -> DataFrame:
    """The knockout baseline in every run: heats of sqrt(n), then one of their winners."""
    directed = judge.reversed() if want == "min" else judge

    def level(df: DataFrame, heats: int, seed: int) -> DataFrame:
        placed = df.withColumn("pos", coin(seed, F.lit("heat"), F.col("run"), F.col("id")))
        heat = placed.groupBy("run", F.pmod("pos", F.lit(heats)).alias("heat")).agg(F.array_sort(F.collect_list(F.struct("pos", "id", "val"))).alias("entries"))
        return heat.select("run", extremum.array_bracket(F.col("entries"), directed).alias("w")).select("run", "w.id", "w.val")

    last = level(level(many, max(1, math.isqrt(n)), SEED), 1, SEED + 1)
    return last.select("run", F.col("id").alias("winner_id"), F.col("val").alias("winner_val"), F.lit(n - 1).cast("long").alias("questions"))


def samplers(many: DataFrame, judge: Judge, n: int, want: str) -> DataFrame:
    """The sampling baseline in every run: sqrt(n) records in one heat, all pairs of them."""
    size = math.ceil(math.sqrt(n))
    few = many.where(coin(SEED, F.lit("few"), F.col("run"), F.col("id")) < int(size / n * COIN_RANGE))
    return extremum.round_robin_by(few, "run", judge, want, SEED)


def _success(found: DataFrame, best: DataFrame, want: str, bound: float) -> DataFrame:
    ratio = F.col("best") / F.col("winner_val") if want == "max" else F.col("winner_val") / F.col("best")
    rated = found.crossJoin(F.broadcast(best)).withColumn("r", ratio)
    return rated.agg(F.count("*").alias("runs"), F.round(F.avg("r"), 6).alias("ratio"), F.round(F.avg((F.col("r") <= bound + 1e-9).cast("double")), 4).alias("within"), F.round(F.avg("questions"), 1).alias("questions"))


@query()
def max_band_seeds(spark, sf_dir):
    return over_seeds(spark, sf_dir, "max", "band")


@query()
def min_band_seeds(spark, sf_dir):
    return over_seeds(spark, sf_dir, "min", "band")


@query()
def max_coin_seeds(spark, sf_dir):
    return over_seeds(spark, sf_dir, "max", "coin")


@query()
def min_coin_seeds(spark, sf_dir):
    return over_seeds(spark, sf_dir, "min", "coin")


def _by_method(df: DataFrame, *keys: str) -> DataFrame:
    return df.groupBy(*keys).pivot("method", ["ours", "knockout", "sampler"]).agg(F.first("ratio"))


BAND_CLAIMS = ["exact_without_noise", "sampler_misses_without_noise", "within_bound", "within_factor_four"]


def _band_claims(spark, sf_dir, want):
    df = over_seeds(spark, sf_dir, want, "band").persist()
    wide, ours = _by_method(df, "data", "band"), F.col("method") == "ours"
    return claim(df, exact_without_noise=~(ours & (F.col("band") == 0)) | (F.col("ratio") == 1), within_bound=~ours | (F.col("within") >= 1 - DELTA), within_factor_four=~(ours & (F.col("band") <= 1)) | (F.col("ratio") <= 4)).unionByName(claim(wide.where("band = 0 AND data = 'skewed'"), sampler_misses_without_noise=F.col("sampler") > F.col("ours")))


@query(claims(BAND_CLAIMS))
def max_band_claims(spark, sf_dir):
    """Over RUNS seeds: exact at mu = 0, within (1 + mu)**3 in 90 % of runs, within 4 on average up to mu = 1; the sampler errs even without noise."""
    return _band_claims(spark, sf_dir, "max")


@query(claims(["exact_without_noise", "sampler_misses_without_noise", "within_bound"]))
def min_band_claims(spark, sf_dir):
    return _band_claims(spark, sf_dir, "min").where("claim <> 'within_factor_four'")


def _coin_claims(spark, sf_dir, want):
    df = over_seeds(spark, sf_dir, want, "coin").persist()
    wide = _by_method(df, "data", "coin")
    better = claim(wide.where("data = 'skewed' AND coin >= 0.2"), better_than_knockout=F.col("ours") <= F.col("knockout"), better_than_sampler=F.col("ours") <= F.col("sampler"))
    return better.unionByName(claim(df.where("method = 'ours' AND coin = 0"), exact_without_noise=F.col("ratio") == 1))


COIN_CLAIMS = ["better_than_knockout", "better_than_sampler", "exact_without_noise"]


@query(claims(COIN_CLAIMS))
def max_coin_claims(spark, sf_dir):
    """Over RUNS seeds on the skewed set: never worse than knockout and sampler from p = 0.2 on."""
    return _coin_claims(spark, sf_dir, "max")


@query(claims(COIN_CLAIMS))
def min_coin_claims(spark, sf_dir):
    return _coin_claims(spark, sf_dir, "min")


# --- farthest and nearest


@query(HELD)
def farthest_line_bound(spark, sf_dir):
    """The farthest event on a line where few are far: within (1 + mu)**3 at mu = 0.1."""
    df = event_line(spark, sf_dir)
    first = middle(df)
    gaps = proximity.distances(df, first, metrics.gap)
    return held(measures.against_best(gaps, proximity.farthest_band(df, first, metrics.gap, Judge.band(0.1, seed=SEED))), F.col("ratio") <= 1.1**3)


@query(HELD)
def nearest_line_bound(spark, sf_dir):
    df = event_line(spark, sf_dir)
    first = middle(df)
    gaps = proximity.distances(df, first, metrics.gap).where("val > 0")
    asked = df.join(gaps.select("id"), "id", "left_semi").unionByName(df.where(F.col("id") == first))
    return held(measures.against_best(gaps, proximity.nearest_band(asked, first, metrics.gap, Judge.band(0.1, seed=SEED)), "min"), F.col("ratio") <= 1.1**3)


@query(HELD)
def farthest_anchored_line(spark, sf_dir):
    """Votes of near anchors under coin noise lose at most 6 alpha, where 6 alpha is below a third of the largest distance."""
    df = event_line(spark, sf_dir)
    first = middle(df)
    gaps = proximity.distances(df, first, metrics.gap)
    near = gaps.orderBy("val", "id").limit(48)
    anchors = df.join(near, "id").select("id", "payload", "val").collect()  # 48 rows
    found = measures.against_best(gaps, proximity.farthest_coin_anchored(df, first, anchors, metrics.gap, Judge.coin(0.2, seed=SEED)))
    alpha = max(a["val"] for a in anchors)
    return held(found, (F.col("gap") <= 6 * alpha) & (18 * alpha < F.col("best_val")))


@query(HELD)
def nearest_anchored_line(spark, sf_dir):
    df = event_line(spark, sf_dir)
    first = middle(df)
    gaps = proximity.distances(df, first, metrics.gap)
    anchors = df.join(gaps.orderBy("val", "id").limit(48), "id").select("id", "payload", "val").collect()  # 48 rows
    found = measures.against_best(gaps, proximity.farthest_coin_anchored(df, first, anchors, metrics.gap, Judge.coin(0.2, seed=SEED), want="min"), "min")
    return held(found, F.col("gap") <= 6 * max(a["val"] for a in anchors))


@query("SELECT 'anchored' AS method, TRUE AS pure, TRUE AS held")
def farthest_core_anchors(spark, sf_dir):
    """Anchors taken from a judged core of the query's planted cluster, and the farthest record by their votes."""
    df, metric, judge = tables.planted(spark, sf_dir), metrics.planted(4.0), Judge.coin(0.1, seed=SEED)
    own = df.where(F.col("id") == 0).first()["truth"]
    anchors = proximity.core_anchors(df, 0, metric, judge, df.where(F.col("truth") == own).select("id", "payload"), 24, SEED)
    gaps = proximity.distances(df, 0, metric)
    found = measures.against_best(gaps, proximity.farthest_coin_anchored(df, 0, anchors, metric, judge))
    pure = measures.core_purity(anchors, df.select("id", "truth"), 0)
    return found.crossJoin(pure).select(F.lit("anchored").alias("method"), (F.col("purity") == 1).alias("pure"), (F.col("winner_val") >= 4_000_000).alias("held"))


@query(HELD)
def batch_farthest_band(spark, sf_dir):
    """All records as queries at once: nine in ten answers are within (1 + mu)**3 of the true nearest distances."""
    df = tables.customer_tree(spark, sf_dir)
    best = proximity.batch_exact(df, df, metrics.tree, "min").select("query_id", F.col("winner_val").alias("best"))
    found = proximity.batch_band(df, df, metrics.tree, Judge.band(0.1, seed=SEED), want="min").join(best, "query_id")
    return found.agg((F.avg((F.col("winner_val") <= F.col("best") * 1.1**3).cast("double")) >= 1 - DELTA).alias("held"))


@query("SELECT id, wins FROM (SELECT x.id, count(y.id) AS wins FROM (SELECT s_suppkey AS id, CAST(floor((s_acctbal + 1000) * 1e6) AS BIGINT) AS val FROM supplier) x LEFT JOIN (SELECT s_suppkey AS id, CAST(floor((s_acctbal + 1000) * 1e6) AS BIGINT) AS val FROM supplier) y ON (x.val > y.val OR (x.val = y.val AND x.id > y.id)) GROUP BY x.id) ORDER BY wins DESC LIMIT 10")
def top_ten_exact(spark, sf_dir):
    """The ten records with most duels won."""
    df = tables.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), ticks(F.col("s_acctbal") + 1000).alias("val"))
    return extremum.top_k(df, Judge.exact(), 10, SEED).select("id", "wins")


@query("SELECT 'default' AS setting, 6 AS rounds, TRUE AS held")
def robust_defaults(spark, sf_dir):
    """The default t = 2 ln(2 / delta) and sqrt(n) heats."""
    from .operators import sampling

    df = tables.values_flat(spark, sf_dir)
    found = measures.against_best(df, extremum.robust_band(df, Judge.band(0.3, seed=SEED), seed=SEED))
    return found.select(F.lit("default").alias("setting"), F.lit(sampling.rounds_for("max", df.count(), delta=DELTA)).alias("rounds"), (F.col("ratio") <= 1.3**3).alias("held"))


# --- k-center


def tree_of_labels(spark: SparkSession, sf_dir: str, k: int) -> DataFrame:
    """Embeddings in ten planted categories, of which the first k - 10 have two subcategories each; truth has k values."""
    df = tables.table(spark, sf_dir, "embeddings")
    sub = F.when(F.col("label") < k - 10, F.col("vec_id") % 2).otherwise(0)
    return df.select(F.col("vec_id").alias("id"), F.struct(F.col("embedding").alias("v"), "label", sub.alias("sub")).alias("payload"), (F.col("label") * 2 + sub).alias("truth"))


def tree_metric(a: Column, b: Column) -> Column:
    """Embedding distance with a step of 16 between categories and 4 between subcategories."""
    step = F.when(a["label"] != b["label"], 256.0).when(a["sub"] != b["sub"], 16.0).otherwise(0.0)
    return ticks(F.sqrt(metrics.squared(a["v"], b["v"]) + step))


tree_metric.form = stepped(("label", 256.0), ("sub", 16.0))


def places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five places of two labels each."""
    df = tables.table(spark, sf_dir, "embeddings")
    return df.select(F.col("vec_id").alias("id"), F.struct(F.col("embedding").alias("v"), F.floor(F.col("label") / 2).alias("label")).alias("payload"), F.floor(F.col("label") / 2).alias("truth"))


def fscore_sets(spark: SparkSession, sf_dir: str) -> list[tuple]:
    trees = [(f"images {k}", k, tree_of_labels(spark, sf_dir, k), tree_metric) for k in (10, 15, 20)]
    parts = tables.part_catalogue(spark, sf_dir)
    return [*trees, ("places 5", 5, places(spark, sf_dir), metrics.planted(4.0)), ("regions 5", 5, tables.customer_tree(spark, sf_dir), metrics.tree), ("types", parts.select("truth").distinct().count(), parts, metrics.catalogue)]


def fscores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All sets and methods in one plan: a k-center is a task of its own where its set fits one."""
    from .operators.judges import same_cluster

    def of_set(name, k, df, metric):
        data, truth, judge = df.select("id", "payload"), df.select("id", "truth"), Judge.crowd(0.02, seed=SEED) if name.startswith("types") else Judge.band(0.8, seed=SEED)
        pairs = baselines.same_cluster_pairs(truth, 150, SEED)
        named = pairs.join(truth.withColumnsRenamed({"id": "a", "truth": "ta"}), "a").join(truth.withColumnsRenamed({"id": "b", "truth": "tb"}), "b")
        yes = named.where(same_cluster(F.col("ta"), F.col("tb"), F.col("a"), F.col("b"), 0.5, 0.02, SEED)).select("a", "b")
        # random errors that persist need the votes of cores, as the method asks for coin noise
        m, votes_needed = max(4, data.count() // (4 * k)), judge.kind == "crowd"
        if centers.fits(data, k, metric):
            ours = centers.coin_noise(data, k, m, metric, judge, t=2, seed=SEED) if votes_needed else centers.assigned(data, k, metric, judge, seed=SEED)
            runs = {"ours": ours, **{method: centers.assigned(data, k, metric, judge, way, seed=SEED) for method, way in (("knockout", "knockout"), ("sampler", "sampled"))}}
        else:
            ours = kcenter.coin_noise(data, k, m, metric, judge, t=2, seed=SEED)[0] if votes_needed else kcenter.band(data, k, metric, judge, seed=SEED)[0]
            runs = {"ours": ours, "knockout": baselines.kcenter_knockout(data, k, metric, judge, seed=SEED)[0], "sampler": baselines.kcenter_sampled(data, k, metric, judge, SEED)[0]}
        runs["same cluster"] = baselines.clusters_of_yes(truth, yes)
        out = [found.select(F.lit(name).alias("data"), F.lit(k).alias("k"), F.lit(method).alias("method"), F.col("id").cast("long").alias("id"), F.col("center_id").cast("long").alias("center_id")) for method, found in runs.items()]
        return out, truth.select(F.lit(name).alias("data"), F.col("id").cast("long").alias("id"), F.col("truth").cast("string").alias("truth"))

    sets = fscore_sets(spark, sf_dir)
    with ThreadPoolExecutor(len(sets)) as side_by_side:  # the small jobs of all sets
        parts = list(side_by_side.map(lambda one: of_set(*one), sets))
    out, truths = [found for runs, _ in parts for found in runs], [truth for _, truth in parts]
    found = measures.pair_fscores(cut(stacked(out)), stacked(truths), ["data", "k", "method"], ["data"])
    return found.select("data", "k", "method", "precision", "recall", F.coalesce("fscore", F.lit(0.0)).alias("fscore"))


@query()
def kcenter_fscore_sets(spark, sf_dir):
    """F-score over pairs for every set and k: ours, both baselines, and 150 same-cluster questions."""
    return fscores(spark, sf_dir)


@query(claims(["ours_near_one", "ours_best", "same_cluster_far_below"]))
def kcenter_fscore_claims(spark, sf_dir):
    """Ours reaches 0.9 on every set, and no baseline is above it."""
    wide = fscores(spark, sf_dir).groupBy("data").pivot("method", ["ours", "knockout", "sampler", "same cluster"]).agg(F.first("fscore"))
    return claim(wide, ours_near_one=F.col("ours") >= 0.9, ours_best=F.col("ours") >= F.greatest("knockout", "sampler") - 1e-9, same_cluster_far_below=F.col("same cluster") <= 0.78 * F.col("ours"))


@query("SELECT * FROM (VALUES (0.0, TRUE, TRUE), (0.1, TRUE, TRUE)) AS v(p, precise, complete)")
def kcenter_coin_planted(spark, sf_dir):
    """Coin noise, all ten planted clusters, records thinned and swept: precision and recall over pairs at least 0.95 at p = 0 and 0.1."""
    df = tables.planted(spark, sf_dir)
    n, out = df.count(), []
    for p in (0.0, 0.1):
        found, _ = kcenter.coin_noise(df.select("id", "payload"), 10, n // 20, metrics.planted(4.0), Judge.coin(p, seed=SEED), t=2, seed=SEED)
        out.append(measures.pair_fscore(found, df.select("id", "truth")).select(F.lit(p).cast("decimal(2,1)").alias("p"), (F.col("precision") >= 0.95).alias("precise"), (F.col("recall") >= 0.95).alias("complete")))
    return stacked(out)


def radii(spark: SparkSession, sf_dir: str, ks: tuple[int, ...], judge: Judge) -> DataFrame:
    """k, method, radius under a judge, for ours, the baselines and greedy on true distances."""
    df = tables.customer_tree(spark, sf_dir).select("id", "payload")
    n, out = df.count(), []
    for k in ks:
        ours = kcenter.coin_noise(df, k, max(4, n // (4 * k)), metrics.tree, judge, t=2, seed=SEED)[0] if judge.kind == "coin" else kcenter.band(df, k, metrics.tree, judge, seed=SEED)[0]
        runs = {"ours": ours, "knockout": baselines.kcenter_knockout(df, k, metrics.tree, judge, seed=SEED)[0], "sampler": baselines.kcenter_sampled(df, k, metrics.tree, judge, SEED)[0], "true distances": kcenter.exact_greedy(df, k, metrics.tree, seed=SEED)[0]}
        out += [measures.objective(found).select(F.lit(k).alias("k"), F.lit(method).alias("method"), "radius") for method, found in runs.items()]
    return stacked(out)


@query()
def kcenter_coin_objective(spark, sf_dir):
    """Radius by k under coin noise at p = 0.1."""
    return radii(spark, sf_dir, (5, 10), Judge.coin(0.1, seed=SEED))


@query(claims(["no_worse_than_baselines", "near_true_distances"]))
def kcenter_coin_claims(spark, sf_dir):
    """Under coin noise ours finds the five regions, and no baseline has a smaller radius."""
    wide = radii(spark, sf_dir, (5,), Judge.coin(0.1, seed=SEED)).groupBy("k").pivot("method", ["ours", "knockout", "sampler", "true distances"]).agg(F.first("radius"))
    return claim(wide, no_worse_than_baselines=F.col("ours") <= F.least("knockout", "sampler"), near_true_distances=F.col("ours") <= 1.5 * F.col("true distances"))


@query()
def kcenter_band_objective(spark, sf_dir):
    """Radius by k under band noise."""
    return radii(spark, sf_dir, (2, 5, 10), Judge.band(0.05, seed=SEED))


@query(claims(["near_true_distances", "shrinks_with_k"]))
def kcenter_band_claims(spark, sf_dir):
    """Band noise: the radius stays within (1 + mu)**9 of greedy's (the analysis allows twice that), and falls with k."""
    df = radii(spark, sf_dir, (2, 5, 10), Judge.band(0.05, seed=SEED)).persist()
    wide = df.groupBy("k").pivot("method", ["ours", "true distances"]).agg(F.first("radius"))
    return claim(wide, near_true_distances=F.col("ours") <= 1.05**9 * F.col("true distances")).unionByName(claim(df.where("method = 'ours'").agg(F.min_by("radius", "k").alias("first"), F.max_by("radius", "k").alias("last")), shrinks_with_k=F.col("last") < F.col("first")))


@query(claims(["grades_below_comparisons"]))
def kcenter_grades_claims(spark, sf_dir):
    """Greedy on distance grades, which are off by up to half, is not better than greedy on comparisons."""
    df = tables.customer_tree(spark, sf_dir)
    rich = df.select("id", F.struct("payload.region", "payload.nation", "payload.segment", "payload.bal", "id").alias("payload"), "truth")
    same = lambda a, b: a["region"] == b["region"]
    graded, _ = baselines.graded_greedy(rich.select("id", "payload"), 5, metrics.tree, same, seed=SEED)
    ours, _ = kcenter.band(df.select("id", "payload"), 5, metrics.tree, Judge.band(0.05, seed=SEED), seed=SEED)
    score = lambda found, name: measures.pair_fscore(found, df.select("id", "truth")).select(F.coalesce("fscore", F.lit(0.0)).alias(name))
    return claim(score(graded, "graded").crossJoin(score(ours, "ours")), grades_below_comparisons=F.col("graded") <= F.col("ours"))


# --- hierarchies


def hierarchies(spark: SparkSession, sf_dir: str, mu: float) -> dict[tuple[str, str], DataFrame]:
    """Measured hierarchies of the suppliers on a line: (link, method)."""
    df, judge = tables.table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("id"), ticks(F.col("s_acctbal") + 1000).alias("payload"), (F.col("s_nationkey") % 2).alias("half")), Judge.band(mu, seed=SEED)
    runs = {"ours": linkage.hierarchy, "knockout": baselines.linkage_knockout, "sampler": baselines.linkage_sampled}
    out = {(link, m): run(df, linkage.line, judge, link, block="half", measured=True) for link in ("single", "complete") for m, run in runs.items()}
    return out | {(link, "exact"): baselines.linkage_exact(df, linkage.line, link, block="half") for link in ("single", "complete")}


@query()
def linkage_by_iteration(spark, sf_dir):
    """Mean merged distance by iteration over that of the exact hierarchy (which is 1), both linkages and all methods, mu = 0.5."""
    found = hierarchies(spark, sf_dir, 0.5)
    return stacked([measures.by_iteration(f, found[link, "exact"]).select(F.lit(link).alias("link"), F.lit(m).alias("method"), "block", "step", "ratio") for (link, m), f in found.items() if m != "exact"])


@query(claims(["complete_within_bound", "ours_better_than_sampler", "single_within_bound"]))
def linkage_per_merge_claims(spark, sf_dir):
    """Every merge is within (1 + mu)**3 of the best one then available, and ours merges nearer pairs than the sampler."""
    found = {k: f for k, f in hierarchies(spark, sf_dir, 0.5).items() if k[1] in ("ours", "sampler")}
    rated = stacked([measures.per_merge_ratio(f).select(F.lit(link).alias("link"), F.lit(m).alias("method"), "worst", "mean") for (link, m), f in found.items()]).persist()
    wide = rated.groupBy("link").pivot("method", ["ours", "sampler"]).agg(F.first("mean"))
    bound = lambda link: claim(rated.where(f"method = 'ours' AND link = '{link}'"), **{f"{link}_within_bound": F.col("worst") <= 1.5**3})
    return stacked([bound("complete"), bound("single"), claim(wide, ours_better_than_sampler=F.col("ours") <= F.col("sampler"))])


@query("SELECT CAST(k AS VARCHAR) AS block, row_number() OVER (PARTITION BY k ORDER BY d) AS step, d AS link_dist FROM (SELECT k, lead(v) OVER (PARTITION BY k ORDER BY v) - v AS d FROM (SELECT c_nationkey AS k, CAST(floor((c_acctbal + 1000) * 1e6) AS BIGINT) AS v FROM customer)) WHERE d IS NOT NULL")
def linkage_exact_tree(spark, sf_dir):
    """The distance of every single-linkage merge, step by step, for each nation's customers on a line."""
    df = tables.table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("id"), ticks(F.col("c_acctbal") + 1000).alias("payload"), F.col("c_nationkey").alias("nation"))
    return baselines.linkage_exact(df, linkage.line, block="nation").select("block", F.col("step").cast("long").alias("step"), "link_dist")


@query("SELECT n_regionkey AS truth, count(*) AS n, 1 AS clusters FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def linkage_cut_regions(spark, sf_dir):
    """The hierarchy over the customers' nations under band noise, cut into five clusters, gives the regions."""
    df = tables.customer_tree(spark, sf_dir)
    nation = df.groupBy(F.col("payload.nation").alias("nation")).agg(F.min_by("payload", "id").alias("payload"), F.min("truth").alias("truth"))
    few = nation.select(F.col("nation").cast("long").alias("id"), F.struct("payload.region", "payload.nation").alias("payload"), "truth")  # a row for each nation
    merges = linkage.hierarchy(few, lambda a, b: 8_000_000 if a["region"] != b["region"] else 2_000_000 + abs(a["nation"] - b["nation"]), Judge.band(0.2, seed=SEED))
    found = linkage.cut(merges, few, few.select("truth").distinct().count())
    placed = df.join(found.withColumnRenamed("id", "nation_id"), F.col("payload.nation") == F.col("nation_id"))
    return placed.groupBy("truth").agg(F.count("*").alias("n"), F.countDistinct("center_id").cast("int").alias("clusters"))


@query("SELECT TRUE AS central, TRUE AS held")
def linkage_blocked_claims(spark, sf_dir):
    """Blocks by nation: central records are found by questions, and the tree over them joins nations of one region first."""
    df = tables.customer_tree(spark, sf_dir).withColumn("nation", F.col("payload.nation"))

    merges = linkage.blocked(df, "nation", linkage.tree, Judge.band(0.2, seed=SEED)).persist()
    top = merges.where("block = 'medoids'")
    nations, regions = df.select("nation").distinct().count(), df.select("truth").distinct().count()
    return top.agg((F.sum((F.col("link_dist") < 4_000_000).cast("int")) == nations - regions).alias("central"), (F.count("*") == nations - 1).alias("held"))


@query("SELECT CAST(count(DISTINCT label) - 1 AS BIGINT) AS merges, 4 AS least, TRUE AS held FROM embeddings")
def linkage_groups_claims(spark, sf_dir):
    """Over groups that are all one step apart, every merge joins two groups that were there, and its witness lies across them."""
    df = tables.planted(spark, sf_dir)
    merges = linkage.over_groups(df, "truth", linkage.planted(4.0), Judge.coin(0.2, seed=SEED))
    label = df.select(F.col("id"), "truth")
    ends = merges.join(label.withColumnsRenamed({"id": "rep_u", "truth": "tu"}), "rep_u").join(label.withColumnsRenamed({"id": "rep_v", "truth": "tv"}), "rep_v")
    return ends.agg(F.count("*").alias("merges"), F.floor(F.min("link_dist") / 1_000_000).cast("int").alias("least"), ((F.countDistinct("parent_id") == F.count("*")) & F.bool_and(F.col("tu") != F.col("tv"))).alias("held"))


# --- worked examples


@query(_around_sql("min") + WON.format("g"))
def worked_farthest(spark, sf_dir):
    """The order farthest from every customer's first one at mu = 1, all confusable answers wrong."""
    return _won(around(spark, sf_dir, F.min))


@query(_around_sql("max") + "k AS (SELECT x.id AS k1, y.id AS k3, x.val, y.val AS other FROM g x JOIN g y ON x.o_custkey = y.o_custkey AND x.id <> y.id) SELECT k1 AS x, CAST(sum(CAST((CASE WHEN val = other THEN k1 < k3 ELSE val < other END) <> ((k1 + k3) % 3 = 0) AS INTEGER)) AS BIGINT) AS n FROM k GROUP BY k1")
def worked_core(spark, sf_dir):
    """Core scores around every customer's last order with a third of the answers flipped: stored answers over an exact judge."""
    gaps = around(spark, sf_dir, F.max)
    asked = gaps.select("o_custkey", F.col("id").alias("k1"), "val").join(gaps.select("o_custkey", F.col("id").alias("k3"), F.col("val").alias("other")), "o_custkey").where("k1 <> k3")
    said = Judge.exact().at_most(item(F.col("k1"), F.col("val")), item(F.col("k3"), F.col("other"))) != ((F.col("k1") + F.col("k3")) % 3 == 0)
    return asked.groupBy(F.col("k1").alias("x")).agg(F.sum(said.cast("long")).alias("n"))


@query(f"WITH {REGIONS} SELECT id, min(id) OVER (PARTITION BY region) AS cluster FROM c")
def six_items_clusters(spark, sf_dir):
    """Customers in clusters by region: distance comparisons alone recover them with k = 5."""
    found, _ = kcenter.band(tables.customer_tree(spark, sf_dir).select("id", "payload"), 5, metrics.tree, Judge.band(0.5, seed=SEED), seed=SEED)
    least = found.groupBy("center_id").agg(F.min("id").alias("cluster"))
    return found.join(least, "center_id").select("id", "cluster")


# --- how judges err


@query("SELECT TRUE AS same_median, TRUE AS other_median, TRUE AS same_most, TRUE AS other_most")
def grade_quantiles(spark, sf_dir):
    """Errors of distance grades: half of them under half of the largest error, inside clusters and across."""
    df = tables.customer_tree(spark, sf_dir)
    gaps = proximity.distances(df, 1, metrics.tree).join(df.select("id", F.col("truth")), "id")
    own = df.where("id = 1").select(F.col("truth").alias("own"))
    rated = gaps.crossJoin(F.broadcast(own)).where("val > 1000").withColumn("same", F.col("truth") == F.col("own"))
    off = F.abs(grade(F.col("val"), F.lit(1).cast("long"), F.col("id"), F.col("same")) - F.col("val")) / F.col("val")
    q = rated.groupBy("same").agg(F.percentile(off, 0.5).alias("median"), F.max(off).alias("most"))
    return q.agg(F.max(F.when(F.col("same"), F.col("median").between(0.07, 0.13))).alias("same_median"), F.max(F.when(~F.col("same"), F.col("median").between(0.2, 0.3))).alias("other_median"), F.max(F.when(F.col("same"), F.col("most") <= 0.201)).alias("same_most"), F.max(F.when(~F.col("same"), F.col("most") <= 0.501)).alias("other_most"))


@query("SELECT TRUE AS learned, TRUE AS cheap, TRUE AS persistent")
def learned_judge(spark, sf_dir):
    """A forest that has asked a few hundred questions about blocked pairs answers the others: better than guessing by far, at a cost of dollars."""
    pool = part_questions(spark, sf_dir)
    curve, answers = noisefit.learned_answers(pool, ["common", "sizes", "words"], most=10)
    again = noisefit.learned_answers(pool, ["common", "sizes", "words"], most=10)[1]
    right = answers.agg(F.avg((F.col("yes") == (F.col("answer") == 1)).cast("double")).alias("accuracy"))
    asked = curve.agg(F.max("asked").alias("asked"))
    same = answers.join(again.select("qid", F.col("yes").alias("other")), "qid").agg(F.bool_and(F.col("yes") == F.col("other")).alias("persistent"))
    return right.crossJoin(asked).crossJoin(same).select((F.col("accuracy") >= 0.7).alias("learned"), (F.col("asked") * measures.QUESTION_PRICE <= 45).alias("cheap"), "persistent")


@query()
def active_learning_curve(spark, sf_dir):
    """Questions asked, accuracy and cost, batch by batch."""
    curve = noisefit.active_learn(part_questions(spark, sf_dir), ["common", "sizes", "words"])
    return curve.withColumn("dollars", F.round(F.col("asked") * measures.QUESTION_PRICE, 2))


@query(claims(["knockout_asks_each_once", "linear_in_records", "sampler_asks_fewer"]))
def questions_claims(spark, sf_dir):
    """Questions of the robust maximum grow in proportion to the records; the knockout asks n - 1, the sampler fewer than ours."""
    rows = []
    for load in (tables.values_shifted, tables.values_flat, tables.values_skewed):
        df, judge = load(spark, sf_dir), Judge.band(1.0, seed=SEED)
        n = df.count()
        asked = {"ours": extremum.robust_band(df, judge, t=1, seed=SEED, n=n), "knockout": baselines.knockout(df, judge, seed=SEED), "sampler": baselines.sampled_round_robin(df, judge, seed=SEED)}
        rows.append((n, *(found.first()["questions"] for found in asked.values())))
    table = spark.createDataFrame(rows, "n long, ours long, knockout long, sampler long")
    per = F.col("ours") / F.col("n")
    return claim(table, knockout_asks_each_once=F.col("knockout") == F.col("n") - 1, linear_in_records=(per >= 1) & (per <= 4), sampler_asks_fewer=F.col("sampler") < F.col("ours"))


def part_questions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Questions "is part a nearer to b than to c?" for blocked candidates: qid, features that need no distance, and the answer by the catalogue's distance."""
    df = tables.part_catalogue(spark, sf_dir)
    words = df.select("id", F.concat_ws(" ", F.col("payload.words")).alias("words"))
    asked = blocking.drawn_partners(words, "words", ("x", "y"), 2, SEED).withColumnRenamed("id", "a").where("x.b <> y.b")
    part = lambda c, name: df.select(F.col("id").alias(c), F.col("payload").alias(name))
    full = asked.select("a", F.col("x.b").alias("b"), F.col("y.b").alias("c"), (F.col("x.common") - F.col("y.common")).cast("double").alias("common")).join(part("a", "p"), "a").join(part("b", "q"), "b").join(part("c", "r"), "c")
    size = F.abs(F.col("p.p_size") - F.col("q.p_size")) - F.abs(F.col("p.p_size") - F.col("r.p_size"))
    names = metrics.jaccard(F.col("p.words"), F.col("q.words")) - metrics.jaccard(F.col("p.words"), F.col("r.words"))
    truth = metrics.catalogue(F.col("p"), F.col("q")) <= metrics.catalogue(F.col("p"), F.col("r"))
    return full.select(F.concat_ws("-", "a", "b", "c").alias("qid"), "common", size.cast("double").alias("sizes"), names.alias("words"), truth.cast("int").alias("answer"))
