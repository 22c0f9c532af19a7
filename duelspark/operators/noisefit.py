"""How a judge errs: accuracy by buckets of distance, the noise model that fits, and a learned judge."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.metrics import Metric, euclid
from ..functions.ticks import COIN_RANGE, coin
from ..functions.tosses import Field
from . import cells
from .judges import Judge, grade, item, pair_id
from .scores import opponents


def bucket_pairs(df: DataFrame, metric: Metric, n_buckets: int, low: int, high: int) -> DataFrame:
    """a, b, dist, bucket: all pairs of a small metric set, by equal ranges of distance."""
    other = df.select(F.col("id").alias("b"), F.col("payload").alias("q"))
    pairs = opponents(df, other, F.col("id") < F.col("b")).select(F.col("id").alias("a"), "b", metric(F.col("payload"), F.col("q")).alias("dist"))
    return pairs.withColumn("bucket", F.least(F.greatest(F.width_bucket(F.col("dist").cast("double"), F.lit(float(low)), F.lit(float(high)), F.lit(n_buckets)), F.lit(1)), F.lit(n_buckets)).cast("int"))


def lowest_pairs(df: DataFrame, metric: Metric, n_buckets: int, low: int, high: int, per_cell: int, seed: int = 7) -> DataFrame:
    """Of bucket_pairs those that sample_questions may draw: in every cell of a grid, each bucket's pairs with the lowest coins.

    All pairs are measured and tossed for; only vectors under euclid are worked on as arrays.
    """
    if not (metric is euclid and cells.plain(df)):
        return bucket_pairs(df, metric, n_buckets, low, high)
    most = per_cell + 1

    def work(x: cells.Vectors, y: cells.Vectors) -> pd.DataFrame:
        names, limit, kept, waiting = Field(y.ids), np.full(n_buckets + 1, COIN_RANGE, np.int64), pd.DataFrame(), []

        def settled() -> pd.DataFrame:
            out = pd.concat([kept, *(pd.DataFrame(dict(zip(("a", "b", "dist", "bucket", "coin"), w, strict=True))) for w in waiting)])
            waiting.clear()
            out = out.sort_values(["bucket", "coin", "a", "b"])
            out = out[out.groupby("bucket").cumcount() < most]
            full = out.groupby("bucket")["coin"].agg(["size", "max"])
            full = full[full["size"] == most]
            limit[full.index.to_numpy()] = full["max"].to_numpy()
            return out

        for k, (id_, point) in enumerate(zip(x.ids.tolist(), x.axes.T, strict=True)):
            first = int(np.searchsorted(y.ids, id_, "right"))
            if first < len(y.ids):
                tossed = names.coins(f"{seed}|cell|{id_}|", low=first)
                dist = y.ticks(point, low=first)
                bucket = np.clip(np.floor(n_buckets * (dist - float(low)) / (float(high) - float(low))) + 1, 1, n_buckets).astype(np.int32)
                at = np.flatnonzero(tossed <= limit[bucket])
                waiting.append((id_, y.ids[first:][at], dist[at], bucket[at], tossed[at].astype(np.int64)))
            if waiting and (k < 4 or k % 32 == 0):
                kept = settled()
        return (settled() if waiting else kept).reindex(columns=["a", "b", "dist", "bucket"]).astype("int64")

    vectors = df.select(F.col("id").cast("long").alias("id"), "payload")
    return cells.over(vectors, vectors, work, "a long, b long, dist long, bucket int")


def most_off(df: DataFrame, weight: float, seed: int = 7) -> DataFrame:
    """s, o: how far grades of the planted distances (payload v, label; labels apart by `weight`) are off at most, inside clusters and across, over all pairs.

    A distance of nought has the grade nought, which is not off.
    """
    flat = df.select(F.col("id").cast("long").alias("id"), F.col("payload.v").alias("payload"), F.col("payload.label").alias("label"))
    if not cells.plain(flat):
        from ..functions.metrics import planted

        other = df.select(F.col("id").alias("b"), F.col("payload").alias("q"))
        pairs = opponents(df, other, F.col("id") < F.col("b")).select("id", "b", (F.col("payload.label") == F.col("q.label")).alias("same"), planted(weight)(F.col("payload"), F.col("q")).alias("dist"))
        off = F.when(F.col("dist") == 0, 0.0).otherwise(F.abs(grade(F.col("dist"), F.col("id"), F.col("b"), F.col("same"), seed=seed) - F.col("dist")) / F.when(F.col("dist") != 0, F.col("dist")))
        return pairs.select("same", off.alias("off")).agg(F.max(F.when(F.col("same"), F.col("off"))).alias("s"), F.max(F.when(~F.col("same"), F.col("off"))).alias("o"))

    def work(x: cells.Vectors, y: cells.Vectors) -> pd.DataFrame:
        names, most = Field(y.ids), [-1.0, -1.0]
        for id_, label, point in zip(x.ids.tolist(), x.labels, x.axes.T, strict=True):
            first = int(np.searchsorted(y.ids, id_, "right"))
            if first == len(y.ids):
                continue
            share = names.coins(f"{seed}|{id_}|", low=first) / float(COIN_RANGE) * 2 - 1
            same = y.labels[first:] == label
            dist = y.ticks(point, np.where(same, 0.0, weight * weight), first)
            off = np.abs(np.floor(dist * (1 + share * np.where(same, 0.2, 0.5))) - dist) / np.maximum(dist, 1)
            for k, of in enumerate((same, ~same)):
                most[k] = max(most[k], off.max(where=of, initial=-1.0))
        return pd.DataFrame({"s": [most[0]], "o": [most[1]]})

    found = cells.over(flat, flat, work, "s double, o double")
    return found.agg(*(F.max(F.when(F.col(c) >= 0, F.col(c))).alias(c) for c in ("s", "o")))


def sample_questions(bucketed: DataFrame, per_cell: int, seed: int = 7) -> DataFrame:
    """Questions for every two buckets: per_cell times a drawn pair of one is set against a drawn pair of the other."""
    order = W.partitionBy("bucket").orderBy(coin(seed, F.lit("cell"), F.col("a"), F.col("b")), "a", "b")
    ranked = bucketed.withColumn("slot", F.row_number().over(order)).where(F.col("slot") <= per_cell + 1)
    side = lambda s: ranked.select("slot", *(F.col(c).alias(f"{c}{s}") for c in ("a", "b", "dist", "bucket")))
    one, two = side("1"), side("2").withColumn("slot", F.col("slot") - 1)
    return one.where(F.col("slot") <= per_cell).join(two, "slot").where("bucket1 <= bucket2")


def ask(questions: DataFrame, judge: Judge) -> DataFrame:
    """questions with truth, yes and correct."""
    left, right = (item(pair_id(F.col(f"a{s}"), F.col(f"b{s}")), F.col(f"dist{s}")) for s in "12")
    return questions.withColumn("truth", Judge.exact(pairs=True).at_most(left, right)).withColumn("yes", judge.on_pairs().at_most(left, right)).withColumn("correct", F.col("truth") == F.col("yes"))


def accuracy_grid(answers: DataFrame) -> DataFrame:
    return answers.groupBy("bucket1", "bucket2").agg(F.count("*").alias("asked"), F.round(F.avg(F.col("correct").cast("double")), 6).alias("accuracy"))


def accuracy_cube(answers: DataFrame) -> DataFrame:
    """The grid with its margins; -1 stands for all buckets."""
    cube = answers.cube("bucket1", "bucket2").agg(F.count("*").alias("asked"), F.round(F.avg(F.col("correct").cast("double")), 6).alias("accuracy"))
    return cube.select(F.coalesce("bucket1", F.lit(-1)).alias("bucket1"), F.coalesce("bucket2", F.lit(-1)).alias("bucket2"), "asked", "accuracy")


def ratio_milli(x: Column, y: Column) -> Column:
    """The larger over the smaller, in thousandths, rounded down."""
    return F.floor(F.greatest(x, y).cast("decimal(38,0)") * 1000 / F.greatest(F.least(x, y), F.lit(1))).cast("long")


def estimate_mu(answers: DataFrame, tolerance: float = 0.0, bin_milli: int = 10) -> DataFrame:
    """mu_milli: the smallest ratio (less one) from which all bins are right up to the tolerance."""
    binned = answers.groupBy((F.floor(ratio_milli(F.col("dist1"), F.col("dist2")) / bin_milli) * bin_milli).cast("long").alias("ratio")).agg(F.avg(F.col("correct").cast("double")).alias("accuracy"))
    bad = binned.where(F.col("accuracy") < 1 - tolerance)
    return bad.agg(F.coalesce(F.max("ratio") + bin_milli - 1000, F.lit(0)).alias("mu_milli"))


def estimate_p(answers: DataFrame) -> DataFrame:
    """p: the share of wrong answers between different buckets."""
    return answers.where("bucket1 <> bucket2").agg(F.round(1 - F.avg(F.col("correct").cast("double")), 6).alias("p"))


def choose_model(answers: DataFrame, tolerance: float = 0.02) -> DataFrame:
    """band if answers across the widest bucket gaps are right, else coin."""
    gap = F.col("bucket2") - F.col("bucket1")
    widest = answers.agg(F.max(gap).alias("g"))
    far = answers.crossJoin(F.broadcast(widest)).where(gap * 2 >= F.col("g"))
    wrong = F.avg((~F.col("correct")).cast("double"))
    return far.agg(F.when(wrong > tolerance, "coin").otherwise("band").alias("model"))


def active_learn(pool: DataFrame, features: list[str], batch: int = 20, min_gain: float = 0.01, most: int = 12, seed: int = 7) -> DataFrame:
    """batch, asked, accuracy, gain of a random forest that asks for the answers it is least sure of.

    pool: qid, the features, and `answer` (0 or 1), which is read only for the questions asked and for a validation fifth.
    """
    return learned_answers(pool, features, batch, min_gain, most, seed)[0]


def learned_answers(pool: DataFrame, features: list[str], batch: int = 20, min_gain: float = 0.01, most: int = 12, seed: int = 7) -> tuple[DataFrame, DataFrame]:
    """The curve of active_learn, and the pool with `yes`: the answer itself where it was asked, the forest's elsewhere.

    The second is a source of answers for the other methods (judges.from_table). Learning stops when a batch after the third
    gains at most min_gain.
    """
    from pyspark.ml.classification import RandomForestClassifier
    from pyspark.ml.feature import VectorAssembler
    from pyspark.ml.functions import vector_to_array

    from ..plans.lineage import cut

    table = VectorAssembler(inputCols=features, outputCol="x").transform(cut(pool)).withColumn("label", F.col("answer").cast("double"))
    fifth = F.pmod(coin(seed, F.lit("held"), F.col("qid")), F.lit(5))
    held, free = table.where(fifth == 0), table.where(fifth != 0)
    drawn = coin(seed, F.lit("batch"), F.col("qid"))
    chosen = [r["qid"] for r in free.orderBy(drawn, "qid").limit(batch).select("qid").collect()]  # a batch
    curve, before, model = [], None, None
    for turn in range(most):
        known = free.where(F.col("qid").isin(chosen))
        accuracy = 0.5
        if known.select("label").distinct().count() > 1:
            model = RandomForestClassifier(featuresCol="x", numTrees=20, maxDepth=5, seed=seed).fit(known)
            accuracy = model.transform(held).agg(F.avg((F.col("prediction") == F.col("label")).cast("double"))).first()[0] or 0.0
        gain = None if before is None else accuracy - before
        curve.append((turn + 1, len(chosen), round(accuracy, 6), None if gain is None else round(gain, 6)))
        if gain is not None and gain <= min_gain and turn >= 3:
            break
        before = accuracy
        rest = free.where(~F.col("qid").isin(chosen))
        doubt = F.abs(vector_to_array("probability")[0] - 0.5) if model else F.lit(0.0)
        chosen += [r["qid"] for r in (model.transform(rest) if model else rest).orderBy(doubt, drawn, "qid").limit(batch).select("qid").collect()]  # a batch
    said = F.col("prediction") == 1 if model else F.lit(True)
    answered = model.transform(table) if model else table
    yes = F.when(F.col("qid").isin(chosen[: curve[-1][1]]), F.col("answer") == 1).otherwise(said)
    return pool.sparkSession.createDataFrame(curve, "batch int, asked int, accuracy double, gain double"), answered.select(*pool.columns, yes.alias("yes"))


def per_cell(n: int) -> int:
    """Questions for each two buckets: ln n."""
    return max(1, math.ceil(math.log(max(2, n))))
