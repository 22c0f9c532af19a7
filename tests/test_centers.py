import numpy as np
from pyspark.sql import functions as F

from duelspark import experiments
from duelspark.functions import metrics
from duelspark.functions.tosses import coins_of
from duelspark.operators import baselines, centers, kcenter, measures
from duelspark.operators.judges import Judge
from duelspark.sources import tables

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_arrays_of_messages_have_the_coins_of_single_ones():
    from hashlib import md5

    draws = np.random.default_rng(3)
    a, b = draws.integers(0, 10**9, 2000) >> draws.integers(0, 28, 2000), draws.integers(0, 10**18, 2000)
    for wide in (b >> 40, b):
        one = lambda x, y: int(md5(f"7|{x}|{y}|2".encode()).hexdigest()[:8], 16)
        assert coins_of("7|", a, "|", wide, "|2").tolist() == list(map(one, a.tolist(), wide.tolist()))


def test_arrays_of_questions_have_the_answers_of_single_ones():
    draws = np.random.default_rng(4)
    keys, vals = np.sort(draws.integers(0, 30, (2, 500, 2))), draws.integers(0, 100, (2, 500))
    for judge in (Judge.coin(0.2), Judge.fresh_coin(0.3, 2), Judge.crowd(0.1), Judge.crowd(0.1).reversed()):
        judge, sides = judge.on_pairs(), [(k[:, 0], k[:, 1], v) for k, v in zip(keys, vals, strict=True)]
        single = lambda side, i: ((int(side[0][i]), int(side[1][i])), int(side[2][i]))
        assert judge.answers(*sides).tolist() == [judge.answer(single(sides[0], i), single(sides[1], i)) for i in range(500)]


def test_a_task_finds_the_clusters_that_rounds_of_jobs_find(spark):
    df, judge = tables.part_catalogue(spark, SF).select("id", "payload").where("id % 2 = 0"), Judge.crowd(0.1)
    assert centers.fits(df, 3, metrics.catalogue)
    assert rows(centers.assigned(df, 3, metrics.catalogue, judge)) == rows(kcenter.band(df, 3, metrics.catalogue, judge)[0])
    assert rows(centers.assigned(df, 3, metrics.catalogue, judge, "knockout")) == rows(baselines.kcenter_knockout(df, 3, metrics.catalogue, judge)[0])
    assert rows(centers.coin_noise(df, 3, 20, metrics.catalogue, judge, t=1)) == rows(kcenter.coin_noise(df, 3, 20, metrics.catalogue, judge, t=1)[0])


def test_distances_in_arrays_are_those_of_spark(spark):
    for df, metric in ((tables.part_catalogue(spark, SF), metrics.catalogue), (tables.customer_tree(spark, SF), metrics.tree), (tables.planted(spark, SF), metrics.planted(4.0)), (experiments.tree_of_labels(spark, SF, 15), experiments.tree_metric)):
        found = centers.assigned(df.select("id", "payload"), 1, metric, Judge.exact()).select("id", "center_id", "dist").persist()
        center = df.where(F.col("id") == found.first()["center_id"]).select(F.col("payload").alias("q"))
        assert rows(found.select("id", "dist")) == rows(df.crossJoin(center).select("id", metric(F.col("payload"), F.col("q"))))


def test_a_set_with_repeated_ids_or_null_payloads_stays_with_spark(spark):
    df = tables.customer_tree(spark, SF).select("id", "payload")
    assert not centers.fits(df.union(df.limit(1)), 3, metrics.tree)
    assert not centers.fits(df.withColumn("payload", F.when(F.col("id") > 0, F.col("payload"))), 3, metrics.tree)
    assert not centers.fits(df, 3, metrics.euclid)


def test_parts_under_a_crowd_are_clustered_by_votes(spark):
    """Single answers of a crowd misplace some, and the sampler was above ours."""
    df = tables.part_catalogue(spark, "/root/testdata/sf0.01")
    found = centers.coin_noise(df.select("id", "payload"), 6, 83, metrics.catalogue, Judge.crowd(0.02, seed=7), t=2, seed=7)
    assert measures.pair_fscore(found, df).first()["fscore"] == 1


def test_a_share_of_no_pairs_is_null(spark):
    found, truth = spark.createDataFrame([(1, 1), (2, 2)], "id long, center_id long"), spark.createDataFrame([(1, 1), (2, 1)], "id long, truth long")
    row = measures.pair_fscore(found, truth).first()
    assert (row["precision"], row["recall"], row["fscore"]) == (None, 0.0, None)
