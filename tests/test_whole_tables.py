"""Queries that say "all" take all of their table."""

from pyspark.sql import functions as F

from duelspark import experiments, workloads
from duelspark.operators import measures, proximity
from duelspark.sources import tables

SF = "/root/testdata/sf0.001"


def test_every_customer_is_a_query_of_the_batch(spark, monkeypatch):
    asked = []
    for name in ("batch_exact", "batch_band"):
        plain = getattr(proximity, name)
        monkeypatch.setattr(proximity, name, lambda df, queries, *more, plain=plain, **named: asked.append((df.count(), queries.count())) or plain(df, queries, *more, **named))
    assert experiments.batch_farthest_band(spark, SF).first()["held"]
    assert len(asked) == 2 and all(n == m > 0 for n, m in asked)


def test_answers_are_about_all_pairs(spark):
    rows = [(i % 3, i % 5) for i in range(40)]
    every = [(a[0] == b[0], a[1] == b[1]) for k, a in enumerate(rows) for b in rows[k + 1 :]]
    classes = measures.class_pairs(spark.createDataFrame(rows, "truth int, nation int"))
    answered = classes.select((F.col("x.truth") == F.col("y.truth")).alias("truth"), (F.col("x.nation") == F.col("y.nation")).alias("yes"), "n")
    assert answered.agg(F.sum("n")).first()[0] == len(every)
    assert measures.pair_answers_fscore(answered).first() == measures.pair_answers_fscore(spark.createDataFrame(every, "truth boolean, yes boolean")).first()


def test_six_items_scores_every_pair_of_customers(spark, monkeypatch):
    seen, plain = [], measures.pair_answers_fscore
    monkeypatch.setattr(measures, "pair_answers_fscore", lambda pairs: seen.append(pairs.agg(F.sum("n") if "n" in pairs.columns else F.count("*")).first()[0]) or plain(pairs))
    n = tables.customer_tree(spark, SF).count()
    workloads.six_items_fscore(spark, SF)
    assert seen == [n * (n - 1) // 2]
