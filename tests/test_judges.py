import random

import pytest
from pyspark.sql import functions as F

from duelspark.operators.judges import Judge, from_table, item, pair_id
from duelspark.operators.votes import vote_share

KINDS = [Judge.exact(), Judge.band(0.5), Judge.band(1.0, "coinflip"), Judge.band(1.0, "truthful"), Judge.band(1.0, "protect", ids=(3,)), Judge.band(1.0, "favour", ids=(4,)), Judge.additive_band(50), Judge.additive_band(50, "coinflip"), Judge.coin(0.3), Judge.fresh_coin(0.3, 2), Judge.crowd(0.3)]


@pytest.mark.parametrize("judge", KINDS, ids=lambda j: f"{j.kind}-{j.policy}")
def test_column_and_python_answers_agree(spark, judge):
    rng = random.Random(1)
    rows = [(rng.randrange(9), rng.randrange(1, 200), rng.randrange(9), rng.randrange(1, 200)) for _ in range(300)]
    values = {}
    rows = [(a, values.setdefault(a, x), b, values.setdefault(b, y)) for a, x, b, y in rows]
    df = spark.createDataFrame(rows, "a long, x long, b long, y long")
    left, right = item(F.col("a"), F.col("x")), item(F.col("b"), F.col("y"))
    got = df.select("*", judge.at_most(left, right).alias("yes"), judge.at_most(right, left).alias("back")).collect()
    for r in got:
        assert r["yes"] == judge.answer((r["a"], r["x"]), (r["b"], r["y"]))
        assert r["a"] == r["b"] or r["yes"] != r["back"]


@pytest.mark.parametrize("judge", [Judge.coin(0.3), Judge.band(0.5, "coinflip"), Judge.crowd(0.2)], ids=lambda j: j.kind)
def test_pairs_agree_too(spark, judge):
    rng = random.Random(2)
    rows = [tuple(rng.randrange(6) for _ in range(4)) for _ in range(200)]
    dist = lambda p, q: 10 + abs(p - q) * 7 + (p * q) % 3
    df = spark.createDataFrame([(*r, dist(r[0], r[1]), dist(r[2], r[3])) for r in rows], "a long, b long, c long, d long, x long, y long")
    said = judge.on_pairs().at_most(item(pair_id(F.col("a"), F.col("b")), F.col("x")), item(pair_id(F.col("c"), F.col("d")), F.col("y")))
    for r in df.withColumn("yes", said).collect():
        assert r["yes"] == judge.on_pairs().answer((tuple(sorted((r["a"], r["b"]))), r["x"]), (tuple(sorted((r["c"], r["d"]))), r["y"]))


def test_stored_answers_come_first(spark):
    questions = spark.createDataFrame([(1, 2, 3, 4), (1, 2, 5, 6)], "k1 long, k2 long, k3 long, k4 long")
    stored = spark.createDataFrame([(1, 2, 3, 4, False)], "k1 long, k2 long, k3 long, k4 long, yes boolean")
    got = {r["k3"]: r["yes"] for r in from_table(questions, stored, F.lit(True)).collect()}
    assert got == {3: False, 5: True}


def test_vote_shares():
    assert vote_share("fixed") == 0.3 and vote_share("half_correct", 0.4) == 0.3 and vote_share("majority") == 0.5


def test_bad_settings():
    with pytest.raises(ValueError):
        Judge.coin(0.5)
    with pytest.raises(ValueError):
        Judge.band(-1)
