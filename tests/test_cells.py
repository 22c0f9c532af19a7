import hashlib

import numpy as np
from pyspark.sql import functions as F

from duelspark.functions import metrics
from duelspark.functions.tosses import Field
from duelspark.operators import cells, noisefit, proximity
from duelspark.operators.judges import Judge, grade


def vectors(spark, n):
    return spark.range(n).select((F.col("id") * 7).alias("id"), F.transform(F.sequence(F.lit(1), F.lit(5)), lambda k: ((F.col("id") % 60 * k * k) % 7 / 3).cast("float")).alias("payload"))


def test_coins_for_arrays_are_those_of_md5():
    ids = np.unique(np.random.default_rng(1).integers(0, 300_000, 20_000))
    field = Field(ids)
    for before, after, low, high in (("7|cell|12|", "", 0, None), ("7|", "|99", 11, 17_001), ("", "|x|1", 5, 5), ("7|a", "", 3, 9)):
        want = [int(hashlib.md5(f"{before}{i}{after}".encode()).hexdigest()[:8], 16) for i in ids[low:high]]
        assert field.coins(before, after, low, high).tolist() == want


def test_questions_from_cells_are_the_plain_ones(spark, monkeypatch):
    """Copies, ends of buckets and several cells; no pair of rows is joined."""
    monkeypatch.setattr(cells, "ROWS", 40)
    monkeypatch.setattr(cells, "COLUMNS", 70)
    df, ends = vectors(spark, 150), (10, 1_000_000, 3_000_000)
    for per_cell in (3, 200):
        want = noisefit.sample_questions(noisefit.bucket_pairs(df, metrics.euclid, *ends), per_cell)
        found = noisefit.lowest_pairs(df, metrics.euclid, *ends, per_cell)
        assert "NestedLoop" not in found._jdf.queryExecution().toString()
        assert sorted(map(str, noisefit.sample_questions(found, per_cell).collect())) == sorted(map(str, want.collect()))


def test_grades_from_cells_are_the_plain_ones(spark, monkeypatch):
    """Copies have a distance of nought, by which nothing is divided."""
    monkeypatch.setattr(cells, "ROWS", 40)
    monkeypatch.setattr(cells, "COLUMNS", 70)
    df = vectors(spark, 150).select("id", F.struct(F.col("payload").alias("v"), (F.col("id") % 3).alias("label")).alias("payload"))
    a, b = df.select(F.col("id").alias("a"), F.col("payload").alias("p")), df.select(F.col("id").alias("b"), F.col("payload").alias("q"))
    pairs = a.join(b, F.col("a") < F.col("b")).select("a", "b", (F.col("p.label") == F.col("q.label")).alias("same"), metrics.planted(4.0)(F.col("p"), F.col("q")).alias("dist")).where("dist > 0")
    off = F.abs(grade(F.col("dist"), F.col("a"), F.col("b"), F.col("same")) - F.col("dist")) / F.col("dist")
    want = pairs.agg(F.max(F.when(F.col("same"), off)), F.max(F.when(~F.col("same"), off))).first()
    assert tuple(noisefit.most_off(df, 4.0).first()) == tuple(want)
    monkeypatch.setattr(cells, "plain", lambda df: False)
    assert tuple(noisefit.most_off(df, 4.0).first()) == tuple(want)


def test_anchor_counts_from_cells_are_the_plain_ones(spark, monkeypatch):
    """Anchors and near records with smaller and larger ids than the far ones, short arrays and long ones."""
    df = vectors(spark, 500).select("id", F.struct(F.col("payload").alias("v"), (F.col("id") % 3).alias("label")).alias("payload"))
    near, far = df.where("id % 11 = 3"), df.where("id % 11 > 4")
    anchors = df.where("id % 11 = 0").orderBy("id").limit(3).collect() + near.orderBy(F.desc("id")).limit(2).collect()
    found = {}
    for few, whole in ((400, True), (1, True), (400, False)):
        monkeypatch.setattr("duelspark.functions.tosses.FEW", few)
        if not whole:
            monkeypatch.setattr(cells, "plain", lambda df: False)
        found[few, whole] = sorted(tuple(r) for r in proximity.anchor_counts(near, far, anchors, 4.0, Judge.coin(0.3)).where("pairs > 0").collect())
    assert found[400, True] == found[1, True] == found[400, False]
