from pyspark.sql import functions as F

from duelspark.functions import metrics
from duelspark.operators import proximity


def test_batches_by_cells_are_the_plain_ones(spark, monkeypatch):
    """Copies, equal distances and several cells; no pair of rows is joined."""
    monkeypatch.setattr(proximity, "CELL", 40)
    df = spark.range(150).select("id", F.transform(F.sequence(F.lit(1), F.lit(5)), lambda k: ((F.col("id") % 60 * k * k) % 7 / 3).cast("float")).alias("payload"))
    plain = lambda a, b: metrics.euclid(a, b)  # noqa: E731  not euclid itself, so every pair is measured by it
    for queries in (df, df.where("id % 10 = 0")):
        for want in ("max", "min"):
            fast = proximity.batch_exact(df, queries, metrics.euclid, want)
            assert sorted(fast.collect()) == sorted(proximity.batch_exact(df, queries, plain, want).collect())
            assert "NestedLoop" not in fast._jdf.queryExecution().toString()
    odd = df.unionByName(spark.createDataFrame([(900, None), (901, [1.0, None, 0.0, 0.0, 0.0])], "id long, payload array<float>"))
    assert sorted(proximity.batch_exact(odd, df, metrics.euclid).collect()) == sorted(proximity.batch_exact(odd, df, plain).collect())
