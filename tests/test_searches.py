from pyspark.sql import functions as F

from duelspark.functions import metrics
from duelspark.operators import extremum, proximity
from duelspark.operators.judges import Judge
from duelspark.sources import tables

SF = "/root/testdata/sf0.001"


def rows(df):
    return sorted(map(tuple, df.select(*sorted(df.columns)).collect()))


def test_coin_search_over_measured_distances_ends_and_is_that_of_plain_questions(spark, monkeypatch):
    """Asked straight from a plan of distances, this search could end in an error of the optimizer (key not found)."""
    asked, judge = proximity._asked(tables.customer_tree(spark, SF), 1, metrics.tree), Judge.coin(0.2).on_pairs()
    found = rows(extremum.robust_coin(asked, judge))
    plain = spark.createDataFrame(asked.collect(), asked.schema)
    monkeypatch.setattr(extremum, "_numbered", lambda df: False)
    assert found == rows(extremum.robust_coin(plain, judge))


def test_searches_in_arrays_find_what_joins_find(spark, monkeypatch):
    """Votes of anchors, and batches of queries: forms of metrics against Spark's own measuring."""
    line = tables.values_skewed(spark, SF).select("id", F.col("val").alias("payload")).where("id < 200")
    anchors, customers, judge = line.where("id < 5 AND id > 0").select("id", "payload").collect(), tables.customer_tree(spark, SF), Judge.band(0.1)
    few = customers.where("id % 40 = 0")
    searches = [
        lambda: proximity.farthest_coin_anchored(line, 0, anchors, metrics.gap, Judge.coin(0.2)),
        lambda: proximity.batch_band(customers, few, metrics.tree, judge, want="min").select("query_id", "winner_id", "winner_val", "pool_size", "questions"),
        lambda: proximity.batch_exact(customers, few, metrics.tree, "min"),
    ]
    found = [rows(search()) for search in searches]
    assert proximity.centers.fits(line, 1, metrics.gap) and proximity.centers.fits(few, 1, metrics.tree)
    monkeypatch.setattr(proximity.centers, "fits", lambda *a: False)
    assert found == [rows(search()) for search in searches]
