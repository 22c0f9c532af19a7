import time

import duckdb
import pytest
from pyspark.sql import functions as F

from duelspark.operators import noisefit, sqlapi
from duelspark.operators.judges import Judge
from duelspark.sources import exchange
from duelspark.streaming import windows

SF = "/root/testdata/sf0.001"
NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def same(a, b):
    order = sorted(a.columns)
    rows = lambda df: sorted(tuple("null" if v is None or v != v else f"{v:.6g}" if isinstance(v, float) else str(v) for v in r) for r in df[order].astype(object).itertuples(index=False))
    return order == sorted(b.columns) and rows(a) == rows(b)


@pytest.mark.parametrize("name", ["tick_parity", "coin_parity", "judge_band_grid", "crowd_majority_answers", "win_scores_coin", "exact_max_flat", "confusion_share", "worked_scores", "ops_asof", "ops_cube", "ops_range_join", "ops_window", "ops_subqueries", "ops_frames", "ops_grouping_sets", "ops_custom_metric", "sql_linkage", "stream_dedup_late", "stream_join", "accuracy_grid", "accuracy_cube", "sampled_max", "token_block_pairs", "worked_core", "worked_farthest", "six_items_clusters", "linkage_exact_tree"])
def test_queries_equal_their_sql(spark, name):
    import __spark_entry__ as entry

    db = duckdb.connect()
    for t in NAMES:
        db.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    assert same(entry.queries()[name](spark, SF).toPandas(), db.sql(entry.oracle_sql()[name]).df())


@pytest.mark.parametrize("name", ["running_champion_chain", "worked_scores", "worked_kcenter", "worked_farthest", "worked_core"])
def test_examples_read_the_orders(spark, name):
    import __spark_entry__ as entry

    db, got = duckdb.connect(), entry.queries()[name](spark, SF)
    db.sql(f"CREATE VIEW orders AS SELECT * FROM '{SF}/orders.parquet'")
    assert any(f.endswith("/orders.parquet") for f in got.inputFiles())
    assert same(got.toPandas(), db.sql(entry.oracle_sql()[name]).df())


@pytest.mark.parametrize("name", ["six_items_clusters", "six_items_fscore"])
def test_examples_read_the_customers(spark, name):
    import __spark_entry__ as entry

    assert "FROM customer" in entry.oracle_sql()[name]
    assert any(f.endswith("/customer.parquet") for f in entry.queries()[name](spark, SF).inputFiles())


def test_answer_log(spark, tmp_path):
    rows = [(1, 2, 3, 4, True, "crowd", 7), (1, 2, 5, 6, False, "crowd", 7)]
    log = spark.createDataFrame(rows, exchange.ANSWER)
    exchange.log_answers(log, str(tmp_path / "log"))
    again = spark.read.parquet(str(tmp_path / "log"))
    asked = spark.createDataFrame([(1, 2, 3, 4), (1, 2, 7, 8), (1, 2, 7, 8)], exchange.QUESTION)
    assert [r["k3"] for r in exchange.unanswered(asked, again).collect()] == [7]
    for kind in ("json", "csv", "orc", "parquet"):
        exchange.write_questions(asked, str(tmp_path / kind), kind)
        assert len(list((tmp_path / kind).iterdir())) > 1
    votes = spark.createDataFrame([(1, 2, 3, 4, y) for y in (True, True, False)], f"{exchange.QUESTION}, yes boolean")
    assert exchange.majority(votes).first()["yes"]


def test_late_events_and_duplicates(spark, tmp_path):
    import datetime as dt

    at = lambda m: dt.datetime(2024, 1, 1) + dt.timedelta(minutes=m)
    first = [(1, at(0), 1, "a", 5.0, "{}"), (1, at(0), 1, "a", 5.0, "{}"), (2, at(600), 1, "a", 7.0, "{}")]
    late = [(3, at(1), 1, "a", 99.0, "{}"), (4, at(700), 1, "a", 1.0, "{}")]
    middle = [(5, at(650), 1, "a", 2.0, "{}")]  # with two stateful steps the watermark holds from the batch after the next
    for i, rows in enumerate((first, middle, late)):
        spark.createDataFrame(rows, windows.EVENTS).coalesce(1).write.parquet(str(tmp_path / f"in{i}"))
        time.sleep(1.1)  # files are read in the order of their times
    stream = spark.readStream.schema(windows.EVENTS).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path))
    got = windows.run_to_end(windows.window_maxima(windows.deduplicated(stream, "10 minutes"), "1 hour"), "late_maxima", "append")
    rows = {r["start"].hour: (r["best"], r["n"]) for r in got.collect()}
    assert rows[0] == (5_000_000, 1)


def test_sql_functions(spark):
    sqlapi.register(spark)
    spark.createDataFrame([(i, (i * 7919) % 1009 + 1) for i in range(200)], "id long, val long").createOrReplaceTempView("t_values")
    got = spark.sql("SELECT * FROM robust_max(TABLE(t_values), CAST(0.0 AS DOUBLE))").first()
    assert got["winner_val"] == max((i * 7919) % 1009 + 1 for i in range(200))


def test_equal_values_without_noise_go_by_id(spark):
    rows = [(g, 100 * g + i, 5 if i < 4 else 3) for g in range(3) for i in range(6)]
    got = sqlapi.group_maxima(spark.createDataFrame(rows, "g long, id long, val long"), "g", 0.0)
    assert {r["g"]: r["winner_id"] for r in got.collect()} == {g: 100 * g + 3 for g in range(3)}
    spark.sql("SELECT id, val FROM __judged").createOrReplaceTempView("t_tied")
    assert spark.sql("SELECT * FROM robust_max(TABLE(t_tied), CAST(0.0 AS DOUBLE))").first()["winner_id"] == 203


def test_noise_is_recovered(spark):
    df = spark.createDataFrame([(i, (i * i * 37) % 997) for i in range(60)], "id long, payload long")
    from duelspark.functions import metrics

    pairs = noisefit.bucket_pairs(df, metrics.gap, 8, 0, 1000)
    asked = noisefit.sample_questions(pairs, 60)
    assert noisefit.choose_model(noisefit.ask(asked, Judge.coin(0.25))).first()["model"] == "coin"
    assert noisefit.choose_model(noisefit.ask(asked, Judge.band(0.2))).first()["model"] == "band"
    p = noisefit.estimate_p(noisefit.ask(asked, Judge.coin(0.25))).first()["p"]
    assert abs(p - 0.25) < 0.08
    assert noisefit.accuracy_grid(noisefit.ask(asked, Judge.exact())).agg(F.min("accuracy")).first()[0] == 1.0
