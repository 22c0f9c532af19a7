import itertools
import math

import pytest
from pyspark.sql import functions as F

from duelspark.operators import baselines, extremum, measures, scores
from duelspark.operators.judges import Judge
from duelspark.plans import ledger


def make(spark, values):
    return spark.createDataFrame([(i, v) for i, v in enumerate(values)], "id long, val long")


def test_worked_example(spark):
    df = make(spark, [51, 101, 102, 202])
    assert {r["id"]: r["wins"] for r in scores.win_scores(df, df, Judge.band(1.0)).collect()} == {0: 2, 1: 2, 2: 1, 3: 1}


def test_grid_scores_equal_broadcast_scores(spark):
    df = make(spark, [(i * 7919) % 1009 + 1 for i in range(120)])
    one, two = scores.round_robin(df, Judge.coin(0.2)), scores.round_robin(df, Judge.coin(0.2), grid=5)
    assert sorted(map(tuple, one.collect())) == sorted(map(tuple, two.collect()))


@pytest.mark.parametrize("values", [[], [5], [5, 7], [3, 3, 3]])
def test_edges(spark, values):
    df = make(spark, values)
    got = extremum.robust_band(df, Judge.exact(), t=1).collect()
    assert [r["winner_val"] for r in got] == ([max(values)] if values else [])
    assert len(baselines.truth(df).collect()) == bool(values)


@pytest.mark.parametrize("want", ["max", "min"])
def test_exact_judge_finds_the_optimum(spark, want):
    df = make(spark, [(i * 7919) % 10_007 + 1 for i in range(700)])
    best = (max if want == "max" else min)((i * 7919) % 10_007 + 1 for i in range(700))
    judge = Judge.exact()
    assert extremum.robust_band(df, judge, want=want, t=1).first()["winner_val"] == best
    assert extremum.robust_coin(df, judge, want=want).first()["winner_val"] == best
    assert baselines.knockout(df, judge, want).first()["winner_val"] == best
    for fanout in (2, 3, 8):
        assert extremum.bracket(df, judge, fanout, want=want).first()["winner_val"] == best


def test_round_robin_bound_holds_for_every_adversary():
    """All answers inside the band, on five items: the winner is never below max / (1 + mu)**2."""
    values, mu = [100, 150, 199, 260, 390], 1.0
    pairs = list(itertools.combinations(range(5), 2))
    free = [(a, b) for a, b in pairs if values[b] <= (1 + mu) * values[a]]
    for lies in itertools.product((False, True), repeat=len(free)):
        said, wins = dict(zip(free, lies, strict=True)), [0] * 5
        for a, b in pairs:
            wins[a if said.get((a, b), False) else b] += 1
        assert min(values[i] for i in range(5) if wins[i] == max(wins)) * (1 + mu) ** 2 >= max(values)


def test_band_bound_over_seeds(spark):
    df = make(spark, [1000 + (i * 7919) % 9001 for i in range(300)]).persist()
    found = [measures.against_best(df, extremum.robust_band(df, Judge.band(0.5, "coinflip", seed=s), seed=s)).first()["ratio"] for s in range(6)]
    assert max(found) <= 1.5**3


def test_coin_rank(spark):
    df = make(spark, [1000 + (i * 7919) % 9001 for i in range(2000)]).persist()
    rank = measures.rank_of(df, extremum.robust_coin(df, Judge.coin(0.2), seed=3)).first()["rank"]
    assert rank <= 4 * math.log(2000 / 0.1) ** 2


def test_ledger_counts_questions(spark):
    df = make(spark, [1000 + i for i in range(400)])
    got = extremum.robust_band(df, Judge.band(1.0), t=2, seed=5).first()
    assert got["questions"] == ledger.robust_band(400, got["pool_size"], 2)
    book = ledger.Ledger()
    with book.timed("m", "p") as seen:
        seen["asked"] = 3
    assert book.frame(spark).first()["asked"] == 3


def test_cells_equal_a_broadcast(spark, monkeypatch):
    from duelspark.operators import scores

    df = spark.createDataFrame([(i, i * 37 % 101 + 1) for i in range(90)], "id long, val long")
    judge = Judge.coin(0.3)
    want = {tuple(r) for r in scores.win_scores(df, df, judge).collect()}
    robin = {tuple(r) for r in scores.round_robin(df, judge).collect()}
    monkeypatch.setattr(scores, "BROADCAST_ROWS", 20)
    assert {tuple(r) for r in scores.win_scores(df, df, judge).collect()} == want
    assert {(i, w) for i, _, w in robin} == want
    assert extremum.top_k(df, Judge.exact(), 3).agg({"val": "min"}).first()[0] == sorted((i * 37 % 101 + 1 for i in range(90)), reverse=True)[2]


def test_leaves_are_a_permutation(spark, monkeypatch):
    monkeypatch.setattr(extremum, "LEAVES", 10)
    df = spark.createDataFrame([(i, i) for i in range(95)], "id long, val long")
    pos = sorted(r["pos"] for r in extremum.leaves(df, 95, 3).collect())
    assert pos == list(range(95))


def test_many_searches_at_once(spark):
    df = spark.createDataFrame([(i, 1000 + i * 13 % 500) for i in range(200)], "id long, val long")
    runs = extremum.robust_band_by(extremum.runs_of(df, 5), "run", Judge.exact(pairs=True), 200).collect()
    assert len(runs) == 5 and {r["winner_val"] for r in runs} == {max(1000 + i * 13 % 500 for i in range(200))}
    low = extremum.robust_band_by(extremum.runs_of(df, 2), "run", Judge.band(0.1, pairs=True), 200, want="min").collect()
    assert all(r["winner_val"] <= 1000 * 1.1**3 for r in low)


def test_coin_search_in_runs(spark):
    """Exact without noise, answers as the judge's expression gives them, and under noise of a low rank in every run."""
    import math

    from duelspark.operators import scores
    from duelspark.operators.judges import item

    df = spark.range(900).select((F.col("id") * 13).alias("id"), F.pmod(F.col("id") * 7919, F.lit(900)).alias("val"))
    many = extremum.runs_of(df, 4)
    for want, best in (("max", 899), ("min", 0)):
        exact = extremum.robust_coin_by(many, Judge.coin(0.0).on_pairs(), want=want).collect()
        assert sorted((r["run"], r["winner_val"]) for r in exact) == [(k, best) for k in range(4)]
        noisy = extremum.robust_coin_by(many, Judge.coin(0.3).on_pairs(), want=want).collect()
        assert all(abs(r["winner_val"] - best) <= math.log(900 / 0.1) ** 2 for r in noisy) and len({r["winner_id"] for r in noisy}) > 1
    # a set below the size of two samples is a round robin alone
    few = extremum.runs_of(df.where("id < 260"), 3)
    judge = Judge.coin(0.3).on_pairs()
    found = {r["run"]: r["winner_id"] for r in extremum.robust_coin_by(few, judge).collect()}
    x, y = few.select("run", item(F.col("id"), F.col("val")).alias("x")), few.select("run", item(F.col("id"), F.col("val")).alias("y"))
    won = x.join(y, "run").where("x.id <> y.id").groupBy("run", "x").agg(F.sum(judge.beats(F.col("x"), F.col("y")).cast("int")).alias("wins")).collect()
    most = {k: max(r["wins"] for r in won if r["run"] == k) for k in found}
    assert all(most[r["run"]] == r["wins"] for r in won if r["x"]["id"]["k2"] == found[r["run"]])


def test_counted_duels_are_the_asked_ones(spark, monkeypatch):
    """Equal values, every judge that goes by values, both directions; other sets and judges are asked."""
    df = spark.range(300).select((F.col("id") * 7 % 307).alias("id"), (F.pmod(F.col("id") * 7919, F.lit(97)) * 10).alias("val"))
    for judge in (Judge.exact(), Judge.band(1.0), Judge.band(0.3, "truthful"), Judge.additive_band(55)):
        for directed in (judge, judge.reversed()):
            assert extremum._countable(df, directed)
            want = scores.round_robin(df, directed).select("id", "val", "wins")
            assert sorted(extremum._counted(df, directed).collect()) == sorted(want.collect())
    monkeypatch.setattr(scores, "BROADCAST_ROWS", 100)
    assert "FlatMapGroupsInPandas" in extremum.round_robin(df, Judge.band(1.0))._jdf.queryExecution().toString()
    assert not any(extremum._countable(*x) for x in ((df, Judge.coin(0.1)), (df.unionByName(df), Judge.exact()), (df.withColumn("val", -F.col("val")), Judge.exact())))
