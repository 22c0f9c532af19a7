import math
import random

from pyspark.sql import functions as F

from duelspark import workloads
from duelspark.functions import metrics
from duelspark.operators import baselines, kcenter, linkage, measures, proximity, votes
from duelspark.operators.judges import Judge


def clusters(spark, k=4, each=12):
    rows = [(c * each + i, [float(c * 50 + (i * 37) % 10), float((i * 13) % 7)], c) for c in range(k) for i in range(each)]
    return spark.createDataFrame(rows, "id long, payload array<double>, truth int")


def fscore(found, df):
    return measures.pair_fscore(found, df).first()["fscore"]


def test_band_kcenter_finds_separate_clusters(spark):
    df = clusters(spark)
    for frontier, assign in (("robust", "all_pairs"), ("knockout", "incumbent"), ("sampled", "all_pairs")):
        found, centers = kcenter.band(df.select("id", "payload"), 4, metrics.euclid, Judge.band(0.3), frontier=frontier, assign=assign)
        assert len(centers) == 4 and fscore(found, df) == 1.0
    found, _ = baselines.kcenter_sampled(df.select("id", "payload"), 4, metrics.euclid, Judge.exact())
    assert found.count() == df.count()


def test_exact_greedy_and_ties(spark):
    df = spark.createDataFrame([(0, 0), (1, 51), (2, 101), (3, 102), (4, 202)], "id long, payload long")
    found, centers = kcenter.exact_greedy(df, 2, metrics.gap, first=3)
    assert centers == [3, 0] and measures.objective(found).first()["radius"] == 100
    same = spark.createDataFrame([(i, 5) for i in range(4)], "id long, payload long")
    assert len(kcenter.exact_greedy(same, 3, metrics.gap)[1]) == 1
    assert len(kcenter.band(same, 3, metrics.gap, Judge.exact())[1]) == 1


def test_coin_kcenter(spark):
    df = clusters(spark, 3, 14)
    found, _ = kcenter.coin_noise(df.select("id", "payload"), 3, 14, metrics.euclid, Judge.coin(0.0), thin=False)
    assert fscore(found, df) == 1.0


def test_worked_core(spark):
    """Center w; the answers about (u, s) and (s, t) are flipped: scores v 3, s 2, u 1, t 0."""
    place, flipped = {"s": 0, "u": 51, "v": 101, "w": 102, "t": 202}, [{"u", "s"}, {"s", "t"}]
    others = [x for x in place if x != "w"]
    gap = {x: abs(place[x] - 102) for x in others}
    score = {x: sum((gap[x] <= gap[y]) != ({x, y} in flipped) for y in others if y != x) for x in others}
    assert score == {"v": 3, "s": 2, "u": 1, "t": 0}
    df = spark.createDataFrame(list(enumerate(place.values())), "id long, payload long")
    got = kcenter.core_scores(df, df.where("id = 3").first(), metrics.gap, Judge.exact())
    assert {r["id"]: r["score"] for r in got.collect()} == {2: 3, 1: 2, 4: 1, 0: 0}


def test_anchored_votes_beat_single_questions(spark):
    rows = [(i, i % 5) for i in range(40)] + [(100, 300), (101, 600)]
    df = spark.createDataFrame(rows, "id long, payload long")
    anchors = kcenter.as_literal(df.where("id < 40").collect())
    one = lambda i, p: F.struct(F.lit(i).cast("long").alias("id"), F.lit(p).cast("long").alias("payload"))
    ask = lambda s: votes.anchored_vote(one(100, 300), one(101, 600), anchors, Judge.coin(0.3, seed=s), metrics.gap)
    said = spark.range(1).select(*(ask(s).alias(f"s{s}") for s in range(20))).first()
    assert sum(said) >= 18
    none = votes.anchored_vote(one(1, 1), one(2, 2), F.array().cast("array<struct<id:bigint,payload:bigint>>"), Judge.exact(), metrics.gap)
    assert spark.range(1).select(none.alias("x")).first()["x"]


def test_farthest_and_nearest(spark):
    df = clusters(spark).select("id", "payload")
    gaps = proximity.distances(df, 0, metrics.euclid)
    assert proximity.farthest_band(df, 0, metrics.euclid, Judge.exact(), t=1).first()["winner_val"] == gaps.agg(F.max("val")).first()[0]
    assert proximity.nearest_coin(df, 0, metrics.euclid, Judge.exact()).first()["winner_val"] == gaps.agg(F.min("val")).first()[0]


def test_anchors_vote_in_the_heats(spark):
    """6 alpha is 12 and all but one record are 4000 short of the farthest one."""
    rows = [(i, i % 3) for i in range(41)] + [(i, 1000 + i % 7) for i in range(100, 700)] + [(900, 5000)]
    df = spark.createDataFrame(rows, "id long, payload long")
    anchors = df.where("id BETWEEN 1 AND 40").collect()
    for seed in range(4):
        found = proximity.farthest_coin_anchored(df.where("id = 0 OR id > 40"), 0, anchors, metrics.gap, Judge.coin(0.3, seed=seed), seed=seed)
        assert found.first()["winner_val"] >= 5000 - 12


def test_exact_hierarchies_against_a_plain_version():
    values = random.Random(5).sample(range(1_000_000), 24)
    for link, pick in (("single", min), ("complete", max)):
        groups, want = [[v] for v in values], []
        while len(groups) > 1:
            d, i, j = min((pick(abs(a - b) for a in groups[i] for b in groups[j]), i, j) for i in range(len(groups)) for j in range(i + 1, len(groups)))
            want.append(d)
            groups[i] += groups.pop(j)
        for naive in (False, True):
            got = linkage.agglomerate(list(range(24)), values, linkage.line, Judge.exact(), link, naive=naive)
            assert [r[7] for r in got] == want and got[-1][4] == 24


def test_hierarchies_under_noise(spark):
    df = clusters(spark, 3, 8)
    for judge in (Judge.band(0.5), Judge.coin(0.1)):
        got = linkage.hierarchy(df, linkage.euclid, judge, "complete", "truth")
        assert got.count() == 3 * 7
    assert linkage.over_groups(df, "truth", linkage.euclid, Judge.coin(0.1)).count() == 2
    assert linkage.blocked(df, "truth", linkage.euclid, Judge.exact()).where("block = 'medoids'").count() == 2
    exact = baselines.linkage_exact(df, linkage.euclid)
    assert fscore(linkage.cut(exact, df, 3), df) == 1.0


def test_same_cluster_questions(spark):
    df = clusters(spark, 3, 5)
    pairs = baselines.same_cluster_pairs(df, 150)
    assert 0 < pairs.count() <= 150
    yes = spark.createDataFrame([(0, 1), (1, 2), (7, 8)], "a long, b long")
    label = {r["id"]: r["center_id"] for r in baselines.clusters_of_yes(df, yes).collect()}
    assert label[2] == 0 and label[8] == 7 and label[14] == 14


def test_bounds():
    assert math.isclose(measures.kcenter_bound(0.0), 2.0) and measures.cost(540) == 32.4


def test_group_votes_use_more_than_the_first_members(spark):
    """The first six ids of group 0 lie beyond group 2; the others say that groups 0 and 1 are the nearest."""
    rows = [(i, [400.0 if i < 6 else float(i % 9)], 0) for i in range(60)] + [(i, [90.0 + i % 9], 1) for i in range(100, 160)] + [(i, [300.0 + i % 9], 2) for i in range(200, 203)]
    df = spark.createDataFrame(rows, "id long, payload array<double>, truth int")
    for judge in (Judge.exact(), Judge.coin(0.2)):
        first = linkage.over_groups(df, "truth", linkage.euclid, judge).where("step = 1").first()
        assert {first["left_id"], first["right_id"]} == {0, 100} and first["size"] == 120


def test_planted_queries_use_the_whole_table(spark, monkeypatch):
    """Every record is swept over all ten centers, and every near record meets every far one."""
    sf, seen, pairs, plain = "/root/testdata/sf0.001", [], [], kcenter.sweep_assign
    monkeypatch.setattr(kcenter, "sweep_assign", lambda rest, centers, *more: seen.append((rest.count(), len(centers))) or plain(rest, centers, *more))
    assert workloads.sweep_assign_exact(spark, sf).first()["held"] and seen == [(500, 10)]
    df = workloads.tables.planted(spark, sf)
    gaps = proximity.distances(df, 0, metrics.planted(4.0))
    want = gaps.where("val < 2000000").count() * gaps.where("val >= 3000000").count()
    real = workloads.F.avg
    monkeypatch.setattr(workloads.votes, "count_yes", lambda *a: F.lit(1))
    monkeypatch.setattr(workloads.F, "avg", lambda c: pairs.append(1) or F.count("*") if len(pairs) == 0 else real(c))
    assert workloads.anchored_asymmetry(spark, sf).collect()[0]["nearer_first"] == want


def test_both_linkages_have_both_baselines(spark):
    got = {(r["link"], r["method"]) for r in workloads.linkage_methods(spark, "/root/testdata/sf0.001").collect()}
    assert got == {(link, method) for link in ("single", "complete") for method in ("ours", "sampler", "knockout")}


def test_coin_kcenter_thins_and_sweeps(spark):
    """Four far clusters of 60 at p = 0.15: records are thinned, the frontier is voted for, the rest is swept."""
    rows = [(i, [1000.0 * (i % 4) + (i * 7 % 13)], i % 4) for i in range(240)]
    df = spark.createDataFrame(rows, "id long, payload array<double>, truth int")
    found, centers = kcenter.coin_noise(df.select("id", "payload"), 4, 40, metrics.euclid, Judge.coin(0.15), t=2)
    assert len({c % 4 for c in centers}) == 4 and found.count() == 240
    assert measures.pair_fscore(found, df).first()["fscore"] > 0.95


def test_answers_persist_over_rounds(spark):
    """A center kept from round to round is asked about in the same words, so more centers only refine the assignment."""
    df = spark.createDataFrame([(i, i * i) for i in range(60)], "id long, payload long")
    judge = Judge.coin(0.3)
    few, many = (kcenter.assign_duels(df, [{"id": c, "payload": c * c} for c in cs], metrics.gap, judge).orderBy("id").collect() for cs in ([3, 40], [3, 40, 55]))
    side = lambda u, c: ((min(u, c), max(u, c)), abs(u * u - c * c))
    for a, b in zip(few, many, strict=True):
        u = a["id"]
        first = judge.on_pairs().answer(side(u, 3), side(u, 40))
        assert a["wins"] == [int(first), int(not first)] and b["wins"][0] - int(first) in (0, 1) and b["d"][:2] == a["d"]
        assert sum(b["wins"]) == 3


def test_token_pairs_against_all_pairs(spark):
    from duelspark.operators import blocking

    rows = [(i, f"common {'' if i % 3 else 'also'} w{i % 7} v{i % 11}") for i in range(80)] + [(100, ""), (101, None), (102, "alone")]
    df = spark.createDataFrame(rows, "id long, text string")
    sets = {i: set(t.split()) for i, t in rows if t}
    for least in (1, 2, 3):
        want = {(a, b): len(sets[a] & sets[b]) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= least}
        got = blocking.token_pairs(df, "text", least).collect()
        assert len(got) == len(want) and {(r["a"], r["b"]): r["common"] for r in got} == want


def test_yes_answers_along_a_chain(spark):
    df = spark.createDataFrame([(i,) for i in range(150)], "id long")
    yes = spark.createDataFrame([(i, i + 1) for i in range(149) if i != 70], "a long, b long")
    label = {r["id"]: r["center_id"] for r in baselines.clusters_of_yes(df, yes).collect()}
    assert all(label[i] == (0 if i <= 70 else 71) for i in range(150))
    pairs = [(r["a"], r["b"]) for r in baselines.same_cluster_pairs(df, 40).collect()]
    assert len(pairs) == len(set(pairs)) == 40 and all(a < b for a, b in pairs)
    assert max(pairs.count(p) for p in pairs) == 1 and len({x for p in pairs for x in p}) > 45  # not a chain: ends hardly repeat


def test_measured_hierarchy(spark):
    rng = __import__("random").Random(5)
    rows = [(i, rng.randrange(10**6)) for i in range(40)]
    for link in ("single", "complete"):
        exact = linkage.agglomerate([i for i, _ in rows], [v for _, v in rows], linkage.line, Judge.exact(), link, measured=True)
        assert all(r[7] == r[9] for r in exact)
        noisy = linkage.agglomerate([i for i, _ in rows], [v for _, v in rows], linkage.line, Judge.band(0.5), link, measured=True)
        assert all(r[9] <= r[7] for r in noisy) and any(r[9] < r[7] for r in noisy)


def test_central_records_by_questions(spark):
    df = spark.createDataFrame([(i, 100 * (i // 20) + abs(i % 20 - 10) ** 2 // 4, str(i // 20)) for i in range(60)], "id long, payload long, block string")
    merges = linkage.blocked(df, "block", linkage.line, Judge.exact()).where("block = 'medoids'").collect()
    assert len(merges) == 2 and all(80 <= r["link_dist"] <= 120 for r in merges)
