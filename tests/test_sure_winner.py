import numpy as np

from duelspark.operators import linkage, measures
from duelspark.operators.judges import Judge


def test_the_winner_from_near_pairs_is_that_of_the_whole_bracket():
    judge = Judge.band(0.5).on_pairs()
    for seed in range(300):
        rng = np.random.default_rng(seed)
        n = int(rng.integers(2, 60))
        d = rng.integers(0, 40, n) if seed % 3 else (1.3 ** rng.integers(0, 30, n)).astype(np.int64)
        one, two, place = np.arange(n), np.arange(n) + 100, rng.permutation(n)
        ask = lambda x, y, one=one, two=two, d=d: judge.answers((one[x], two[x], d[x]), (one[y], two[y], d[y]))
        want = linkage._heat_winners(np.argsort(place), 1, ask)[0]
        drawn = []

        def between(low, high, d=d, drawn=drawn):
            i = np.nonzero((d > low) & (d <= high))[0]
            drawn.append(i)
            return i, i + 100, d[i]

        got = linkage.sure_winner(n, int(d.min()), int(d.max()), between, lambda m, taken, place=place, drawn=drawn: place[drawn[-1]], lambda pairs, x, y, ask=ask: ask(pairs[0][x], pairs[0][y]), judge.mu_milli)
        assert got == (want, want + 100)


def test_a_knockout_hierarchy_looks_at_near_pairs_only(monkeypatch):
    rng, looked = np.random.default_rng(1), []
    values = rng.integers(0, 10**9, 150).tolist()
    plain = Judge.answers
    monkeypatch.setattr(Judge, "answers", lambda self, a, b: looked.append(len(a[2])) or plain(self, a, b))
    for link in ("single", "complete"):
        looked.clear()
        got = linkage.agglomerate([*range(150)], values, linkage.line, Judge.band(0.5), link, search="knockout", naive=True, measured=True)
        assert len(got) == 149 and got[-1][4] == 150
        assert got[-1][8] == sum(m * (m - 1) // 2 - 1 + m - 2 for m in range(2, 151)) > 1.5 * sum(looked)


def test_ratio_where_the_best_merges_are_of_distance_zero(spark):
    table = lambda values: spark.createDataFrame([("x", k, v) for k, v in enumerate(values, 1)], "block string, step int, link_dist long")
    got = measures.by_iteration(table([0, 0, 6]), table([0, 0, 3])).orderBy("step").collect()
    assert [r["ratio"] for r in got] == [1.0, 1.0, 2.0]
    assert measures.by_iteration(table([1]), table([0])).first()["ratio"] is None
