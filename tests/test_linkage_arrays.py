import random

import numpy as np
from pyspark.sql import functions as F

from duelspark.operators import linkage
from duelspark.operators.judges import Judge


def test_array_answers_are_the_plain_ones():
    r = random.Random(3)
    key = lambda: tuple(sorted((r.randint(0, 3), r.randint(0, 3))))
    split = lambda rows: tuple(np.array(c) for c in zip(*((*k, v) for k, v in rows), strict=True))
    for judge in (Judge.exact(), Judge.band(0.5), Judge.band(1.0, "truthful"), Judge.band(0.5, "coinflip"), Judge.additive_band(4), Judge.coin(0.2), Judge.crowd(0.2), Judge.band(0.5).reversed()):
        judge = judge.on_pairs()
        a, b = ([(key(), r.randint(0, 9)) for _ in range(80)] for _ in "ab")
        assert list(judge.answers(split(a), split(b))) == [judge.answer(x, y) for x, y in zip(a, b, strict=True)]
        if judge.by_value:
            items = [(k, r.randint(0, 20)) for k in sorted({key() for _ in range(40)})]
            one, two, val = split(items)
            assert list(judge.firsts((one, two), val)) == [sum(judge.answer(x, y) for y in items if y != x) for x in items]
            twice = judge.firsts((np.append(one, one[:2]), np.append(two, two[:2])), np.append(val, val[:2]))  # as pointers do that point at one another
            more = [*items, *items[:2]]
            assert list(twice) == [sum(judge.answer(x, y) if i < j else not judge.answer(y, x) for j, y in enumerate(more) if i != j) for i, x in enumerate(more)]


def test_searches_by_arrays_agree():
    """Truthful answers with many ties: pointers, the search over all pairs and the plain order of distances give the same merges."""
    r = random.Random(5)
    for _ in range(20):
        n = r.randint(2, 25)
        values = [r.randint(0, 30) for _ in range(n)]
        for link in ("single", "complete"):
            fast, slow = (linkage.agglomerate([*range(n)], values, linkage.line, Judge.exact(), link, naive=naive) for naive in (False, True))
            assert [m[1:8] for m in fast] == [m[1:8] for m in slow]
        assert [m[7] for m in linkage.on_line([*range(n)], values)] == sorted(y - x for x, y in zip(sorted(values), sorted(values)[1:], strict=False))


def test_array_metrics_are_the_plain_ones():
    r = random.Random(9)
    people = [{"region": r.randint(0, 1), "nation": r.randint(0, 3), "segment": r.choice("AB"), "bal": r.randint(0, 10**10)} for _ in range(12)]
    vectors = [{"v": [r.random() for _ in range(8)], "label": r.randint(0, 2)} for _ in range(12)]
    i, j = np.triu_indices(12)
    for metric, rows in ((linkage.tree, people), (linkage.planted(4.0), vectors), (linkage.euclid, [v["v"] for v in vectors]), (linkage.line, [p["bal"] for p in people])):
        assert linkage.between(metric, rows)(i, j).tolist() == [metric(rows[x], rows[y]) for x, y in zip(i, j, strict=True)]


def test_a_block_above_three_thousand_records(spark):
    """Larger blocks were refused."""
    df = spark.range(3100).select("id", (F.col("id") * F.col("id") % 100_003 + 1).alias("payload"))
    merges = linkage.hierarchy(df, linkage.line, Judge.band(0.5), "complete").collect()
    assert len(merges) == 3099 and max(m["size"] for m in merges) == 3100
