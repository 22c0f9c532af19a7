from duelspark.operators import blocking


def test_partners_are_drawn_from_all_candidates_and_from_nothing_else(spark):
    """The query wrote out all pairs before it drew one for each record."""
    texts = ["big red box"] * 6 + ["red box"] * 5 + ["box of tin"] * 4 + ["tin of red paint"] * 3 + ["alone here", "single", None]
    df = spark.createDataFrame(list(enumerate(texts)), "id long, words string")
    pairs = {(r["a"], r["b"]): r["common"] for r in blocking.token_pairs(df, "words", 2).collect()}
    pairs |= {(b, a): n for (a, b), n in pairs.items()}
    seen = set()
    for seed in range(3):
        found = blocking.drawn_partners(df, "words", ("x", "y"), 2, seed).collect()
        assert sorted(r["id"] for r in found) == sorted({a for a, _ in pairs})
        for r in found:
            for one in (r["x"], r["y"]):
                assert pairs[r["id"], one["b"]] == one["common"]
                seen.add((r["id"], one["b"]))
    assert len(seen) > len(pairs) / 4
