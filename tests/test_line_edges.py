from duelspark.workloads import line_edges


def test_edges_of_a_line_grow_with_its_records(spark):
    df = spark.createDataFrame([(i, i * 37 % 101) for i in range(100)], "id long, v long")
    got = line_edges(df, 8).collect()
    assert len(got) == 8 * 100 - 36 and sorted(r["dist"] for r in got)[0] >= 1
    order = sorted((i * 37 % 101, i) for i in range(100))
    assert {(min(i, j), max(i, j), y - x) for (x, i), (y, j) in zip(order, order[1:], strict=False)} <= {tuple(r) for r in got}
