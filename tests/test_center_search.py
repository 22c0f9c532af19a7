from duelspark.functions import metrics
from duelspark.operators import centers, extremum, kcenter
from duelspark.operators.judges import Judge
from duelspark.sources import tables

SF = "/root/testdata/sf0.001"


def test_band_finds_its_centers_in_a_task_as_its_rounds_do(spark, monkeypatch):
    df = tables.customer_tree(spark, SF).select("id", "payload")
    runs = [{"first": 3}, {"frontier": "knockout", "assign": "incumbent"}, {"t": 2, "seed": 11}]
    calls, plain = [], extremum.robust_band
    monkeypatch.setattr(extremum, "robust_band", lambda *a, **more: calls.append(1) or plain(*a, **more))
    fast = [kcenter.band(df, 5, metrics.tree, Judge.band(0.5), **run) for run in runs]
    assert not calls  # no search by joins
    monkeypatch.setattr(centers, "fits", lambda *a: False)
    slow = [kcenter.band(df, 5, metrics.tree, Judge.band(0.5), **run) for run in runs]
    assert calls and [ids for _, ids in fast] == [ids for _, ids in slow]
    for (one, _), (other, _) in zip(fast, slow, strict=True):
        assert one.exceptAll(other).isEmpty() and one.count() == other.count()
