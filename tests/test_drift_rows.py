"""The drift workload reads the whole event log."""

from vecmend.operators import graph as G
from vecmend.plans import experiments as X


def test_drift_takes_all_rows(spark, tiny, monkeypatch):
    seen = []
    monkeypatch.setattr(X, "_base_graph", lambda base: spark.createDataFrame([], G.EDGES))
    monkeypatch.setattr(X.R, "run", lambda base, edges, history, *a, **k: seen.append(history.count()) or edges)
    monkeypatch.setattr(X, "curve", lambda name, base, edges, test, truth, *a: seen.append(test.count()) or test.select("query_id"))
    X.drift(spark, tiny)
    mended, adapted, last, again = seen
    assert mended + adapted + last == 895 and last == again
