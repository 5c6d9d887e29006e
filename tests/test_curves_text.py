"""Curves of the text family compare all graphs."""

from pyspark.sql import functions as F

from vecmend.plans import experiments as X


def test_curves_text_have_all_graphs(spark, tiny, monkeypatch):
    monkeypatch.setattr(X, "curve", lambda name, base, edges, *a, **k: edges.agg(F.lit(name).alias("method"), F.count(F.lit(1)).alias("n")))
    got = {r.method: r.n for r in X.WORKLOADS["curves_text"](spark, tiny).collect()}
    assert set(got) == {"layered_bottom", "layered_full", "spreading", "relaxed", "bridge", "unmended", "mended"} and min(got.values()) > 0
