"""Neighbours among many rows, found in single precision first; token vectors; graphs of recall_mix."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecmend.functions import kernels as K
from vecmend.functions import vectors as V
from vecmend.plans import experiments as X
from vecmend.sources import families as D


def brute(x, ids, q, k, metric):
    rows = []
    for v in q:
        d = K.exact_distances(x, np.arange(len(x)), v[None, :], np.zeros(len(x), dtype=np.int64), metric)
        rows.append(np.lexsort((ids, d))[:k])
    return np.array(rows)


@pytest.mark.parametrize("metric", ("cosine", "l2", "ip"))
@pytest.mark.parametrize("kind", ("plain", "offset", "copies", "huge"))
def test_many_rows_have_their_exact_neighbours(monkeypatch, metric, kind):
    monkeypatch.setattr(K, "MANY", 256)
    monkeypatch.setattr(K, "TOGETHER", 16)
    monkeypatch.setattr(K, "TILE", 1 << 12)
    rng = np.random.default_rng(4)
    x = rng.normal(size=(3001, 16))
    x = {"plain": x, "offset": x + 1e4, "copies": np.repeat(x[:7], 450, axis=0)[:3001], "huge": x * 1e16}[kind]
    x, ids, given = K.prepare(x, metric), rng.permutation(3001), []
    likely = K.likely
    monkeypatch.setattr(K, "likely", lambda *a: given.append(likely(*a)) or given[-1])
    rows, _ = K.nearest(x, ids, x[:40], 9, metric)
    assert (rows == brute(x, ids, x[:40], 9, metric)).all()
    assert len(given) == 3 and (given[0] is None) == (kind == "huge" and metric != "cosine")


def test_token_vectors_are_those_of_sql(spark):
    rows = [(1, "The cat, the CAT; a-b c3po"), (2, None), (3, "123 ..."), (4, ""), (None, "x y z"), (5, "first part"), (5, "second Part"), (6, "äpfel naïve straße K"), (7, "w " * 5000)]
    docs = spark.createDataFrame(rows, "d bigint, t string").repartition(2)
    h = V.hash32(F.lower("t"))
    cells = docs.select("d", F.explode(F.regexp_extract_all("t", F.lit("[A-Za-z]+"), F.lit(0))).alias("t")).select("d", (h % D.DIM).alias("j"), F.when(F.floor(h / D.DIM) % 2 == 0, 1.0).otherwise(-1.0).alias("x"))
    want = cells.groupBy("d").agg(F.array(*[F.sum(F.when(F.col("j") == i, F.col("x")).otherwise(0.0)) for i in range(D.DIM)]).alias("raw")).where(V.norm(F.col("raw")) > 0)
    got = {r[0]: r[1] for r in D._token_vectors(docs, "d", "t").collect()}
    assert got == {r[0]: r[1] for r in want.select("d", V.normalise(F.col("raw"))).collect()} and set(got) == {1, None, 5, 6, 7}


def test_recall_mix_builds_one_graph_a_base(spark, monkeypatch):
    built, make = [], X._base_graph
    monkeypatch.setattr(X, "_base_graph", lambda base: built.append(1) or make(base))
    rows = X.recall_mix(spark, "/root/testdata/sf0.001").collect()
    assert len(built) == 2 and {r.family for r in rows} == {"sphere", "sphere_id", "text"}
