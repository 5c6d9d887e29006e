"""One walk for several beams, and bounds on neighbours."""

import numpy as np
import pytest

from vecmend.functions import kernels as K
from vecmend.operators import graph as G
from vecmend.operators import search as S


@pytest.mark.parametrize("kind", ("plain", "copies", "grid"))
@pytest.mark.parametrize("metric", ("cosine", "l2"))
def test_a_sweep_gives_what_each_beam_gives(kind, metric):
    rng = np.random.default_rng(5)
    x = rng.integers(0, 3, size=(400, 4)).astype(float) + 0.5 if kind == "grid" else rng.normal(size=(400, 8))
    x = K.prepare(np.concatenate([x[:200], x[:200]]) if kind == "copies" else x, metric)
    out = [np.sort(rng.choice(400, 6, replace=False)) for _ in range(400)]
    beams = [10, 3, 20, 40, 500]
    for q in K.prepare(rng.normal(size=(30, x.shape[1])), metric):
        for beam, (w, _) in zip(beams, K.sweep_walk(out, x, q, 5, [0, 7], beams, metric), strict=True):
            one = K.walk(out, x, q, 5, [0, 7], beam, metric)
            assert (w.rows.tolist(), w.dist.tolist(), w.ndc, w.hops) == (one.rows.tolist(), one.dist.tolist(), one.ndc, one.hops)


def test_a_sweep_evaluates_what_its_widest_beam_does(monkeypatch):
    rng = np.random.default_rng(6)
    x = K.prepare(rng.normal(size=(400, 8)), "cosine")
    out = [rng.choice(400, 6, replace=False) for _ in range(400)]
    calls, plain = [], K.distances

    def counted(block, q, metric):
        calls.append(len(block))
        return plain(block, q, metric)

    monkeypatch.setattr(K, "distances", counted)
    walks = K.sweep_walk(out, x, x[3], 5, [0], [10, 20, 40], "cosine")
    assert sum(calls) == walks[-1][0].ndc


def test_neighbours_by_slabs_equal_brute_force():
    rng = np.random.default_rng(7)
    for n, k in ((40, 7), (700, 10), (5000, 33)):
        x = np.concatenate([rng.normal(size=(n // 2, 6))] * 2)
        q, ids = rng.normal(size=(20, 6)), rng.permutation(len(x))
        d = K.all_distances(q, x, "l2")
        assert (K.kth_bounds(d, k) >= np.sort(d, axis=1)[:, k - 1]).all()
        rows, _ = K.nearest(x, ids, q, k, "l2")
        exact = np.array([K.exact_distances(q, np.full(len(x), i), x, np.arange(len(x)), "l2") for i in range(len(q))])
        assert rows.tolist() == [np.lexsort((ids, e))[:k].tolist() for e in exact]


def test_sweep_over_shards_equals_single_searches(spark):
    rng = np.random.default_rng(8)
    base = spark.createDataFrame([(i, v.tolist(), i % 2) for i, v in enumerate(rng.normal(size=(120, 6)))], "vec_id bigint, vec array<double>, shard int")
    asked = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(9, 6)))], "query_id bigint, vec array<double>")
    edges = G.hnsw(base, 3, 20, layers=True)
    for rows in (base, base.drop("shard")):
        for dead in (None, base.where("vec_id % 7 = 0").select("vec_id")):
            got = {tuple(r) for r in S.sweep(rows, edges, asked, 4, [6, 12], tombstones=dead).drop("us").select("beam", "query_id", "rank", "vec_id", "ndc", "hops").collect()}
            want = {(b, *r) for b in (6, 12) for r in S.sharded(rows, edges, asked, 4, b, tombstones=dead).select("query_id", "rank", "vec_id", "ndc", "hops").collect()}
            assert got == want
