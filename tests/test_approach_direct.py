"""The approach mend thins without a row for each candidate, to the arcs of the candidates that are written out."""

import numpy as np
import pytest

from vecmend.operators import graph as G
from vecmend.operators import mend as M
from vecmend.operators import truth as T


@pytest.mark.parametrize("metric", ("cosine", "l2"))
@pytest.mark.parametrize("shards", (None, 3))
def test_the_same_arcs_as_from_written_candidates(spark, monkeypatch, metric, shards):
    rng = np.random.default_rng(4)
    vecs = np.repeat(rng.normal(size=(60, 5)), 2, axis=0)
    base = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(vecs)], "vec_id bigint, vec array<double>")
    asked = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(150, 5)))], "query_id bigint, vec array<double>")
    if shards:
        base = G.with_shards(base, shards)
        near, asked = T.exact_shards(base, asked, 20, shards, metric), T.per_shard(asked, shards)
    else:
        near = T.exact_blocked(base, asked, 50, metric)
    stops = near.where("rank = 20").selectExpr("query_id", "vec_id stop", "dist stop_dist").localCheckpoint()
    want = M.approach_arcs(base, M.approach_candidates(base, None, asked, stops, metric), 3, metric)
    plain = lambda df: sorted((r.query_id, r.seq, r.src, r.dst, r.hardness, r.dist) for r in df.collect())
    got = plain(M.approach_direct(base, asked, stops, 3, metric))
    assert got == plain(want) and len(got) > 150
    written = []
    monkeypatch.setattr(M, "approach_candidates", lambda *a, **k: written.append(a))
    M.approach(base, G.as_edges(G.knn(base.drop("shard"), 1)), asked, near, 5, 5, 4, metric, max_iter=1)
    assert not written
