"""Exact searches on a table whose rows repeat under other keys, against their SQL; no pair is formed by a join."""

import duckdb
import numpy as np
import pytest

from vecmend import catalog
from vecmend.functions import kernels as K


@pytest.fixture(scope="module")
def doubled(spark, tiny, tmp_path_factory):
    d = str(tmp_path_factory.mktemp("doubled"))
    con = duckdb.connect()
    con.execute(f"COPY (SELECT * FROM '{tiny}/embeddings.parquet' UNION ALL SELECT * REPLACE (vec_id + 500 AS vec_id) FROM '{tiny}/embeddings.parquet' WHERE vec_id < 300) TO '{d}/embeddings.parquet'")
    con.execute(f"CREATE VIEW embeddings AS SELECT * FROM '{d}/embeddings.parquet'")
    return d, con


@pytest.mark.parametrize("name", ("knn_l2", "knn_cosine", "knn_blocked_l2", "approach_candidates", "approach_thinned", "sql_vector_functions"))
def test_equal_rows_are_ordered_by_their_ids(spark, doubled, name):
    d, con = doubled
    df = catalog.QUERIES[name](spark, d)
    assert "NestedLoop" not in df._jdf.queryExecution().executedPlan().toString()
    cur = con.execute(catalog.ORACLE_SQL[name])
    cols = [c[0] for c in cur.description]
    plain = lambda v: round(v, 6) + 0.0 if isinstance(v, float) else v
    want = sorted(repr([plain(r[cols.index(c)]) for c in df.columns]) for r in cur.fetchall())
    assert sorted(repr([plain(v) for v in r]) for r in df.collect()) == want


@pytest.mark.parametrize("metric", ("cosine", "l2", "ip"))
def test_blocks_and_copies_change_no_answer(monkeypatch, metric):
    rng = np.random.default_rng(3)
    base = K.prepare(np.repeat(rng.normal(size=(30, 7)), 4, axis=0), metric)
    q, ids = K.prepare(np.concatenate([base[:5], rng.normal(size=(20, 7))]), metric), rng.permutation(120)
    d = np.stack([K.exact_distances(q, np.full(120, i), base, np.arange(120), metric) for i in range(25)])
    want = np.stack([np.lexsort((ids, own))[:10] for own in d])
    for cells in (1, 500, 1 << 22):
        monkeypatch.setattr(K, "CELLS", cells)
        rows, dist = K.nearest(base, ids, q, 10, metric)
        assert (rows == want).all() and (dist == np.take_along_axis(d, want, 1)).all()
        whose, row, _ = K.nearer(base, q, dist[:, 8], metric)
        assert {*zip(whose.tolist(), row.tolist())} == {*zip(*(x.tolist() for x in np.nonzero(d < dist[:, 8:9])))}
