"""Sweeps of beams go on until recall is reached or a wider beam changes nothing."""

import numpy as np

from vecmend.operators import graph as G
from vecmend.operators import truth as T
from vecmend.plans import experiments as X


def sets(spark, n, reach):
    rng = np.random.default_rng(9)
    base = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(n, 8)))], "vec_id bigint, vec array<double>")
    asked = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(20, 8)))], "query_id bigint, vec array<double>")
    arcs = {(i, int(j)) for i in range(n) for j in np.append(rng.choice(reach, 3, replace=False), (i + 1) % reach) if i != j}
    return base, G.as_edges(spark.createDataFrame(sorted(arcs), "src bigint, dst bigint")), asked, T.exact_blocked(base, asked, 5).localCheckpoint()


def test_a_sweep_goes_on_until_recall_is_reached(spark):
    base, edges, asked, truth = sets(spark, 600, 600)
    rows = {r.beam: r.recall for r in X.curve("random", base, edges, asked, truth, k=5).collect()}
    assert sorted(rows) == list(range(5, max(rows) + 1, 10)) and max(rows) > 195
    reached = min(b for b, v in rows.items() if v >= X.STOP)
    assert max(rows) - reached < X.STEP * X.CHUNK and len(rows) % X.CHUNK == 0


def test_a_sweep_ends_where_all_that_can_be_reached_was_seen(spark):
    base, edges, asked, truth = sets(spark, 900, 300)
    rows = {r.beam: (r.recall, r.ndc) for r in X.curve("apart", base, edges, asked, truth, k=5).collect()}
    assert rows[max(rows)][0] < X.STOP and 300 <= max(rows) < 600
    assert rows[max(rows)][1] <= 301
