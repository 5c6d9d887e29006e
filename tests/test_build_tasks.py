"""A base of one shard is built by several tasks, into the graph that one task builds; lost rows are attached as before."""

import numpy as np
import pytest

from vecmend.functions import kernels as K
from vecmend.operators import graph as G


@pytest.mark.parametrize("metric", ("cosine", "l2"))
def test_several_tasks_build_what_one_builds(spark, monkeypatch, metric):
    rng = np.random.default_rng(5)
    rows = [(i * 3, v.tolist()) for i, v in enumerate(rng.normal(size=(160, 8)))]
    base = spark.createDataFrame(rows, "vec_id bigint, vec array<double>")
    history = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.normal(size=(25, 8)) + 1)], "query_id bigint, vec array<double>")
    make = {
        "hnsw": lambda: G.hnsw(base, 3, 20, metric, layers=True), "nsg": lambda: G.nsg(base, 12, 15, 5, metric),
        "tau": lambda: G.tau_mng(base, 0.01, 12, 15, 5, metric), "bridge": lambda: G.query_bridge(base, history, 6, 3, 10, metric, block_bytes=8 * 8 * 9),
    }
    arcs = lambda df: sorted((r.layer, r.src, r.dst) for r in df.collect())
    one = {n: arcs(f()) for n, f in make.items()}
    monkeypatch.setattr(G, "TASK_ROWS", 32)
    assert G.tasks_for(base) == 5
    for n, f in make.items():
        assert arcs(f()) == one[n], n


def test_lost_rows_are_attached_one_after_the_other():
    rng = np.random.default_rng(2)
    x = K.prepare(rng.normal(size=(90, 4)), "cosine")
    lists = [rng.integers(0, 90, size=1) if i % 3 else np.zeros(0, dtype=np.int64) for i in range(90)]
    want = [*lists]
    while True:  # the plain form: look again at everything after each row
        seen, queue = {7}, [7]
        for u in queue:
            for v in want[u].tolist():
                if v not in seen:
                    seen.add(v)
                    queue.append(v)
        lost = [v for v in range(90) if v not in seen]
        if not lost:
            break
        have = np.array(sorted(seen))
        u = int(have[np.argmin(K.distances(x[have], x[lost[0]], "cosine"))])
        want[u] = np.append(want[u], lost[0])
    for block in (1, 4, 256):
        assert [a.tolist() for a in K.grow_tree(lists, x, 7, "cosine", block)] == [a.tolist() for a in want]
