"""Worked examples and invariants of the numeric kernels."""

import numpy as np
import pytest

from vecmend.functions import kernels as K


def ranks(arcs, n_near, most):
    return K.bottleneck_ranks(np.array(arcs, dtype=np.int64).reshape(-1, 2), n_near, most)


def test_detour_of_rank_ten():
    arcs = [(1, 10), (10, 9), (9, 8), (8, 3), (10, 11), (11, 9)]
    assert ranks(arcs, 3, 11)[0, 2] == 10


def test_incremental_fill():
    h = ranks([(1, 3), (2, 4), (4, 1)], 3, 4)
    assert h[0, 2] == 3 and h[1, 0] == 4 and h[1, 2] == 4 and h[0, 1] == K.NEVER


def test_line_needs_no_mending():
    arcs = [(i, i + 1) for i in range(1, 8)] + [(i + 1, i) for i in range(1, 8)]
    h = ranks(arcs, 8, 8)
    assert all(h[i, j] == max(i, j) + 1 for i in range(8) for j in range(8))
    assert K.mend_pairs(h, np.ones((8, 8)), 8) == []


def minimax(arcs, n_near, most):
    best = {(a, b): max(a, b) for a, b in arcs if max(a, b) <= most}
    while True:
        new = dict(best)
        for (a, b), x in best.items():
            for c, e in arcs:
                if c == b and e <= most:
                    new[a, e] = min(new.get((a, e), K.NEVER), max(x, e))
        if new == best:
            break
        best = new
    return np.array([[i if i == j else best.get((i, j), K.NEVER) for j in range(1, n_near + 1)] for i in range(1, n_near + 1)])


@pytest.mark.parametrize("seed", range(12))
def test_incremental_ranks_equal_the_definition(seed):
    rng = np.random.default_rng(seed)
    arcs = [(a, b) for a in range(1, 13) for b in range(1, 13) if a != b and rng.random() < 0.12]
    h = ranks(arcs, 6, 12)
    assert (h == minimax(arcs, 6, 12)).all()
    assert all(h[i, j] <= max(h[i, k], h[k, j]) for i in range(6) for j in range(6) for k in range(6))


@pytest.mark.parametrize("n", (4, 6, 10))
def test_islands_take_a_spanning_tree_both_ways(n):
    x = np.random.default_rng(n).normal(size=(n, 3))
    gaps = K.all_distances(x, x, "l2")
    h = ranks([], n, n)
    arcs = K.mend_pairs(h, gaps, n)
    assert len(arcs) == 2 * (n - 1)
    assert (ranks([(s + 1, t + 1) for s, t, _ in arcs], n, n) <= n).all()


@pytest.mark.parametrize("seed", range(8))
def test_mended_pairs_are_within_the_cap_and_arcs_within_the_bound(seed):
    rng = np.random.default_rng(seed)
    arcs = [(a, b) for a in range(1, 31) for b in range(1, 31) if a != b and rng.random() < 0.05]
    gaps = K.all_distances(*[rng.normal(size=(8, 4))] * 2, "l2")
    h = ranks(arcs, 8, 30)
    for order in ("length", "random"):
        new = K.mend_pairs(h, gaps, 8, order)
        assert (ranks(arcs + [(s + 1, t + 1) for s, t, _ in new], 8, 30) <= 8).all()
        if order == "length":
            assert len(new) <= 2 * (8 - 1)


@pytest.fixture(scope="module")
def cloud():
    x = np.random.default_rng(1).normal(size=(200, 8))
    return K.prepare(x, "cosine"), np.arange(200)


def test_full_beam_on_a_reachable_graph_is_brute_force(cloud):
    x, ids = cloud
    lists, root = K.spreading(x, ids, 20, 20, 8, "cosine")
    for q in K.prepare(np.random.default_rng(2).normal(size=(10, 8)), "cosine"):
        w = K.walk(lists, x, q, 10, [root], len(x), "cosine")
        assert w.rows.tolist() == K.nearest(x, ids, q[None], 10, "cosine")[0][0].tolist() and w.ndc <= len(x)


def test_a_beam_of_the_bottleneck_rank_finds_the_pair(cloud):
    x, ids = cloud
    lists = K.knn_lists(x, ids, 5, "cosine")
    for q in K.prepare(np.random.default_rng(4).normal(size=(6, 8)), "cosine"):
        near = K.nearest(x, ids, q[None], 40, "cosine")[0][0]
        at = {int(v): r + 1 for r, v in enumerate(near)}
        arcs = [(at[int(u)], at[int(v)]) for u in near for v in lists[int(u)] if int(v) in at]
        h = ranks(arcs, 6, 40)
        for i in range(6):
            for j in range(6):
                if h[i, j] < K.NEVER:
                    assert near[j] in K.walk(lists, x, q, 1, [int(near[i])], int(h[i, j]), "cosine").seen


def test_removed_rows_are_walked_but_not_returned(cloud):
    x, ids = cloud
    lists, root = K.spreading(x, ids, 20, 20, 8, "cosine")
    dead = ids % 5 == 0
    w = K.walk(lists, x, x[3], 10, [root], 10, "cosine", dead)
    assert len(w.rows) == 10 and not dead[w.rows].any()


def test_thinning_keeps_no_violation_and_drops_with_a_witness(cloud):
    x, _ = cloud
    d = K.distances(x[1:60], x[0], "cosine")
    order = np.argsort(d)
    between = K.all_distances(x[1:60][order], x[1:60][order], "cosine")
    d = d[order]
    kept = K.thin(d, between, 1000)
    for a, v in enumerate(kept):
        assert all(between[v, r] > d[v] for r in kept[:a])
    for v in set(range(len(d))) - set(kept):
        assert any(between[v, r] <= d[v] for r in kept if r < v)


def test_greedy_tree_joins_the_nearest_rows_at_least_cost():
    import numpy as np

    from vecmend.functions import kernels as K

    assert K.greedy_tree(np.array([[1, 2], [2, 3], [1, 5], [5, 4]]), 5, 4) == (4, 4)
    assert K.greedy_tree(np.array([[1, 5], [5, 2], [5, 3]]), 5, 3) == (3, 3)
    assert K.greedy_tree(np.array([[2, 1]]), 3, 3) == (0, 1)
    assert K.greedy_tree(np.zeros((0, 2)), 3, 2) == (0, 1)
