"""Measures, distances to distributions, splits, pictures, SQL functions, and theorems on small cases."""

import itertools

import numpy as np
from pyspark.sql import functions as F

from vecmend.functions import kernels as K
from vecmend.functions import vectors as V
from vecmend.operators import graph as G
from vecmend.operators import joins as J
from vecmend.operators import metrics as E
from vecmend.operators import truth as T
from vecmend.operators import upkeep as U
from vecmend.operators import vicinity as N


def answers(spark, rows):
    return spark.createDataFrame(rows, "query_id bigint, rank int, vec_id bigint, dist double")


def test_short_answers_have_no_distance_error(spark):
    truth = answers(spark, [(1, 1, 5, 1.0), (1, 2, 6, 2.0), (2, 1, 5, 1.0), (2, 2, 6, 2.0)])
    got = answers(spark, [(1, 1, 5, 1.0), (2, 1, 6, 1.5), (2, 2, 7, 2.0)])
    assert {r.query_id: r.rderr for r in E.rderr(got, truth, 2).collect()} == {1: None, 2: 0.25}


def test_approximate_answer_is_measured_against_what_it_leaves_out(spark):
    truth = answers(spark, [(1, 1, 5, 1.0), (1, 2, 6, 1.2), (1, 3, 7, 5.0), (2, 1, 5, 1.0), (2, 2, 6, 1.2), (2, 3, 7, 1.3)])
    got = answers(spark, [(1, 1, 5, 1.0), (1, 2, 7, 5.0), (2, 1, 5, 1.0), (2, 2, 7, 1.3)])
    assert {r.query_id: r.ok for r in E.epsilon_answers(got, truth, 2, 0.1).collect()} == {1: False, 2: True}
    exact = answers(spark, [(1, 1, 5, 1.0), (1, 2, 6, 1.2)])
    assert [r.ok for r in E.epsilon_answers(exact, truth, 2, 0.0).collect()] == [True]


def test_value_between_points_of_a_curve(spark):
    curve = spark.createDataFrame([("a", 10, 0.5, 100.0), ("a", 20, 0.9, 60.0), ("b", 10, 0.95, 30.0), ("c", 10, 0.2, 9.0)], "method string, beam int, recall double, qps double")
    assert {r.method: round(r.qps, 6) for r in E.at_level(curve, "recall", "qps", 0.7).collect()} == {"a": 80.0, "b": 30.0}


def test_out_degrees_count_rows_without_arcs(spark):
    base = spark.createDataFrame([(i,) for i in range(4)], "vec_id bigint")
    edges = spark.createDataFrame([(0, 1, "base", 0, 0, -1, -1), (0, 2, "extra", 0, 5, 0, 0), (1, 2, "base", 0, 0, -1, -1), (1, 3, "base", 1, 0, -1, -1)], G.EDGES)
    assert {r.degree: r.n for r in E.out_degrees(edges, base).collect()} == {2: 1, 1: 1, 0: 2}
    assert E.arrival_share(spark.createDataFrame([(1, 0.0), (2, 0.5)], "query_id int, recall double")).first().share == 0.5


def test_full_mahalanobis_equals_numpy(spark):
    rng = np.random.default_rng(1)
    x, q = rng.normal(size=(80, 5)) @ rng.normal(size=(5, 5)), rng.normal(size=(7, 5))
    base = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id bigint, vec array<double>").repartition(3)
    asked = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(q)], "query_id bigint, vec array<double>")
    inverse = np.linalg.inv(np.cov(x.T, bias=True) + 1e-6 * np.eye(5))
    want = np.sqrt(np.einsum("ij,jk,ik->i", q - x.mean(0), inverse, q - x.mean(0)))
    got = {r.query_id: r.distance for r in U.mahalanobis(asked, base).collect()}
    assert all(abs(got[i] - want[i]) < 1e-9 for i in range(7))


def test_split_keeps_test_keys_out_of_history(spark):
    rows = [(i, [float(i // 2), 1.0], i) for i in range(20)]
    q = spark.createDataFrame(rows, "query_id bigint, vec array<double>, ts long")
    for mode in ("random", "latest"):
        got = U.split(q, 3, mode).collect()
        assert len(got) == 10 and sum(r.role == "test" for r in got) == 3 and len({r.key_md5 for r in got}) == 10
        if mode == "latest":
            assert {r.query_id for r in got if r.role == "test"} == {14, 16, 18}


def test_shape_and_picture_of_a_vicinity(spark):
    truth = answers(spark, [(1, r, 10 + r, r / 10) for r in range(1, 5)])
    edges = spark.createDataFrame([(11, 12, "base", 0, 0, -1, -1), (12, 11, "base", 0, 0, -1, -1), (13, 11, "base", 0, 0, -1, -1)], G.EDGES)
    r = N.shape(truth, N.extract(truth, edges, 4), 4).first()
    assert (r.n_arcs, r.n_isolated, r.strong) == (3, 1, False)
    ring = spark.createDataFrame([(11, 12), (12, 13), (13, 14), (14, 11)], "src bigint, dst bigint")
    assert N.shape(truth, N.extract(truth, ring, 4), 4).first().strong
    corners = {11: (0.0, 0.0), 12: (1.0, 0.0), 13: (0.0, 1.0), 14: (1.0, 1.0)}
    base = spark.createDataFrame([(k, list(v)) for k, v in corners.items()], "vec_id bigint, vec array<double>")
    place = {r.rank: np.array([r.x, r.y]) for r in N.layout(T.pair_gaps(truth, base, 4, "l2")).collect()}
    for i, j in itertools.combinations(range(1, 5), 2):
        assert abs(np.linalg.norm(place[i] - place[j]) - np.linalg.norm(np.subtract(corners[10 + i], corners[10 + j]))) < 1e-6


def test_sql_functions_and_item_means(spark):
    V.register(spark)
    row = spark.sql("SELECT vec_dot(array(1D, 2D), array(3D, 4D)) AS d, vec_l2(array(0D, 0D), array(3D, 4D)) AS l, vec_norm(array(3D, 4D)) AS n, vec_cos(array(1D, 0D), array(0D, 2D)) AS c, canon_key(array(1D)) AS k").first()
    assert tuple(row)[:4] == (11.0, 5.0, 5.0, 1.0) and row.k == spark.range(1).select(V.key_md5(F.array(F.lit(1.0))).alias("k")).first().k
    mean = spark.range(1).select(V.combine(F.array(F.lit(1.0), F.lit(0.0)), F.array(F.lit(0.0), F.lit(1.0))).alias("v")).first().v
    assert np.allclose(mean, [0.5**0.5] * 2)


def test_joins_by_time(spark):
    left = spark.createDataFrame([(1, "a", 10), (2, "a", 20), (3, "b", 5)], "id int, k string, t int")
    right = spark.createDataFrame([("a", 10, 7), ("a", 10, 8), ("a", 15, 9), ("b", 6, 1)], "k string, t int, v int")
    assert {r.id: r.last for r in J.as_of(left, right, "k", "t", "v", "last").collect()} == {1: 8, 2: 9, 3: None}
    at = lambda df: df.withColumn("t", F.timestamp_seconds("t"))
    got = J.within_span(at(left), at(right), "k", "t", 5).select("id", "v_r").collect()
    assert {(r.id, r.v_r) for r in got} == {(1, 9), (3, 1)}


def test_a_wide_enough_walk_visits_all_that_its_vicinity_connects():
    rng = np.random.default_rng(5)
    for _ in range(15):
        x = rng.normal(size=(60, 4))
        out = [rng.choice(60, 3, replace=False) for _ in range(60)]
        out = [o[o != i].astype(np.int64) for i, o in enumerate(out)]
        q, size = rng.normal(size=4), 15
        near = np.argsort(K.distances(x, q, "l2"), kind="stable")[:size]
        rank = {int(v): r + 1 for r, v in enumerate(near)}
        inside = np.array([(rank[int(u)], rank[int(v)]) for u in near for v in out[u] if int(v) in rank], dtype=np.int64).reshape(-1, 2)
        h = K.bottleneck_ranks(inside, size, size)
        for i in range(size):
            seen = set(K.walk(out, x, q, 1, [int(near[i])], size, "l2").seen.tolist())
            assert all(int(near[j]) in seen for j in range(size) if h[i, j] <= size)


def delaunay(points):
    """Edges of triangles whose circumcircle holds no other point."""
    edges = set()
    for a, b, c in itertools.combinations(range(len(points)), 3):
        p, q, r = points[a], points[b], points[c]
        m = 2 * np.array([q - p, r - p])
        if abs(np.linalg.det(m)) < 1e-9:
            continue
        o = np.linalg.solve(m, [q @ q - p @ p, r @ r - p @ p])
        if all(np.linalg.norm(points[d] - o) >= np.linalg.norm(p - o) - 1e-9 for d in range(len(points)) if d not in (a, b, c)):
            edges |= {(a, b), (a, c), (b, c)}
    return edges


def test_dropping_any_delaunay_edge_leaves_a_query_whose_two_nearest_do_not_meet():
    points = np.array([[0.0, 0.0], [2.0, 0.1], [0.3, 1.9], [2.2, 2.1], [1.05, 0.9]])
    edges = delaunay(points)
    assert len(edges) >= 7
    grid = np.array(list(itertools.product(np.linspace(-3, 5, 161), repeat=2)))
    nearest = np.sort(np.argsort(np.linalg.norm(grid[:, None] - points[None], axis=2), axis=1)[:, :2], axis=1)
    meets = {tuple(map(int, p)) for p in np.unique(nearest, axis=0)}
    # every dropped edge is the pair of nearest points of some query, and other pairs never are
    assert meets == edges
