"""Mending over rounds: order of admission, policies, batches, credit, shards, and the approach mend under a cap."""

import pytest
from pyspark.sql import functions as F

from vecmend.operators import graph as G
from vecmend.operators import mend as M
from vecmend.operators import search as S
from vecmend.operators import truth as T
from vecmend.plans import rounds as R
from vecmend.sources import families as D

INF = 32767


@pytest.fixture(scope="module")
def small(spark, tiny):
    base, q = D.sphere(spark, tiny)
    base, history = R.cut(base.where("vec_id < 120")), R.cut(q.where("role = 'history' and query_id < 60"))
    return base, history, R.cut(G.as_edges(G.knn(base, 3)))


def arcs(edges):
    return {(r.src, r.dst, r.hardness) for r in edges.where("kind = 'extra'").collect()}


def test_equal_tags_of_a_later_round_displace_nothing(spark):
    edges = spark.createDataFrame([(1, 9, "base", 0, 0, -1, -1)], G.EDGES)
    first = M.admit(edges, spark.createDataFrame([(9, 900000, 1, 20, INF, 0.5)], M.PROPOSALS), 1)
    second = M.admit(first, spark.createDataFrame([(2, 200000, 1, 30, INF, 0.5)], M.PROPOSALS), 1)
    assert arcs(second) == {(1, 20, INF)}
    harder = M.admit(M.admit(edges, spark.createDataFrame([(9, 900000, 1, 20, 50, 0.5)], M.PROPOSALS), 1), spark.createDataFrame([(2, 200000, 1, 30, 51, 0.5)], M.PROPOSALS), 1)
    assert arcs(harder) == {(1, 30, 51)}


def test_policies(spark, small):
    base, _, edges = small
    near = G.knn(base, 9).where("rank > 3 and src < 40")
    new = near.select(F.lit(1).cast("bigint").alias("query_id"), "rank", F.col("src"), F.col("dst"), (F.col("rank") * 10).cast("int").alias("hardness"), "dist").withColumn("seq", F.col("rank").cast("bigint")).select("query_id", "seq", "src", "dst", "hardness", "dist")
    with pytest.raises(ValueError, match="mrgn"):
        M.admit(edges, new, 2, "mrgn")
    for policy in M.POLICIES:
        kept = M.admit(edges, new, 2, policy, base=base).where("kind = 'extra'").groupBy("src").count()
        assert kept.agg(F.max("count")).first()[0] <= 2
    thinned = {(a, b) for a, b, _ in arcs(M.admit(edges, new, 2, "mrng", base=base))}
    want = {(r.src, r.dst) for r in G.thinned(new.join(edges, ["src", "dst"], "left_anti"), base, 2).collect()}
    assert thinned == want


def test_batches_of_one_equal_the_queries_one_after_another(small):
    base, history, edges = small
    few = R.cut(history.orderBy("query_id").limit(4))
    passes = [R.Pass(5, 5, 20)]
    step = edges
    for r in few.orderBy("query_id").collect():
        step = R.run(base, step, few.where(F.col("query_id") == r.query_id), passes, 2)
    assert arcs(R.run(base, edges, few, passes, 2, batch=1)) == arcs(step)


def test_numbers_follow_ids_over_partitions(spark):
    ids = spark.range(0, 1000, 3).select((F.col("id") * 7919 % 100003).alias("query_id")).repartition(5)
    rows, n = R.numbered(ids)
    got = [r.query_id for r in rows.orderBy("n").collect()]
    assert n == 334 and got == sorted(got) and {r.n for r in rows.collect()} == set(range(334))
    assert R.numbered(ids.limit(0))[1] == 0


def test_refused_arcs_get_no_credit(small):
    base, history, edges = small
    near = R.cut(T.exact_blocked(base, history, 20))
    tagged = M.admit(edges, M.vicinity(near, edges, base, 5, 5, 20), 1)
    full = R.cut(M.least_tags(tagged, 1))
    assert full.count() > 0
    least = {r.vec_id: r.least for r in full.collect()}
    for r in M.vicinity(near, tagged, base, 5, 5, 20, full=full).collect():
        assert r.hardness > least.get(r.src, -1)


def test_one_and_many_shards_find_the_same_truth(small):
    base, history, _ = small
    many = R.cut(G.with_shards(base, 4))
    own = T.exact_shards(many, history, 10, 4)
    merged = T._ranked(own.select(F.floor(F.col("query_id") / 4).cast("bigint").alias("query_id"), "vec_id", "dist"), 10)
    key = lambda df: {(r.query_id, r.rank, r.vec_id) for r in df.collect()}
    assert key(merged) == key(T.exact_blocked(base, history, 10))
    assert G.shards_for(base) == 1 and {r.shard for r in many.select("shard").distinct().collect()} == {0, 1, 2, 3}


def test_every_history_query_arrives_after_the_mend_of_shards(small):
    base, history, _ = small
    many = R.cut(G.with_shards(base, 3))
    edges = R.run(many, R.cut(G.hnsw(many, 3, 20)), history, R.single(5), None)
    truth = {(r.query_id, r.rank, r.vec_id) for r in T.exact_blocked(base, history, 5).collect()}
    assert {(r.query_id, r.rank, r.vec_id) for r in S.sharded(many, edges, history, 5, 5).collect()} == truth


def test_approach_goes_on_where_arcs_only_change_places(spark):
    # a chain: the walk starts at the mean and stops early; every row may have one extra arc, and has a soft one
    n = 12
    base = spark.createDataFrame([(i, [1.0, i / 4.0]) for i in range(n)], "vec_id bigint, vec array<double>")
    rows = [(i, (i + 1) % 3, "base", 0, 0, -1, -1) for i in range(3)] + [(i, 0, "extra", 0, 3, i, 0) for i in range(n)]
    edges = spark.createDataFrame(rows, G.EDGES)
    queries = spark.createDataFrame([(i, [1.0, i / 4.0 + 0.01]) for i in range(n)], "query_id bigint, vec array<double>")
    truth = T.exact_blocked(base, queries, 1, "l2")
    mended = M.approach(base, edges, queries, truth, 1, 1, 1, "l2")
    before, after = (M.stuck(base, e, queries, truth, 1, 1, "l2").count() for e in (edges, mended))
    assert after < before and mended.where("kind = 'extra'").count() == n


def test_slices_and_sweeps_equal_single_walks(small):
    base, history, edges = small
    one = R.cut(base.withColumn("shard", F.lit(0)))
    key = lambda df: {(r.query_id, r.rank, r.vec_id, r.ndc) for r in df.collect()}
    by_beam = {b: key(S.sharded(one, edges, history, 5, b)) for b in (5, 15)}
    assert key(S.sharded(base, edges, history, 5, 15)) == by_beam[15]
    swept = S.sweep(base, edges, history, 5, [5, 15])
    for b in (5, 15):
        assert key(swept.where(F.col("beam") == b)) == by_beam[b]
    assert S.sharded(base, edges, history, 5, 5).where("us <= 0").isEmpty()
