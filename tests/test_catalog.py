"""Registered queries against their SQL on the smallest tables, and invariants of mending and upkeep."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from vecmend import catalog
from vecmend.operators import graph as G
from vecmend.operators import mend as M
from vecmend.operators import search as S
from vecmend.operators import upkeep as U

CHECKED = ["vec_profile", "knn_cosine", "knn_blocked_l2", "graph_mrng", "graph_tau_thinned", "vicinity_edges", "hardness_matrix", "mend_frozen", "admit_cap", "refresh_drop", "containment", "augment_noise", "search_history_after_mend"]


@pytest.fixture(scope="module")
def oracle(tiny):
    con = duckdb.connect()
    for name in os.listdir(tiny):
        con.execute(f"CREATE VIEW {name[:-8]} AS SELECT * FROM '{tiny}/{name}'")
    return con


def plain(v):
    return round(v, 6) + 0.0 if isinstance(v, float) else v


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_its_sql(spark, tiny, oracle, name):
    df = catalog.QUERIES[name](spark, tiny)
    cur = oracle.execute(catalog.ORACLE_SQL[name])
    cols = [c[0] for c in cur.description]
    assert sorted(cols) == sorted(df.columns)
    want = sorted(repr([plain(r[cols.index(c)]) for c in df.columns]) for r in cur.fetchall())
    assert sorted(repr([plain(v) for v in r]) for r in df.collect()) == want


def test_registry_has_sql_only_for_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_full_cap_keeps_the_hardest_and_the_first(spark):
    edges = spark.createDataFrame([(1, 9, "base", 0, 0, -1, -1)], G.EDGES)
    tags = [5, 9, 7, 9, 32767]
    new = spark.createDataFrame([(0, n, 1, 10 + n, h, 0.5) for n, h in enumerate(tags)] + [(0, 9, 1, 9, 99, 0.5)], M.PROPOSALS)
    for parts in (1, 5):
        kept = M.admit(edges, new.repartition(parts), 2)
        assert {(r.dst, r.hardness) for r in kept.where("kind = 'extra'").collect()} == {(14, 32767), (11, 9)}
        assert kept.where("kind = 'base'").count() == 1


def test_refresh_resets_tags_and_purge_leaves_no_trace(spark):
    edges = spark.createDataFrame([(1, d, "extra", 0, 7, d, 0) for d in range(10)] + [(2, 1, "base", 0, 0, -1, -1)], G.EDGES)
    kept = U.refresh_drop(edges, 0.3)
    assert kept.where("kind = 'extra'").count() == 7 and kept.where("kind = 'extra' and hardness <> 0").isEmpty()
    dead = spark.createDataFrame([(1,)], "vec_id bigint")
    assert U.purge(edges, dead).isEmpty()


def test_transport_cost_is_zero_for_one_set_and_the_shift_for_a_moved_one(spark):
    a = spark.createDataFrame([(i, [i / 10, 0.0]) for i in range(20)], "query_id bigint, vec array<double>")
    moved = a.select("query_id", F.array(F.col("vec")[0], F.col("vec")[1] + 3.0).alias("vec"))
    assert U.sinkhorn(a, a, blur=0.005).first().distance < 0.02
    assert abs(U.sinkhorn(a, moved, blur=0.005).first().distance - 3.0) < 0.02
    assert U.sinkhorn(a, a.limit(0)).first().distance is None
    assert all(r.distance == 0 for r in U.sliced_wasserstein(a, a, 3).collect())


def test_training_queries_fill_history_without_repeats(spark):
    schema = "query_id bigint, vec array<double>"
    history = spark.createDataFrame([(1, [1.0, 0.0]), (2, [0.0, 1.0])], schema)
    training = spark.createDataFrame([(9, [0.0, 1.0]), (8, [0.6, 0.8])], schema)
    assert {(r.query_id, r.origin) for r in U.from_training(history, training).collect()} == {(1, "history"), (2, "history"), (8, "training")}


def test_smallest_beam_is_null_where_no_walk_arrives(spark):
    base = spark.createDataFrame([(i, [1.0, i / 10]) for i in range(4)], "vec_id bigint, vec array<double>")
    edges = spark.createDataFrame([(0, 1, "base", 0, 0, -1, -1), (1, 2, "base", 0, 0, -1, -1)], G.EDGES)
    query = spark.createDataFrame([(5, [1.0, 0.2])], "query_id bigint, vec array<double>")
    wanted = spark.createDataFrame([(5, 2), (5, 3)], "query_id bigint, vec_id bigint")
    assert {(r.vec_id, r.beam) for r in S.min_beam(base, edges, query, wanted, [1, 3], entry=0).collect()} == {(2, 1), (3, None)}
