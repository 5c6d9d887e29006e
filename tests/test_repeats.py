"""Logs that repeat: a vector is reckoned, walked and answered once, and all queries are counted."""

import pytest
from pyspark.sql import functions as F

from vecmend import catalog
from vecmend.functions import vectors as V
from vecmend.operators import search as S
from vecmend.operators import truth as T
from vecmend.plans import experiments as X
from vecmend.sources import families as D


def test_a_norm_is_not_found_again_for_each_coordinate(spark):
    df = spark.createDataFrame([(1, [3.0, 4.0]), (2, [0.0, 0.0])], "vec_id bigint, v array<double>").select("vec_id", V.normalise(V.add(F.col("v"), F.col("v"))).alias("u"))
    assert {r.vec_id: list(r.u) for r in df.collect()} == {1: [6 * (1 / 10), 8 * (1 / 10)], 2: [0.0, 0.0]}
    assert df._jdf.queryExecution().optimizedPlan().toString().count("zip_with") <= 2  # the sum, and its norm


def test_the_log_reckons_a_vector_once_for_its_repeats(spark, tiny):
    plan = D.event_log(spark, tiny)[1]._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Join") < plan.index("zip_with")  # below the join with the events


@pytest.fixture
def repeated(spark, tiny, monkeypatch):
    base, q = D.event_log(spark, tiny)
    six = q.where("query_id < 60").withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(5)))).withColumn("query_id", F.col("query_id") + 1000 * F.col("i")).drop("i").localCheckpoint()
    monkeypatch.setattr(D, "event_log", lambda *_: (base, six))
    return six


@pytest.mark.parametrize("name", ("cache_hybrid", "cache_latency"))
def test_equal_queries_are_asked_once_and_all_counted(spark, tiny, monkeypatch, repeated, name):
    asked = []
    for where, what in ((T, "exact_blocked"), (S, "sharded")):
        def seen(base, a, *rest, plain=getattr(where, what), **how):
            asked.append((rest[0] if hasattr(rest[0], "columns") else a).count())
            return plain(base, a, *rest, **how)

        monkeypatch.setattr(where, what, seen)
    rows = X.WORKLOADS[name](spark, tiny).collect()
    halves = repeated.agg(F.percentile(F.unix_timestamp("ts"), 0.5)).first()[0]
    assert sum(r.n for r in rows) == (360 if name == "cache_latency" else repeated.where(F.unix_timestamp("ts") > halves).count())
    assert asked and max(asked) <= 60


def test_repeats_are_counted_whole(spark, tiny, repeated):
    assert catalog.QUERIES["cache_repeats"](spark, tiny).first().n == 360
