"""Vicinity graphs around queries and what can be read from them."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..plans.lineage import cut


def extract(truth: DataFrame, edges: DataFrame, size: int) -> DataFrame:
    """(query_id, src_rank, dst_rank): arcs between a query's ``size`` nearest rows, by two equi-joins."""
    near = truth.where(F.col("rank") <= size).select("query_id", "rank", "vec_id")
    arcs = edges.select("src", "dst").distinct()
    left = near.select("query_id", F.col("rank").alias("src_rank"), F.col("vec_id").alias("src"))
    right = near.select("query_id", F.col("rank").alias("dst_rank"), F.col("vec_id").alias("dst"))
    return left.join(arcs, "src").join(right, ["query_id", "dst"]).where("src_rank <> dst_rank").select("query_id", "src_rank", "dst_rank")


def isolated(truth: DataFrame, vicinity: DataFrame, size: int) -> DataFrame:
    """(query_id, n_isolated): ranks without any arc in or out."""
    near = truth.where(F.col("rank") <= size).select("query_id", "rank")
    touched = vicinity.select("query_id", F.col("src_rank").alias("rank")).union(vicinity.select("query_id", F.col("dst_rank").alias("rank"))).distinct()
    lone = near.join(touched, ["query_id", "rank"], "left_anti").groupBy("query_id").agg(F.count(F.lit(1)).alias("n"))
    return near.select("query_id").distinct().join(lone, "query_id", "left").select("query_id", F.coalesce("n", F.lit(0)).alias("n_isolated"))


def mean_reachable(truth: DataFrame, vicinity: DataFrame, size: int, include_self: bool = True) -> DataFrame:
    """(query_id, mean_reachable): points reachable from a random start, on average."""
    arcs = vicinity.groupBy("query_id").agg(F.collect_list(F.array("src_rank", "dst_rank")).alias("arcs"))
    rows = truth.select("query_id").distinct().join(arcs, "query_id", "left")
    less = 0 if include_self else 1

    def run(batches):
        for pdf in batches:
            out = []
            for a in pdf["arcs"]:
                arr = np.array([list(x) for x in a], dtype=np.int64) if a is not None and len(a) else np.zeros((0, 2), dtype=np.int64)
                out.append(float(np.mean(K.reachable_counts(arr, size))) - less)
            yield pd.DataFrame({"query_id": pdf["query_id"], "mean_reachable": out})

    return rows.mapInPandas(run, "query_id bigint, mean_reachable double")


def shape(truth: DataFrame, vicinity: DataFrame, size: int) -> DataFrame:
    """(query_id, n_arcs, n_isolated, strong): strong if every rank reaches every other."""
    counts = vicinity.groupBy("query_id").agg(F.count(F.lit(1)).alias("n_arcs"))
    reach = mean_reachable(truth, vicinity, size)
    return isolated(truth, vicinity, size).join(counts, "query_id", "left").join(reach, "query_id").select("query_id", F.coalesce("n_arcs", F.lit(0)).alias("n_arcs"), "n_isolated", (F.col("mean_reachable") >= size).alias("strong"))


def layout(gaps: DataFrame) -> DataFrame:
    """(query_id, rank, x, y): classical scaling of the distances (query_id, i, j, gap) of a vicinity to the plane."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        n = int(max(pdf["i"].max(), pdf["j"].max()))
        d = np.zeros((n, n))
        d[pdf["i"].to_numpy() - 1, pdf["j"].to_numpy() - 1] = pdf["gap"].to_numpy()
        c = np.eye(n) - 1.0 / n
        w, v = np.linalg.eigh(-0.5 * c @ (d * d) @ c)
        xy = v[:, -2:] * np.sqrt(np.maximum(w[-2:], 0))
        return pd.DataFrame({"query_id": int(pdf["query_id"].iloc[0]), "rank": np.arange(1, n + 1), "x": xy[:, 1], "y": xy[:, 0]})

    return gaps.groupBy("query_id").applyInPandas(run, "query_id bigint, rank int, x double, y double")


def steiner_proxy(truth: DataFrame, vicinity: DataFrame, size: int, k: int) -> DataFrame:
    """(query_id, n_arcs, n_reached): arcs of a greedy tree from the nearest row to the k nearest, and how many of them it reaches.

    A proxy of a Steiner-tree hardness: one number a query, dear where few arcs join its nearest rows.
    """
    arcs = vicinity.groupBy("query_id").agg(F.collect_list(F.array("src_rank", "dst_rank")).alias("arcs"))
    rows = truth.select("query_id").distinct().join(arcs, "query_id", "left")

    def run(batches):
        for pdf in batches:
            out = [K.greedy_tree([] if a is None else a, size, k) for a in pdf["arcs"]]
            yield pd.DataFrame({"query_id": pdf["query_id"], "n_arcs": [x for x, _ in out], "n_reached": [y for _, y in out]})

    return rows.mapInPandas(run, "query_id bigint, n_arcs int, n_reached int")


# --- hardness ----------------------------------------------------------------------


def hardness(truth: DataFrame, vicinity: DataFrame, n_near: int, max_rank: int, early_stop: bool = True) -> DataFrame:
    """(query_id, i, j, h): bottleneck ranks of all pairs of the n_near nearest; 32767 where nothing connects them."""
    arcs = vicinity.groupBy("query_id").agg(F.collect_list(F.array("src_rank", "dst_rank")).alias("arcs"))
    rows = truth.select("query_id").distinct().join(arcs, "query_id", "left")

    def run(batches):
        for pdf in batches:
            out = []
            for query_id, a in zip(pdf["query_id"], pdf["arcs"], strict=True):
                arr = np.array([list(x) for x in a], dtype=np.int64) if a is not None and len(a) else np.zeros((0, 2), dtype=np.int64)
                h = K.bottleneck_ranks(arr, n_near, max_rank, early_stop)
                i, j = np.meshgrid(np.arange(1, n_near + 1), np.arange(1, n_near + 1), indexing="ij")
                out.append(pd.DataFrame({"query_id": query_id, "i": i.ravel(), "j": j.ravel(), "h": h.ravel()}))
            yield pd.concat(out) if out else pd.DataFrame({"query_id": [], "i": [], "j": [], "h": []})

    return rows.mapInPandas(run, "query_id bigint, i int, j int, h int")


def hardness_fixpoint(truth: DataFrame, vicinity: DataFrame, n_near: int, max_rank: int, rounds: int = 30) -> DataFrame:
    """The same rows from a DataFrame fixpoint of (i, j, least bottleneck), as a cross-check."""
    arcs = cut(vicinity.where(F.greatest("src_rank", "dst_rank") <= max_rank).select("query_id", F.col("src_rank").alias("a"), F.col("dst_rank").alias("b")))
    best = cut(arcs.select("query_id", F.col("a").alias("i"), F.col("b").alias("j"), F.greatest("a", "b").alias("h")))
    last = None
    for _ in range(rounds):
        longer = best.join(arcs.withColumnRenamed("a", "j"), ["query_id", "j"]).select("query_id", "i", F.col("b").alias("j"), F.greatest("h", "b").alias("h"))
        best = cut(best.unionByName(longer).groupBy("query_id", "i", "j").agg(F.min("h").alias("h")))
        state = best.agg(F.count(F.lit(1)), F.sum("h")).first()
        if state == last:
            break
        last = state
    ranks = truth.where(F.col("rank") <= n_near).select("query_id", F.col("rank").alias("i"))
    pairs = ranks.join(ranks.withColumnRenamed("i", "j"), "query_id")
    joined = pairs.join(best, ["query_id", "i", "j"], "left")
    return joined.select("query_id", "i", "j", F.when(F.col("i") == F.col("j"), F.col("i")).otherwise(F.coalesce("h", F.lit(K.NEVER))).alias("h"))


def ok_pairs(h: DataFrame, reach_cap: int) -> DataFrame:
    return h.withColumn("ok", F.col("h") <= reach_cap)


def summary(h: DataFrame, reach_cap: int) -> DataFrame:
    """(query_id, max_h, mean_h, n_never, n_bad): hardness of a query; the mean is over pairs that a path connects."""
    finite = F.when(F.col("h") < K.NEVER, F.col("h"))
    return h.groupBy("query_id").agg(F.max("h").alias("max_h"), F.avg(finite).alias("mean_h"), F.count_if(F.col("h") == K.NEVER).alias("n_never"), F.count_if(F.col("h") > reach_cap).alias("n_bad"))
