"""Vicinity mend, its alternatives, subset mend, approach mend, and admission of arcs under a degree cap."""

from __future__ import annotations

from functools import reduce
from itertools import count

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions import vectors as V
from ..plans.lineage import cut
from . import graph as G
from . import search as S
from . import truth as T
from . import vicinity as N

PROPOSALS = "query_id bigint, seq bigint, src bigint, dst bigint, hardness int, dist double"


def vicinity(truth: DataFrame, edges: DataFrame, base: DataFrame, n_near: int, reach_cap: int, max_rank: int, metric: str = "cosine", method: str = "vicinity", seed: int = 0, full: DataFrame | None = None) -> DataFrame:
    """Proposed arcs (query_id, seq, src, dst, hardness, dist) of each history query against one frozen graph.

    Methods: ``vicinity`` (shortest bad pairs first), ``random`` (bad pairs in hash order), ``rng`` (the relative
    neighbourhood graph of the near set, laid over).  A task holds one query's vicinity: at most max_rank ranks
    and their arcs, and n_near vectors; queries without a bad pair propose nothing.

    An arc that a full row will turn away still counts as laid when the rest is chosen.  With ``full`` (``least_tags``) it does not:
    such an arc is passed over, and other arcs may connect its pair.
    """
    arcs = N.extract(truth, edges, max_rank).groupBy("query_id").agg(F.collect_list(F.array("src_rank", "dst_rank")).alias("arcs"))
    placed = truth.where(F.col("rank") <= n_near).join(base.select("vec_id", "vec"), "vec_id")
    placed = placed.withColumn("least", F.lit(-1)) if full is None else placed.join(full, "vec_id", "left").withColumn("least", F.coalesce("least", F.lit(-1)))
    near = placed.groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct("rank", "vec_id", "vec", "least"))).alias("near"))
    rows = near.join(arcs, "query_id", "left")
    refuse = full is not None

    def run(batches):
        for pdf in batches:
            out = []
            for query_id, group, a in zip(pdf["query_id"], pdf["near"], pdf["arcs"], strict=True):
                ids = np.array([x["vec_id"] for x in group], dtype=np.int64)
                x = K.prepare(np.array([list(r["vec"]) for r in group]), metric)
                gaps = K.all_distances(x, x, metric)
                arr = np.array([list(p) for p in a], dtype=np.int64) if a is not None and len(a) else np.zeros((0, 2), dtype=np.int64)
                h = K.bottleneck_ranks(arr, len(ids), max_rank)
                if method == "rng":
                    have = {(int(p) - 1, int(q) - 1) for p, q in arr}
                    new = [(s, t, int(h[s, t])) for s, t in K.lune_arcs(gaps) if (s, t) not in have]
                else:
                    least = [r["least"] for r in group]
                    takes = (lambda s, t, tag, least=least: tag > least[s]) if refuse else None
                    new = K.mend_pairs(h, gaps, reach_cap, "random" if method == "random" else "length", seed, takes)
                for n, (s, t, tag) in enumerate(new):
                    out.append((query_id, query_id * 100000 + n, ids[s], ids[t], tag, gaps[s, t]))
            yield pd.DataFrame(out, columns=["query_id", "seq", "src", "dst", "hardness", "dist"])

    return rows.mapInPandas(run, PROPOSALS)


def least_tags(edges: DataFrame, extra_cap: int) -> DataFrame:
    """(vec_id, least): the least tag of each row that has as many extra arcs as it may."""
    own = edges.where("kind = 'extra'").groupBy(F.col("src").alias("vec_id")).agg(F.count(F.lit(1)).alias("n"), F.min("hardness").alias("least"))
    return own.where(F.col("n") >= extra_cap).select("vec_id", "least")


POLICIES = ("hardness", "random", "mrng")


def admit(edges: DataFrame, proposals: DataFrame, extra_cap: int | None, policy: str = "hardness", seed: int = 0, base: DataFrame | None = None, metric: str = "cosine") -> DataFrame:
    """The graph after admission: base arcs untouched, at most ``extra_cap`` extra arcs out of a row.

    ``hardness`` keeps the hardest arcs and, among equals, the earliest by epoch and then by place; this is what replacing the
    least hard arc by a strictly harder one gives, over any number of rounds and in any order within one.  An arc proposed twice keeps its
    largest tag and first place; a copy of a base arc is dropped.  The window limit is applied before the shuffle, so a hub
    sends few rows.  ``random`` keeps arcs in hash order, ``mrng`` thins them monotonely (and reads the vectors of ``base``).
    """
    if policy not in POLICIES:
        raise ValueError(f"unknown policy {policy!r}; there are {', '.join(POLICIES)}")
    own = edges.where("kind = 'base'")
    extra = edges.where("kind = 'extra'").select("src", "dst", "hardness", "epoch", "seq")
    epoch = (edges.agg(F.max("epoch")).first()[0] or 0) + 1
    both = extra.unionByName(proposals.select("src", "dst", "hardness", F.lit(epoch).alias("epoch"), "seq"))
    new = both.groupBy("src", "dst").agg(F.max("hardness").alias("hardness"), F.min(F.struct("epoch", "seq")).alias("at")).join(own.select("src", "dst"), ["src", "dst"], "left_anti")
    if extra_cap is not None and policy == "mrng":
        new = new.join(G.thinned(new, base, extra_cap, metric), ["src", "dst"], "left_semi")
    elif extra_cap is not None:
        order = [F.xxhash64("src", "dst", F.lit(seed))] if policy == "random" else [F.desc("hardness"), F.col("at"), F.col("dst")]
        new = new.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(*order))).where(F.col("r") <= extra_cap).drop("r")
    return own.unionByName(new.select("src", "dst", F.lit("extra").alias("kind"), F.lit(0).alias("layer"), "hardness", F.col("at.seq").alias("seq"), F.col("at.epoch").alias("epoch")))


def subset_truth(truth: DataFrame, k: int, widen: int = 2, draws: int = 10, seed: int = 0) -> DataFrame:
    """Pseudo truth of random k-subsets of each query's widen*k nearest: members in order of distance, then the rest."""
    wide = truth.where(F.col("rank") <= widen * k).withColumn("draw", F.explode(F.sequence(F.lit(0), F.lit(draws - 1))))
    h = F.xxhash64("query_id", "draw", "vec_id", F.lit(seed))
    chosen = wide.withColumn("c", F.row_number().over(Window.partitionBy("query_id", "draw").orderBy(h, "vec_id")))
    order = Window.partitionBy("query_id", "draw").orderBy(F.col("c") > k, "rank")
    return chosen.withColumn("r", F.row_number().over(order)).select((F.col("query_id") * 1000 + F.col("draw")).alias("query_id"), F.col("r").alias("rank"), "vec_id", "dist")


# --- approach mend -----------------------------------------------------------------


def stuck(base: DataFrame, edges: DataFrame, queries: DataFrame, truth: DataFrame, n_near: int, arrive_beam: int, metric: str = "cosine", entry: str | int = "centroid") -> DataFrame:
    """(query_id, stop, stop_dist): history queries whose walk ends farther away than their n_near-th neighbour."""
    ends = _walked(base, edges, queries, 1, arrive_beam, metric, entry).select("query_id", F.col("vec_id").alias("stop"), F.col("dist").alias("stop_dist"))
    bound = truth.where(F.col("rank") == n_near).select("query_id", F.col("dist").alias("bound"))
    return ends.join(bound, "query_id").where(F.col("stop_dist") > F.col("bound") + 1e-12).select("query_id", "stop", "stop_dist")


def _walked(base: DataFrame, edges: DataFrame, queries: DataFrame, k: int, beam: int, metric: str, entry: str | int, **how) -> DataFrame:
    """Walks of queries that stand once for each shard (column ``shard``), each in its own, or of plain ones."""
    if "shard" not in queries.columns:
        return S.sharded(base, edges, queries, k, beam, metric, entry, **how)
    shards = T.shard_count(base)
    one = queries.select(F.floor(F.col("query_id") / shards).cast("bigint").alias("query_id"), "vec").dropDuplicates(["query_id"])
    return S.sharded(base, edges, one, k, beam, metric, entry, shards=shards, **how).join(queries.select("query_id"), "query_id", "left_semi")


def approach_candidates(base: DataFrame, edges: DataFrame, queries: DataFrame, stops: DataFrame, metric: str = "cosine", mode: str = "exact", beam: int = 100, entry: str | int = "centroid") -> DataFrame:
    """(query_id, stop, vec_id): rows nearer to the query than where its walk stopped, from the whole base or those a wider walk saw."""
    own = ["shard"] if "shard" in queries.columns else []
    asked = queries.join(stops, "query_id").select("query_id", "vec", "stop", "stop_dist", *own)
    if mode == "visited":
        seen = _walked(base, edges, asked.select("query_id", "vec", *own), 1, beam, metric, entry, visited=True)
        return seen.join(stops, "query_id").where(F.col("dist") < F.col("stop_dist")).select("query_id", "stop", "vec_id")
    pairs = T.nearer(base, asked.select("query_id", "vec", F.col("stop_dist").alias("bound"), *own), metric)
    return pairs.join(stops.select("query_id", "stop"), "query_id").where("vec_id <> stop").select("query_id", "stop", "vec_id")


def approach_arcs(base: DataFrame, cands: DataFrame, cap: int, metric: str = "cosine") -> DataFrame:
    """Thinned arcs out of the stop points, with the tag of a pair that nothing connects."""
    placed = cands.join(base.select("vec_id", F.col("vec").alias("v")), "vec_id").join(base.select(F.col("vec_id").alias("stop"), F.col("vec").alias("o")), "stop")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x, o = K.prepare(np.stack(pdf["v"].to_numpy()), metric), K.prepare(np.stack(pdf["o"].to_numpy()[:1]), metric)[0]
        kept, dist = K.thin_exact(o, x, pdf["vec_id"].to_numpy(), metric, cap)
        q = int(pdf["query_id"].iloc[0])
        return pd.DataFrame({"query_id": q, "seq": 10**15 + q * 1000 + np.arange(len(kept)), "src": pdf["stop"].to_numpy()[kept], "dst": pdf["vec_id"].to_numpy()[kept], "hardness": K.NEVER, "dist": dist})

    return placed.groupBy("query_id").applyInPandas(run, PROPOSALS)


def approach_direct(base: DataFrame, queries: DataFrame, stops: DataFrame, cap: int, metric: str = "cosine") -> DataFrame:
    """``approach_arcs`` of the exact ``approach_candidates``, without a row for each candidate: a walk that stops far away has most of the base.

    A task holds a shard, or one of several copies of a base that is one shard, and thins a share of the queries one after the other.
    """
    own = ["shard"] if "shard" in queries.columns else []
    asked = queries.join(stops, "query_id").select("query_id", "vec", "stop", "stop_dist", *own)
    context, parts = base.sparkSession.sparkContext, []

    def thinner(shared, slices):
        def run(pdf: pd.DataFrame) -> pd.DataFrame:
            q_ids, q, stop, bound, shards = shared.value
            pdf = pdf.sort_values("vec_id")
            ids, x = pdf["vec_id"].to_numpy(), K.prepare(np.stack(pdf["vec"].to_numpy()), metric)
            mine = np.arange(int(pdf["slice"].iloc[0]), len(q_ids), slices) if shards is None else np.flatnonzero(shards == int(pdf["shard"].iloc[0]))
            out, sq, step = [], (x * x).sum(1), max(1, K.CELLS // len(x))
            for i in range(0, len(mine), step):
                some = mine[i : i + step]
                d, off = K.rough_distances(q[some], x, metric, sq)
                for n, near, e in zip(some.tolist(), d, off.tolist(), strict=True):
                    limit = bound[n] * abs(bound[n]) if metric == "l2" else bound[n]
                    rows = np.flatnonzero(near <= limit + e)
                    edge = np.flatnonzero(near[rows] >= limit - e)
                    sure = np.ones(len(rows), dtype=bool)
                    sure[edge] = K.exact_distances(q, np.full(len(edge), n), x, rows[edge], metric) < bound[n]
                    at = int(np.searchsorted(ids, stop[n]))
                    rows = rows[sure & (rows != at)]
                    kept, dist = K.thin_exact(x[at], x[rows], ids[rows], metric, cap)
                    out.append(pd.DataFrame({"query_id": q_ids[n], "seq": 10**15 + q_ids[n] * 1000 + np.arange(len(kept)), "src": stop[n], "dst": ids[rows[kept]], "hardness": K.NEVER, "dist": dist}))
            return pd.concat(out) if out else pd.DataFrame({c.split()[0]: [] for c in PROPOSALS.split(", ")})

        return run

    for ids, vecs, more in T.query_blocks(asked, ["stop", "stop_dist", *own]):
        columns = [np.array([m[i] for m in more]) for i in range(2 + len(own))]
        shared = context.broadcast((ids, K.prepare(vecs, metric), *columns[:2], columns[2] if own else None))
        if own:
            parts.append(base.select("shard", "vec_id", "vec").groupBy("shard").applyInPandas(thinner(shared, 1), PROPOSALS))
            continue
        slices = max(1, min(-(-len(ids) // S.SLICE), context.defaultParallelism))
        run = thinner(shared, slices)

        def whole(frames, run=run):
            held = [f for f in frames if len(f)]
            if held:
                yield run(pd.concat(held))

        copies = base.select("vec_id", "vec").withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(slices - 1)))).repartitionById(slices, F.col("slice"))
        parts.append(copies.mapInPandas(whole, PROPOSALS))
    return reduce(DataFrame.unionByName, parts) if parts else base.sparkSession.createDataFrame([], PROPOSALS)


def approach(base: DataFrame, edges: DataFrame, queries: DataFrame, truth: DataFrame, n_near: int, arrive_beam: int | None = None, extra_cap: int | None = None, metric: str = "cosine", mode: str = "exact", max_iter: int | None = None) -> DataFrame:
    """Repeat detection over all history and mending until no walk is stuck or nothing more is admitted.

    This ends: an arc admitted here has the largest tag, and later ones of that tag do not push it out.
    """
    beam = arrive_beam or n_near
    for _ in count() if max_iter is None else range(max_iter):
        stops = cut(stuck(base, edges, queries, truth, n_near, beam, metric))
        if stops.isEmpty():
            break
        cap = extra_cap or 1 << 30
        arcs = approach_direct(base, queries, stops, cap, metric) if mode == "exact" else approach_arcs(base, approach_candidates(base, edges, queries, stops, metric, mode), cap, metric)
        before, edges = edges, cut(admit(edges, arcs, extra_cap))
        # under a cap one arc may push out another, so their number says nothing
        if edges.join(before, ["src", "dst", "kind", "hardness"], "left_anti").isEmpty():
            break
    return edges
