"""Batch search on a graph index: sharded beam search, round-based search, entry points and filters."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..functions import vectors as V
from ..plans.lineage import cut
from . import graph as G
from . import truth as T

FOUND = "query_id bigint, shard int, vec_id bigint, dist double, ndc bigint, hops int, us double"
#: Queries of a block that one task walks, where the whole index is one shard.
SLICE = 64


def entry_centroid(base: DataFrame, metric: str = "cosine") -> int:
    """Base row nearest to the mean vector; the smallest id wins ties."""
    sums = base.select(F.posexplode("vec").alias("j", "x")).groupBy("j").agg(F.avg("x").alias("x")).orderBy("j").collect()
    center = F.array(*[F.lit(r["x"]) for r in sums])
    return base.select("vec_id", V.distance(F.col("vec"), center, metric).alias("d")).agg(F.min(F.struct("d", "vec_id"))["vec_id"].alias("v")).first()["v"]


def entry_random(base: DataFrame, seed: int = 0) -> int:
    return base.agg(F.min(F.struct(F.xxhash64("vec_id", F.lit(seed)).alias("h"), "vec_id"))["vec_id"].alias("v")).first()["v"]


def packed(base: DataFrame, edges: DataFrame, tombstones: DataFrame | None = None) -> DataFrame:
    """(shard, vec_id, vec, nbrs, layers, dead): adjacency and vectors of the index, one row a vector."""
    sharded = base if "shard" in base.columns else G.with_shards(base, 1)
    lists = edges.groupBy(F.col("src").alias("vec_id")).agg(F.sort_array(F.collect_set(F.struct("layer", "dst"))).alias("nbrs"))
    rows = sharded.select("shard", "vec_id", "vec").join(lists, "vec_id", "left")
    if tombstones is not None:
        rows = rows.join(tombstones.select("vec_id", F.lit(True).alias("dead")), "vec_id", "left").withColumn("dead", F.coalesce("dead", F.lit(False)))
    else:
        rows = rows.withColumn("dead", F.lit(False))
    return rows.select("shard", "vec_id", "vec", F.transform("nbrs", lambda x: x["dst"]).alias("nbrs"), F.transform("nbrs", lambda x: x["layer"]).alias("layers"), "dead")


def _shard_walker(shared, k: int, metric: str, entry: str | int, visited: bool, slices: int = 1, beams: list[int] | None = None):
    """Function that unpacks one shard and walks it for the queries of a broadcast block, or one slice of them; with ``beams`` by each of these."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        from time import perf_counter

        own = pdf["vec_id"].to_numpy()
        by_id = np.argsort(own, kind="stable")
        own = own[by_id]
        mat = K.prepare(np.stack(pdf["vec"].to_numpy()[by_id]), metric)
        none = np.zeros(0, dtype=np.int64)
        nbrs, layers = ([none if x is None else np.asarray(x) for x in pdf[c].to_numpy()[by_id]] for c in ("nbrs", "layers"))
        row, arr, lay = np.repeat(np.arange(len(own)), [len(x) for x in nbrs]), np.concatenate(nbrs).astype(np.int64), np.concatenate(layers)
        del nbrs, layers
        at = np.minimum(np.searchsorted(own, arr), len(own) - 1)
        here_too = own[at] == arr
        out: dict[int, list[np.ndarray]] = {}
        for layer in np.unique(lay).tolist():
            of = here_too & (lay == layer)
            out[int(layer)] = np.split(at[of], np.cumsum(np.bincount(row[of], minlength=len(own)))[:-1])
        del row, arr, lay, at
        zero = out.get(0, [none] * len(own))
        upper = [(out[layer], np.flatnonzero([len(x) > 0 for x in out[layer]])) for layer in sorted((x for x in out if x > 0), reverse=True)]
        dead = pdf["dead"].to_numpy(dtype=bool)[by_id]
        hidden = dead if dead.any() else None
        if isinstance(entry, int):
            start = int(np.searchsorted(own, entry)) if entry in own else 0
        elif entry == "random":
            start = int(np.argmin([hash((v, 7)) for v in own.tolist()]))
        else:
            start = K.medoid(mat, metric)
        here = int(pdf["shard"].iloc[0])
        q_ids, q, own_beams, routes = shared.value
        mine = np.arange(len(q_ids)) if slices == 1 else np.arange(int(pdf["slice"].iloc[0]), len(q_ids), slices)
        n_rows, ids, dist, cost = [], [], [], []
        for n in mine.tolist():
            if routes is not None and here not in routes[n]:
                continue
            vec, began = q[n], perf_counter()
            first, extra = start, 0
            for lists, top in upper:
                if len(top):
                    w = K.walk(lists, mat, vec, 1, [first if len(lists[first]) else int(top[0])], 1, metric)
                    first, extra = int(w.rows[0]), extra + w.ndc
            if beams is not None:
                above = perf_counter() - began
                if hidden is None:
                    walks = K.sweep_walk(zero, mat, vec, k, [first], beams, metric)
                else:
                    walks = []
                    for beam in beams:
                        began = perf_counter()
                        w = K.walk(zero, mat, vec, k, [first], beam, metric, hidden)
                        walks.append((w, perf_counter() - began))
                for i, (w, seconds) in enumerate(walks):
                    n_rows.append(len(w.rows))
                    ids.append(w.rows)
                    dist.append(w.dist)
                    cost.append((q_ids[n] * len(beams) + i, w.ndc + extra, w.hops, 1e6 * (above + seconds)))
                continue
            w = K.walk(zero, mat, vec, k, [first], own_beams[n], metric, hidden)
            took = 1e6 * (perf_counter() - began)
            got = w.seen if visited else w.rows
            n_rows.append(len(got))
            ids.append(got)
            dist.append(K.distances(mat[got], vec, metric) if visited else w.dist)
            cost.append((q_ids[n], w.ndc + extra, w.hops, took))
        if not cost:
            return pd.DataFrame({c: [] for c in ("query_id", "shard", "vec_id", "dist", "ndc", "hops", "us")})
        whose, ndc, hops, us = (np.repeat(np.array(c), n_rows) for c in zip(*cost, strict=True))
        return pd.DataFrame({"query_id": whose, "shard": here, "vec_id": own[np.concatenate(ids)], "dist": np.concatenate(dist), "ndc": ndc, "hops": hops, "us": us})

    return run


def routes(base: DataFrame, queries: DataFrame, probe_shards: int, metric: str = "cosine") -> DataFrame:
    """(query_id, shards): the shards whose mean vectors are nearest to a query."""
    sharded = base if "shard" in base.columns else G.with_shards(base, 1)
    cells = sharded.select("shard", F.posexplode("vec").alias("j", "x")).groupBy("shard", "j").agg(F.avg("x").alias("x"))
    means = cells.groupBy("shard").agg(F.transform(F.sort_array(F.collect_list(F.struct("j", "x"))), lambda c: c["x"]).alias("vec"))
    near = T.exact_blocked(means.select(F.col("shard").cast("bigint").alias("vec_id"), "vec"), queries, probe_shards, metric)
    return near.groupBy("query_id").agg(F.collect_set(F.col("vec_id").cast("int")).alias("shards"))


def sharded(base: DataFrame, edges: DataFrame, queries: DataFrame, k: int, beam: int, metric: str = "cosine", entry: str | int = "centroid", tombstones: DataFrame | None = None, visited: bool = False, beam_col: str | None = None, probe_shards: int | None = None, index: DataFrame | None = None, shards: int | None = None, beams: list[int] | None = None) -> DataFrame:
    """(query_id, rank, vec_id, dist, ndc, hops, us): k nearest of all shards' walks for each query, with evaluations, hops and
    microseconds of the walks alone.

    Query blocks of bounded size are broadcast; each shard is unpacked once for a block and walked
    for each query.  ``visited`` returns every row a walk saw instead of the k best.  ``beam_col`` names a
    column of per-query beams.  ``probe_shards`` walks only the shards whose mean vectors are nearest to a query.
    ``index`` is a packed index kept from before.  A base without a ``shard`` column is one shard, of which
    several tasks walk a share of the queries each.  With ``shards`` each shard's answers are kept apart,
    under the number query_id * shards + shard.  With ``beams`` (without ``visited`` and ``shards``) each query is walked by all of them, under the
    numbers query_id * len(beams) + place.
    """
    index = packed(base, edges, tombstones) if index is None else index
    parts = []
    extra = [beam_col] if beam_col else []
    if probe_shards is not None:
        queries = queries.join(routes(base, queries, probe_shards, metric), "query_id")
        extra.append("shards")
    context = base.sparkSession.sparkContext
    for ids, vecs, more in T.query_blocks(queries, extra):
        own_beams = [int(m[0]) for m in more] if beam_col else [beam] * len(ids)
        routed = [frozenset(m[-1]) for m in more] if probe_shards is not None else None
        shared = context.broadcast((ids, K.prepare(vecs, metric), own_beams, routed))
        slices = 1 if "shard" in base.columns else max(1, min(-(-len(ids) // SLICE), context.defaultParallelism))
        walker = _shard_walker(shared, k, metric, entry, visited, slices, beams)
        if slices == 1:
            parts.append(index.groupBy("shard").applyInPandas(walker, FOUND))
            continue

        def whole(frames, walker=walker):
            held = [f for f in frames if len(f)]
            if held:
                yield walker(pd.concat(held))

        # one shard: each task gets all of it and a share of the block's queries
        copies = index.withColumn("slice", F.explode(F.sequence(F.lit(0), F.lit(slices - 1)))).repartitionById(slices, F.col("slice"))
        parts.append(copies.mapInPandas(whole, FOUND))
    if not parts:
        return base.sparkSession.createDataFrame([], "query_id bigint, rank int, vec_id bigint, dist double, ndc bigint, hops int, us double")
    found = parts[0]
    for p in parts[1:]:
        found = found.unionByName(p)
    if shards is not None:
        found = found.withColumn("query_id", F.col("query_id") * shards + F.col("shard"))
    order = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    found = found.withColumn("rank", F.row_number().over(order))
    # a shard's cost stands on each of its rows; the first one's counts
    once = F.row_number().over(Window.partitionBy("query_id", "shard").orderBy("rank")) == 1
    total = Window.partitionBy("query_id")
    found = found.withColumn("once", once)
    costs = [F.sum(F.when(F.col("once"), F.col(c)).otherwise(0)).over(total).cast(t).alias(c) for c, t in (("ndc", "bigint"), ("hops", "int"), ("us", "double"))]
    best = found.select("query_id", "rank", "vec_id", "dist", *costs)
    return best if visited else best.where(F.col("rank") <= k)


def sweep(base: DataFrame, edges: DataFrame, queries: DataFrame, k: int, beams: list[int], metric: str = "cosine", **how) -> DataFrame:
    """(beam, query_id, rank, ...): ``sharded`` for several beams in one pass over the index, and one walk a query."""
    n = len(beams)
    found = sharded(base, edges, queries.select("query_id", "vec"), k, k, metric, beams=beams, **how)
    at = F.get(F.array(*[F.lit(b) for b in beams]), F.pmod("query_id", F.lit(n)).cast("int"))
    return found.withColumn("beam", at).withColumn("query_id", F.floor(F.col("query_id") / n).cast("bigint"))


def rounds(base: DataFrame, edges: DataFrame, queries: DataFrame, k: int, beam: int, entry: int, metric: str = "cosine", max_rounds: int = 200) -> DataFrame:
    """The same search with one Spark round a hop and one pop a query and round: the semantic cross-check."""
    arcs = cut(edges.where("layer = 0").select("src", "dst").distinct())
    vecs = base.select("vec_id", "vec")
    q = queries.select("query_id", F.col("vec").alias("qvec"))
    start = vecs.where(F.col("vec_id") == entry).join(q, how="cross")
    held = cut(start.select("query_id", "vec_id", V.distance(F.col("vec"), F.col("qvec"), metric).alias("dist"), F.lit(False).alias("done")))
    seen = held.select("query_id", "vec_id")
    nearest_open = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    for _ in range(max_rounds):
        # a popped row is always within the kept rows, since what falls out of the beam is never expanded
        pop = held.where("not done").withColumn("r", F.row_number().over(nearest_open)).where("r = 1").select("query_id", F.col("vec_id").alias("src"))
        if pop.isEmpty():
            break
        fresh = pop.join(arcs, "src").select("query_id", F.col("dst").alias("vec_id")).distinct().join(seen, ["query_id", "vec_id"], "left_anti")
        placed = fresh.join(vecs, "vec_id").join(q, "query_id").select("query_id", "vec_id", V.distance(F.col("vec"), F.col("qvec"), metric).alias("dist"), F.lit(False).alias("done"))
        placed = cut(placed)
        popped = pop.select("query_id", F.col("src").alias("vec_id"), F.lit(True).alias("now"))
        held = held.join(popped, ["query_id", "vec_id"], "left").select("query_id", "vec_id", "dist", (F.col("done") | F.coalesce("now", F.lit(False))).alias("done"))
        held = cut(held.unionByName(placed).withColumn("r", F.row_number().over(nearest_open)).where(F.col("r") <= beam).drop("r"))
        seen = cut(seen.unionByName(placed.select("query_id", "vec_id")))
    return held.withColumn("rank", F.row_number().over(nearest_open)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "dist")


def filtered(base: DataFrame, edges: DataFrame, queries: DataFrame, predicate, k: int, beam: int, metric: str = "cosine", mode: str = "post") -> DataFrame:
    """Search among rows that fulfil a predicate: by brute force over them (``pre``), or walking all and hiding the rest (``post``)."""
    if mode == "pre":
        return T.exact_blocked(base.where(predicate), queries, k, metric)
    hidden = base.where(~predicate).select("vec_id")
    return sharded(base, edges, queries, k, beam, metric, tombstones=hidden)


def min_beam(base: DataFrame, edges: DataFrame, queries: DataFrame, wanted: DataFrame, beams: list[int], metric: str = "cosine", entry: str | int = "centroid") -> DataFrame:
    """(query_id, vec_id, beam): smallest of the beams whose walk holds a wanted row (query_id, vec_id); null where none does."""
    pairs = wanted.select("query_id", "vec_id").distinct()
    held = None
    for beam in sorted(beams):
        found = sharded(base, edges, queries, beam, beam, metric, entry).select("query_id", "vec_id", F.lit(beam).alias("beam"))
        held = found if held is None else held.unionByName(found)
    least = held.join(pairs, ["query_id", "vec_id"]).groupBy("query_id", "vec_id").agg(F.min("beam").alias("beam"))
    return pairs.join(least, ["query_id", "vec_id"], "left")
