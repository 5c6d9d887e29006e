"""Base graphs and baselines, one graph a shard.

Shards are bounded sets of vectors; a kernel builds each shard's graph in one
grouped stage, and graphs of different shards are independent.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import kernels as K
from ..plans.lineage import cut
from . import truth as T

#: ``epoch`` is the round of admission that an extra arc came in by, ``seq`` its place in that round.
EDGES = "src bigint, dst bigint, kind string, layer int, hardness int, seq bigint, epoch int"


#: Bytes of vectors and arcs that one task should hold, and arcs a vector that are reckoned with.
SHARD_BYTES, ARCS = 256 << 20, 64


def shards_for(base: DataFrame) -> int:
    """Shards that keep each within ``SHARD_BYTES``, from the rows and their dimension."""
    row = base.agg(F.count(F.lit(1)).alias("n"), F.max(F.size("vec")).alias("d")).first()
    return -(-(row["n"] or 0) * (8 * (row["d"] or 0) + 16 * ARCS) // SHARD_BYTES) or 1


def with_shards(base: DataFrame, shards: int | None = None) -> DataFrame:
    """Hash shards, as many as given or as the size of the base asks for."""
    shards = shards_for(base) if shards is None else shards
    return base.withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int"))


def _built(base: DataFrame, build) -> DataFrame:
    """Edges of a kernel ``build(ids, vectors) -> [(layer, lists)]`` run on each shard."""
    sharded = base if "shard" in base.columns else with_shards(base, 1)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("vec_id")
        ids = pdf["vec_id"].to_numpy()
        parts = []
        for layer, lists in build(ids, np.stack(pdf["vec"].to_numpy())):
            n = [len(x) for x in lists]
            src, dst = np.repeat(ids, n), ids[np.concatenate(lists).astype(np.int64)] if sum(n) else np.zeros(0, dtype=np.int64)
            parts.append(pd.DataFrame({"src": src, "dst": dst, "kind": "base", "layer": layer, "hardness": 0, "seq": -1, "epoch": -1}))
        return pd.concat(parts)

    return sharded.select("shard", "vec_id", "vec").groupBy("shard").applyInPandas(run, EDGES)


# --- one shard, built by several tasks --------------------------------------------------

#: Rows of a shard that a task builds at least; a base of no more is built by one task.
TASK_ROWS = 2048
LISTS = "vec_id bigint, nbrs array<bigint>"


def tasks_for(base: DataFrame) -> int:
    """Tasks that build a base together: one where it has shards, which are built side by side, or is small."""
    if "shard" in base.columns:
        return 1
    return max(1, min(base.count() // TASK_ROWS, base.sparkSession.sparkContext.defaultParallelism))


def _step(base: DataFrame, lists: DataFrame | None, kernel: Callable, tasks: int, whole: bool = False) -> DataFrame:
    """(vec_id, nbrs) from ``kernel(ids, vectors, lists, own) -> (row, its list)``, in row numbers by order of vec_id.

    Each task holds all vectors and gives the lists of a share of the rows; it is handed the earlier lists of its own rows, or with
    ``whole`` those of all.
    """
    rows = base.select("vec_id", "vec")
    rows = rows.withColumn("nbrs", F.lit(None).cast("array<bigint>")) if lists is None else rows.join(lists, "vec_id", "left")
    rows = rows.withColumn("task", F.explode(F.sequence(F.lit(0), F.lit(tasks - 1)))).withColumn("mine", F.pmod(F.xxhash64("vec_id"), F.lit(tasks)) == F.col("task"))
    rows = rows if whole else rows.withColumn("nbrs", F.when(F.col("mine"), F.col("nbrs")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        t = pa.Table.from_batches(held).combine_chunks()
        ids, vecs, nbrs = t["vec_id"].to_numpy(), t["vec"].chunk(0), t["nbrs"].chunk(0)
        order = np.argsort(ids, kind="stable")
        x = vecs.flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1)[order]
        ids, mine = ids[order], t["mine"].to_numpy()[order]
        at = np.searchsorted(ids, nbrs.flatten().to_numpy(zero_copy_only=False)).astype(np.int64)
        ends = np.cumsum(nbrs.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))
        parts = np.split(at, ends[:-1])
        own = np.flatnonzero(mine)
        del held, t, vecs, nbrs
        got: list[tuple[int, np.ndarray]] = []

        def sent() -> pa.RecordBatch:
            lists = pa.ListArray.from_arrays(np.concatenate([[0], np.cumsum([len(v) for _, v in got])]).astype(np.int32), pa.array(ids[np.concatenate([v for _, v in got]).astype(np.int64)]))
            return pa.RecordBatch.from_arrays([pa.array(ids[[u for u, _ in got]]), lists], names=["vec_id", "nbrs"])

        for pair in kernel(ids, x, [parts[i] for i in order.tolist()], own):
            got.append(pair)
            if len(got) == 4096:
                yield sent()
                got.clear()
        if got:
            yield sent()

    return cut(rows.repartitionById(tasks, F.col("task")).select("vec_id", "vec", "nbrs", "mine").mapInArrow(run, LISTS))


def _both_ways(lists: DataFrame) -> DataFrame:
    """Lists with their reverse arcs, in order of vec_id."""
    arcs = lists.select(F.col("vec_id").alias("src"), F.explode("nbrs").alias("dst"))
    return symmetrize(arcs).groupBy(F.col("src").alias("vec_id")).agg(F.sort_array(F.collect_list("dst")).alias("nbrs"))


def _symmetric(base: DataFrame, lists: DataFrame, metric: str, cap: int, tasks: int, slack: float = 0.0) -> DataFrame:
    def kernel(ids, x, lists, own):
        x = K.prepare(x, metric)
        return ((u, K.capped(u, lists[u], x, metric, cap, slack)) for u in own.tolist())

    return _step(base, _both_ways(lists), kernel, tasks)


def _grown(base: DataFrame, lists: DataFrame, metric: str) -> DataFrame:
    def kernel(ids, x, lists, own):
        x = K.prepare(x, metric)
        return enumerate(K.grow_tree(lists, x, K.medoid(x, metric), metric))

    return _step(base, lists, kernel, 1)


def _edges_of(lists: DataFrame) -> DataFrame:
    return as_edges(lists.select(F.col("vec_id").alias("src"), F.explode("nbrs").alias("dst")))


def hnsw(base: DataFrame, m: int = 6, ef: int = 100, metric: str = "cosine", layers: bool = False) -> DataFrame:
    """Navigable small-world graph: its bottom layer alone, or with upper layers (levels by hash)."""
    if (tasks := tasks_for(base)) == 1:
        return _built(base, lambda ids, x: K.layered(K.prepare(x, metric), ids, m, min(ef, len(ids) - 1), metric, layers))

    def kernel(ids, x, _, own):
        x, most = K.prepare(x, metric), min(ef, len(ids) - 1)
        return ((u, K.thin_rows(u, c, x, metric, m)) for i in range(0, len(own), 4096) for u, c in zip(own[i : i + 4096].tolist(), K.knn_lists(x, ids, most, metric, of=own[i : i + 4096]), strict=True))

    bottom = _edges_of(_symmetric(base, _step(base, None, kernel, tasks), metric, 2 * m, tasks))
    return bottom if not layers else bottom.unionByName(_built(base, lambda ids, x: K.upper_layers(K.prepare(x, metric), ids, m, min(ef, len(ids) - 1), metric)))


def nsg(base: DataFrame, c: int = 60, beam: int = 60, r: int = 16, metric: str = "cosine", slack: float = 0.0) -> DataFrame:
    """Spreading-out graph navigated from the medoid."""
    if (tasks := tasks_for(base)) == 1:
        return _built(base, lambda ids, x: [(0, K.spreading(K.prepare(x, metric), ids, c, beam, r, metric, slack)[0])])

    def near(ids, x, _, own):
        return zip(own.tolist(), K.knn_lists(K.prepare(x, metric), ids, min(c, max(len(ids) - 1, 1)), metric, of=own), strict=True)

    def spread(ids, x, knn, own):
        x = K.prepare(x, metric)
        root = K.medoid(x, metric)
        return ((u, K.spread_row(u, knn, x, root, c, beam, r, metric, slack)) for u in own.tolist())

    lists = _step(base, _step(base, None, near, tasks), spread, tasks, whole=True)
    return _edges_of(_grown(base, _symmetric(base, lists, metric, r, tasks, slack), metric))


def tau_mng(base: DataFrame, tau: float = 0.01, c: int = 60, beam: int = 60, r: int = 16, metric: str = "cosine") -> DataFrame:
    """Monotone graph with the pruning relaxed by three times tau."""
    return nsg(base, c, beam, r, metric, tau)


def query_bridge(base: DataFrame, history: DataFrame, n_near: int = 20, m: int = 10, beam: int = 60, metric: str = "cosine", history_limit: int | None = None, block_bytes: int = T.BLOCK_BYTES) -> DataFrame:
    """Bridge baseline from all history queries, or the first ``history_limit``; a worker holds one block of them at a time."""
    rows = history.orderBy("query_id").limit(history_limit) if history_limit is not None else history
    context = base.sparkSession.sparkContext
    shared = [context.broadcast(vecs) for _, vecs, _ in T.query_blocks(rows, block_bytes=block_bytes)]

    def blocks():
        for block in shared:
            yield K.prepare(block.value, metric)
            block.__dict__.pop("_value", None)  # it is read from its file again where another shard needs it

    if (tasks := tasks_for(base)) == 1:
        return _built(base, lambda ids, x: [(0, K.query_bridge(K.prepare(x, metric), ids, blocks(), min(n_near, len(ids)), m, beam, metric))])

    def pairs(ids, x, _, own):
        # a task takes a share of each block; a row may get candidates from several
        x, share = K.prepare(x, metric), TaskContext.get().partitionId()
        for block in blocks():
            found = K.bridge_pairs(x, ids, block[share::tasks], min(n_near, len(ids)), metric)
            first = np.flatnonzero(np.diff(found[:, 0], prepend=-1))
            yield from zip(found[first, 0].tolist(), np.split(found[:, 1], first[1:]), strict=False)

    def thin(ids, x, cands, own):
        x = K.prepare(x, metric)
        return ((u, K.thin_rows(u, cands[u], x, metric, m)) for u in own.tolist())

    def wide(ids, x, lists, own):
        x = K.prepare(x, metric)
        root = K.medoid(x, metric)
        return ((u, K.widened(u, lists, x, root, m, beam, metric)) for u in own.tolist())

    cands = _step(base, None, pairs, tasks)
    cands = cands.select("vec_id", F.explode("nbrs").alias("n")).groupBy("vec_id").agg(F.sort_array(F.collect_set("n")).alias("nbrs"))
    lists = _grown(base, _step(base, cands, thin, tasks), metric)
    lists = _step(base, lists, wide, tasks, whole=True)
    return _edges_of(_grown(base, _symmetric(base, lists, metric, 2 * m, tasks), metric))


def knn(base: DataFrame, k: int, metric: str = "cosine") -> DataFrame:
    """(src, dst, rank, dist): exact k-nearest-neighbour graph."""
    near = T.exact_blocked(base, base.select(F.col("vec_id").alias("query_id"), "vec"), k + 1, metric).where("query_id <> vec_id")
    order = Window.partitionBy("query_id").orderBy("dist", "vec_id")
    return near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select(F.col("query_id").alias("src"), F.col("vec_id").alias("dst"), "rank", "dist")


def as_edges(arcs: DataFrame, kind: str = "base") -> DataFrame:
    return arcs.select("src", "dst", F.lit(kind).alias("kind"), F.lit(0).alias("layer"), F.lit(0).alias("hardness"), F.lit(-1).cast("bigint").alias("seq"), F.lit(-1).alias("epoch"))


def symmetrize(arcs: DataFrame) -> DataFrame:
    """Arcs and their reverses, each once."""
    return arcs.select("src", "dst").union(arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct()


def rng(base: DataFrame, metric: str = "cosine") -> DataFrame:
    """Exact relative neighbourhood graph of a shard-sized base: no third vector is nearer to both ends."""

    def build(ids: np.ndarray, x: np.ndarray) -> list:
        p = K.prepare(x, metric)
        d = K.all_distances(p, p, metric)
        lists = []
        for i in range(len(ids)):
            worst = np.maximum(d[i][None, :], d)  # [j, w]: the farther of i-w and j-w
            worst[:, i] = np.inf
            np.fill_diagonal(worst, np.inf)
            keep = ~np.any(worst < d[i][:, None], axis=1)
            keep[i] = False
            lists.append(np.flatnonzero(keep))
        return [(0, lists)]

    return _built(base, build)


def thinned(cands: DataFrame, base: DataFrame, cap: int, metric: str = "cosine", slack: float = 0.0) -> DataFrame:
    """(src, dst): monotone thinning of candidate arcs (src, dst), one group a source."""
    placed = cands.select("src", "dst").join(base.select(F.col("vec_id").alias("dst"), F.col("vec").alias("v")), "dst").join(base.select(F.col("vec_id").alias("src"), F.col("vec").alias("o")), "src")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = K.prepare(np.stack(pdf["v"].to_numpy()), metric)
        o = K.prepare(np.stack(pdf["o"].to_numpy()[:1]), metric)[0]
        d = K.distances(x, o, metric)
        order = np.lexsort((pdf["dst"].to_numpy(), d))
        kept = K.thin(d[order], K.all_distances(x[order], x[order], metric), cap, slack)
        return pdf.iloc[order[kept]][["src", "dst"]]

    return placed.groupBy("src").applyInPandas(run, "src bigint, dst bigint")


def components(arcs: DataFrame, rounds: int = 50) -> DataFrame:
    """(node, component) by label propagation over arcs taken both ways; lineage is cut each round."""
    both = cut(symmetrize(arcs))
    labels = cut(both.select(F.col("src").alias("node")).distinct().withColumn("component", F.col("node")))
    for _ in range(rounds):
        step = both.join(labels, both["dst"] == labels["node"]).groupBy("src").agg(F.min("component").alias("m"))
        moved = cut(labels.join(step, labels["node"] == step["src"]).select("node", F.least("component", "m").alias("component"), (F.col("m") < F.col("component")).alias("moved")))
        labels = moved.select("node", "component")
        if moved.where("moved").isEmpty():
            break
    return labels


def degree(edges: DataFrame, base: DataFrame) -> DataFrame:
    """(vec_id, degree) of every base row, those without arcs included."""
    counts = edges.groupBy(F.col("src").alias("vec_id")).agg(F.count(F.lit(1)).alias("degree"))
    return base.select("vec_id").join(counts, "vec_id", "left").select("vec_id", F.coalesce("degree", F.lit(0)).alias("degree"))


