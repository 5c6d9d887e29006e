"""Schedules: batches of history against frozen snapshots, passes, and the full mend."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import mend as M
from ..operators import search as S
from ..operators import truth as T
from .lineage import cut


@dataclass(frozen=True)
class Pass:
    """One pass: near set, bound on bottleneck ranks, vicinity size, and whether walks are mended too."""

    n_near: int
    reach_cap: int
    max_rank: int
    approach: bool = False


def single(n_near: int, approach: bool = True) -> list[Pass]:
    return [Pass(n_near, n_near, 5 * n_near, approach)]


def two_pass(k_small: int = 10, k_large: int = 100) -> list[Pass]:
    """A wide pass over all history, then a narrow one that also mends walks."""
    return [Pass(k_large, k_large, 5 * k_large), Pass(k_small, k_small, 5 * k_small, True)]


def run(
    base: DataFrame, edges: DataFrame, history: DataFrame, passes: list[Pass], extra_cap: int | None = 48, metric: str = "cosine",
    batch: int | None = None, method: str = "vicinity", policy: str = "hardness", truth: str = "exact", beam: int = 800, mode: str = "exact",
) -> DataFrame:
    """Mended graph.  Queries of one batch see the same snapshot; their proposals are admitted together.

    With exact truth the neighbours of all history are computed once, before any mending; with truth ``index`` they come from
    walks with a wide beam.  Lineage is cut after each batch.

    A base with a ``shard`` column is mended shard by shard in the same plans: a query stands once for each shard, with the number
    query_id * shards + shard, beside its neighbours in that shard; arcs stay within shards.
    """
    shards = T.shard_count(base)
    ordered, n_history = numbered(history) if batch else (None, 0)
    batches, size = range(0, n_history, batch) if batch else [None], base.count()
    near, widest = None, max((min(p.max_rank, size) for p in passes), default=0)
    asked = history if shards is None else T.per_shard(history, shards)
    whose = F.col("query_id") if shards is None else F.floor(F.col("query_id") / shards).cast("bigint")
    for p in passes:
        # the exact neighbours do not depend on the graph, so the widest pass's serve all
        if truth == "exact":
            near = near if near is not None else cut(T.exact_blocked(base, history, widest, metric) if shards is None else T.exact_shards(base, history, widest, shards, metric))
        else:
            near = cut(S.sharded(base, edges, history, min(p.max_rank, size), beam, metric, shards=shards).select("query_id", "rank", "vec_id", "dist"))
        for start in batches:
            own = near
            if start is not None:
                now = ordered.where((F.col("n") >= start) & (F.col("n") < start + batch)).select(F.col("query_id").alias("now"))
                own = near.join(now, whose == F.col("now"), "left_semi")
            proposals = M.vicinity(own, edges, base, p.n_near, p.reach_cap, p.max_rank, metric, method)
            edges = cut(M.admit(edges, proposals, extra_cap, policy, base=base, metric=metric))
        if p.approach:
            edges = M.approach(base, edges, asked, near, p.n_near, p.n_near, extra_cap, metric, mode)
    return edges


def numbered(queries: DataFrame) -> tuple[DataFrame, int]:
    """(query_id, n) and the count: places in the order of query_id, from 0.

    Ranges of ids are sorted apart, and shifted by the counts of the ranges before them, one number a partition.
    """
    ranges = cut(queries.select("query_id").repartitionByRange("query_id").sortWithinPartitions("query_id").select("query_id", F.monotonically_increasing_id().alias("at")))
    part, place = F.shiftright("at", 33), F.col("at").bitwiseAND(F.lit((1 << 33) - 1))
    counts = {r["p"]: r["n"] for r in ranges.groupBy(part.alias("p")).agg(F.count(F.lit(1)).alias("n")).collect()}
    before, total = {}, 0
    for p in sorted(counts):
        before[p], total = total, total + counts[p]
    if not before:
        return ranges.select("query_id", place.alias("n")), 0
    shift = F.element_at(F.create_map(*[F.lit(x).cast("bigint") for pair in before.items() for x in pair]), part)
    return ranges.select("query_id", (place + shift).alias("n")), total
