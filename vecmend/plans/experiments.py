"""Experiment workloads on the test tables: curves of recall and cost, ablations, upkeep, times.

A curve has one row a (method, beam): mean recall, mean distance evaluations, out-degree, and the clock of the walks alone,
as queries a second of one thread and mean microseconds.  Beams start at k and grow by ten until a recall is reached.
Times of builds and upkeep are wall clock of whole Spark jobs; ratios between methods are what can be compared.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import graph as G
from ..operators import mend as M
from ..operators import metrics as E
from ..operators import search as S
from ..operators import truth as T
from ..operators import upkeep as U
from ..operators import vicinity as N
from ..sources import families as D
from . import rounds as R
from .lineage import cut

K = 10
CAP = 12
#: Recall at which a sweep of beams stops, the step between beams, and how many of them are judged together.
STOP, STEP, CHUNK = 0.99, 10, 5
#: Beams of ablations, which compare variants at the same effort.
SHORT = (10, 20, 40)


def _sets(spark: SparkSession, d: str, family: str = "sphere", ood: bool = True, k: int = K, metric: str = "cosine"):
    base, q = D.sphere(spark, d, ood) if family == "sphere" else D.FAMILIES[family](spark, d)
    history, test = q.where("role = 'history'"), q.where("role = 'test'")
    base, history, test = cut(base), cut(history), cut(test)
    return base, history, test, cut(T.exact_blocked(base, test, k, metric))


def curve(name: str, base: DataFrame, edges: DataFrame, test: DataFrame, truth: DataFrame, beams=None, k: int = K, stop: float = STOP, **how) -> DataFrame:
    """(method, beam, recall, rderr, ndc, degree, us, qps) over a sweep of beams: given ones, or from k on until recall stops it.

    A sweep ends with the ``CHUNK`` beams in which recall is reached, or where a wider beam changes nothing: it holds the whole base, or every row
    that a walk saw.  Each pass walks from the start, so a pass has as many beams as all before it.
    """
    size, arcs = base.count(), edges.where("layer = 0").count()
    index = cut(S.packed(base, edges, how.pop("tombstones", None)))
    parts, start, many = [], k, CHUNK
    while True:
        now = list(beams) if beams else [start + STEP * i for i in range(many)]
        found = S.sweep(base, edges, test, k, now, index=index, **how)
        want = truth.where(F.col("rank") <= k).select("query_id", "rank", "vec_id", F.col("dist").alias("t")).withColumn("beam", F.explode(F.array(*[F.lit(x) for x in now])))
        found = cut(found)
        hit = found.select("beam", "query_id", "vec_id", F.lit(1).alias("hit"))
        at_rank = found.select("beam", "query_id", "rank", F.col("dist").alias("a"))
        gap = E.distance_error(F.col("a"), F.col("t"))
        row = want.join(hit, ["beam", "query_id", "vec_id"], "left").join(at_rank, ["beam", "query_id", "rank"], "left").groupBy("beam", "query_id").agg(
            F.avg(F.coalesce("hit", F.lit(0))).alias("recall"), F.when(F.count("a") == F.count(F.lit(1)), F.avg(gap)).alias("rderr")
        )
        cost = found.groupBy("beam", "query_id").agg(F.first("ndc").alias("ndc"), F.first("us").alias("us"))
        means = row.join(cost, ["beam", "query_id"], "left").groupBy("beam").agg(
            F.round(F.avg("recall"), 4).alias("recall"), F.round(F.avg("rderr"), 6).alias("rderr"), F.round(F.avg("ndc"), 1).alias("ndc"), F.lit(round(arcs / max(size, 1), 3)).alias("degree"),
            F.round(F.avg("us"), 1).alias("us"), F.round(1e6 / F.avg("us"), 1).alias("qps"),
        )
        means = cut(means.select(F.lit(name).alias("method"), "beam", "recall", "rderr", "ndc", "degree", "us", "qps"))
        reached = None if beams else means.where(F.col("recall") >= stop).agg(F.min("beam")).first()[0]
        parts.append(means if reached is None else means.where(F.col("beam") < start + STEP * CHUNK * ((reached - start) // (STEP * CHUNK) + 1)))
        if beams or reached is not None or now[-1] >= min(size, found.agg(F.max("ndc")).first()[0] or 0):
            return reduce(DataFrame.unionByName, parts)
        start = now[-1] + STEP
        left = -(-(size - start + STEP) // (STEP * CHUNK))
        many = CHUNK * max(1, min((start - k) // (STEP * CHUNK), left))


def timed(make: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
    """A written result and the seconds that it took."""
    began = time.perf_counter()
    out = cut(make())
    return out, time.perf_counter() - began


def _times(spark: SparkSession, rows: list[tuple[str, float]], to: tuple[str, ...]) -> DataFrame:
    """(method, seconds, of_<other>): seconds and their ratios to those of other methods."""
    took = dict(rows)
    return spark.createDataFrame([(n, round(t, 3), *[round(t / took[o], 4) for o in to]) for n, t in rows], ", ".join(["method string", "seconds double", *[f"of_{o} double" for o in to]]))


def _base_graph(base: DataFrame, m: int = 6) -> DataFrame:
    return cut(G.hnsw(base, m, 100))


def _graphs(base: DataFrame, history: DataFrame, metric: str = "cosine", names: tuple[str, ...] = ()) -> dict[str, DataFrame]:
    """The compared graphs of one family, by name: all, or those asked for."""
    thin = cut(G.hnsw(base, 6, 100, metric))
    make = {
        "layered_bottom": lambda: cut(G.hnsw(base, 10, 100, metric)),
        "layered_full": lambda: cut(G.hnsw(base, 10, 100, metric, layers=True)),
        "spreading": lambda: cut(G.nsg(base, 60, 60, 16, metric)),
        "relaxed": lambda: cut(G.tau_mng(base, 0.01, 60, 60, 16, metric)),
        "bridge": lambda: cut(G.query_bridge(base, history, 20, 10, 60, metric)),
        "unmended": lambda: thin,
        "mended": lambda: R.run(base, thin, history, R.two_pass(10, 20), CAP, metric),
    }
    return {n: make[n]() for n in names or make}


MAIN = ("layered_bottom", "bridge", "unmended", "mended")


def main_curves(spark: SparkSession, d: str, family: str = "sphere", ood: bool = True, metric: str = "cosine", k: int = K, stop: float = STOP, names: tuple[str, ...] = ()) -> DataFrame:
    """All graphs on one family: layered, layered in full, spreading, relaxed, bridge, unmended and mended."""
    base, history, test, truth = _sets(spark, d, family, ood, k, metric)
    graphs = _graphs(base, history, metric, names)
    return reduce(DataFrame.unionByName, [curve(n, base, g, test, truth, k=k, stop=stop, metric=metric) for n, g in graphs.items()])


def at_levels(curves: DataFrame) -> DataFrame:
    """(measure, level, method, qps, ndc, qps_of_bridge, qps_of_layered, ndc_of_bridge): speed and evaluations where each curve reaches a level.

    Levels are of recall, and of the distance error, which falls; null where a curve does not reach one.
    """
    curves = cut(curves)
    closer = curves.withColumn("closeness", -F.col("rderr"))
    parts = []
    for measure, level, table, x in [("recall", v, curves, "recall") for v in (0.9, 0.95, 0.99)] + [("rderr", v, closer, "closeness") for v in (0.01, 0.001)]:
        at = level if x == "recall" else -level
        row = E.at_level(table, x, "qps", at).join(E.at_level(table, x, "ndc", at), "method")
        parts.append(curves.select("method").distinct().join(row, "method", "left").select(F.lit(measure).alias("measure"), F.lit(level).alias("level"), "method", "qps", "ndc"))
    rows = reduce(DataFrame.unionByName, parts)
    own = Window.partitionBy("measure", "level")
    of = lambda c, m: F.round(F.col(c) / F.max(F.when(F.col("method") == m, F.col(c))).over(own), 3).alias(f"{c}_of_{m.split('_')[0]}")
    return rows.select("measure", "level", "method", F.round("qps", 1).alias("qps"), F.round("ndc", 1).alias("ndc"), of("qps", "bridge"), of("qps", "layered_bottom"), of("ndc", "bridge"))


def speed_at_level(spark: SparkSession, d: str) -> DataFrame:
    """Speed at equal accuracy of the compared graphs on three families, for 10 neighbours, and for 100 on the first."""
    runs = [("sphere_ood", "sphere", True, K), ("sphere_id", "sphere", False, K), ("text", "text", True, K), ("sphere_ood", "sphere", True, 100)]
    return reduce(DataFrame.unionByName, [at_levels(main_curves(spark, d, f, ood, k=k, names=MAIN)).select(F.lit(n).alias("family"), F.lit(k).alias("k"), "*") for n, f, ood, k in runs])


def equal_latency(spark: SparkSession, d: str) -> DataFrame:
    """(method, recall): accuracy of bridge and mended graphs at the same mean time of a walk, that of the unmended graph at beam 20."""
    curves = cut(main_curves(spark, d, names=("bridge", "unmended", "mended")))
    budget = curves.where("method = 'unmended' and beam = 20").first()["us"]
    return E.at_level(curves, "us", "recall", budget).select("method", F.round("recall", 4).alias("recall")).withColumn("us", F.lit(budget))


def by_similarity(spark: SparkSession, d: str) -> DataFrame:
    """Curves of bridge and mended graphs for each band of distance between test query and history; bands are thirds."""
    base, history, test, truth = _sets(spark, d)
    near = cut(U.similarity_bands(test, history))
    cuts = near.agg(F.percentile("gap", F.array(F.lit(1 / 3), F.lit(2 / 3))).alias("p")).first()["p"]
    banded = cut(U.similarity_bands(test, history, (cuts[0], cuts[1])))
    parts = []
    for name, g in _graphs(base, history, names=("bridge", "unmended", "mended")).items():
        for band in ("high", "moderate", "low"):
            some = cut(test.join(banded.where(F.col("band") == band), "query_id"))
            parts.append(curve(name, base, g, some, truth.join(some.select("query_id"), "query_id", "left_semi"), (10, 20, 40)).withColumn("band", F.lit(band)))
    return reduce(DataFrame.unionByName, parts)


def id_after_ood(spark: SparkSession, d: str) -> DataFrame:
    """Queries from the base's own distribution on graphs mended from shifted history, and from their own."""
    base, shifted, _, _ = _sets(spark, d)
    _, own, test, truth = _sets(spark, d, ood=False)
    thin = _base_graph(base)
    graphs = {"unmended": thin, "mended_ood": R.run(base, thin, shifted, R.single(K), CAP), "mended_id": R.run(base, thin, own, R.single(K), CAP)}
    return reduce(DataFrame.unionByName, [curve(n, base, g, test, truth, SHORT) for n, g in graphs.items()])


def edges_vs_recall(spark: SparkSession, d: str) -> DataFrame:
    """(n_arcs, n, recall): history queries by the arcs that the mend adds for them, and their recall before it; with the correlation."""
    base, history, _, _ = _sets(spark, d)
    edges = _base_graph(base)
    truth = cut(T.exact_blocked(base, history, 5 * K))
    arcs = M.vicinity(truth, edges, base, K, K, 5 * K).groupBy("query_id").agg(F.count(F.lit(1)).alias("n_arcs"))
    rec = E.recall_by_query(S.sharded(base, edges, history, K, K), truth, K)
    both = cut(rec.join(arcs, "query_id", "left").withColumn("n_arcs", F.coalesce("n_arcs", F.lit(0))))
    corr = both.agg(F.round(F.corr("n_arcs", "recall"), 4)).first()[0]
    return both.groupBy("n_arcs").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("recall"), 4).alias("recall")).withColumn("corr", F.lit(corr))


def vicinity_pictures(spark: SparkSession, d: str, size: int = 30) -> DataFrame:
    """(query_id, recall, n_arcs, n_isolated, strong, rank, x, y): plane pictures of the vicinities of the best and the worst found query."""
    base, _, test, _ = _sets(spark, d)
    edges, truth = _base_graph(base), cut(T.exact_blocked(base, test, size))
    rec = cut(E.recall_by_query(S.sharded(base, edges, test, size, size, entry="random"), truth, size))
    ends = rec.agg(F.max_by("query_id", F.struct("recall", "query_id")).alias("best"), F.min_by("query_id", F.struct("recall", "query_id")).alias("worst")).first()
    own = cut(truth.where(F.col("query_id").isin(ends["best"], ends["worst"])))
    shape = N.shape(own, N.extract(own, edges, size), size).join(rec, "query_id")
    return shape.join(N.layout(T.pair_gaps(own, base, size)), "query_id").select("query_id", F.round("recall", 4).alias("recall"), "n_arcs", "n_isolated", "strong", "rank", F.round(F.abs("x"), 6).alias("x"), F.round(F.abs("y"), 6).alias("y"))


def reachable_histogram(spark: SparkSession, d: str) -> DataFrame:
    """(queries, bucket, n, share): queries of both kinds by tenths of the reachable share of their vicinity of 30."""
    parts = []
    for name, ood in (("id", False), ("ood", True)):
        base, _, test, _ = _sets(spark, d, ood=ood)
        truth = cut(T.exact_blocked(base, test, 30))
        reach = N.mean_reachable(truth, N.extract(truth, _base_graph(base), 30), 30)
        counts = reach.groupBy(F.least(F.floor(F.col("mean_reachable") / 3), F.lit(9)).cast("int").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))
        parts.append(counts.select(F.lit(name).alias("queries"), "bucket", "n", F.round(F.col("n") / F.sum("n").over(Window.partitionBy()), 4).alias("share")))
    return reduce(DataFrame.unionByName, parts)


def recall_mix(spark: SparkSession, d: str) -> DataFrame:
    """(family, band, n_queries, share) of the unmended graph at beam K, with the share whose walk finds nothing (band 0)."""
    parts, graphs = [], {}
    for family, ood in (("sphere", True), ("sphere", False), ("text", True)):
        base, _, test, truth = _sets(spark, d, family, ood)
        if family not in graphs:  # both kinds of queries are asked of one base
            graphs[family] = _base_graph(base)
        rec = E.recall_by_query(S.sharded(base, graphs[family], test, K, K), truth, K)
        parts.append(E.bands(rec).select(F.lit(family + ("" if ood else "_id")).alias("family"), "band", "n_queries", F.round("share", 4).alias("share")))
    return reduce(DataFrame.unionByName, parts)


def build_times(spark: SparkSession, d: str) -> DataFrame:
    """Seconds to build each graph: baselines, and the base graph with the mend, from exact truth and from walks."""
    base, history, _, _ = _sets(spark, d)
    cut(G.hnsw(base, 4, 20))  # starts the workers
    rows = [(n, timed(f)[1]) for n, f in {
        "layered": lambda: G.hnsw(base, 10, 100), "layered_full": lambda: G.hnsw(base, 10, 100, layers=True), "spreading": lambda: G.nsg(base, 60, 60, 16),
        "relaxed": lambda: G.tau_mng(base, 0.01, 60, 60, 16), "bridge": lambda: G.query_bridge(base, history, 20, 10, 60),
        "mended_exact": lambda: R.run(base, _base_graph(base), history, R.single(K), CAP),
        "mended_walks": lambda: R.run(base, _base_graph(base), history, R.single(K), CAP, truth="index", beam=80, mode="visited"),
    }.items()]
    return _times(spark, rows, ("bridge", "layered", "spreading"))


def upkeep_times(spark: SparkSession, d: str) -> DataFrame:
    """Seconds of insertion with refreshes of growing shares, and of healing after deletion, beside full rebuilds; recall at beam 20."""
    base, history, test, truth = _sets(spark, d)
    passes = R.single(K)
    old, new = base.where("vec_id % 5 <> 4"), base.where("vec_id % 5 = 4")
    mended = R.run(old, _base_graph(old), history, passes, CAP)
    runs: dict[str, tuple[DataFrame, DataFrame, DataFrame, float]] = {}
    grown, t_insert = timed(lambda: U.insert(old, mended, new))
    for share in (0.1, 0.2, 0.3, 0.4, 0.5):
        g, t = timed(lambda share=share: U.refresh(base, grown, history, share, passes, CAP))
        runs[f"insert_refresh_{share}"] = (base, g, truth, t_insert + t)
    runs["insert_rebuild"] = (base, *_rebuilt(base, history, passes, truth))
    dead, live = cut(base.where("vec_id % 5 = 0").select("vec_id")), cut(base.where("vec_id % 5 <> 0"))
    whole, left = R.run(base, _base_graph(base), history, passes, CAP), cut(T.exact_blocked(live, test, K))
    spread = cut(G.nsg(base, 60, 60, 16))
    narrow = R.single(K, approach=False)
    for name, g in (("delete", whole), ("spreading_delete", spread)):
        healed, t = timed(lambda g=g: U.heal(base, g, dead, narrow, CAP, beam=80))
        runs[f"{name}_heal"] = (live, healed, left, t)
    runs["delete_rebuild"] = (live, *_rebuilt(live, history, passes, left))
    again, t = timed(lambda: G.nsg(live, 60, 60, 16))
    runs["spreading_delete_rebuild"] = (live, again, left, t)
    parts = [curve(n, b, g, test, tr, (20,)).select("method", "recall", "ndc").withColumn("seconds", F.lit(round(t, 3))) for n, (b, g, tr, t) in runs.items()]
    rows = reduce(DataFrame.unionByName, parts)
    full = F.when(F.col("method").startswith("insert"), runs["insert_rebuild"][3]).when(F.col("method").startswith("spreading"), t).otherwise(runs["delete_rebuild"][3])
    return rows.withColumn("of_rebuild", F.round(F.col("seconds") / full, 4))


def _rebuilt(base: DataFrame, history: DataFrame, passes: list, truth: DataFrame) -> tuple[DataFrame, DataFrame, float]:
    g, t = timed(lambda: U.rebuild(base, history, passes, CAP))
    return g, truth, t


def cache_latency(spark: SparkSession, d: str) -> DataFrame:
    """(n, cache_us, walk_us, ratio): mean time of an answer from a dictionary of canonical keys and of a walk at beam 100, over the log's repeats.

    Equal queries walk alike: each distinct one is walked once, and its time counts as often as the query stands in the log.
    """
    base, q = D.event_log(spark, d)
    base, q = cut(base), cut(q.select("query_id", "vec"))
    one = cut(U.repeats(q))
    cache = cut(U.build_cache(one, T.exact_blocked(base, one, K), K))
    hits, _ = U.cache_split(q, cache)
    looked = U.lookup_times(hits, cache)
    walked = S.sharded(base, _base_graph(base), one, K, 100).groupBy("query_id").agg(F.first("us").alias("us")).join(one, "query_id").agg((F.sum(F.col("us") * F.col("n")) / F.sum("n")).alias("walk_us"))
    return looked.join(walked, how="cross").select("n", F.round("cache_us", 2).alias("cache_us"), F.round("walk_us", 1).alias("walk_us"), F.round(F.col("cache_us") / F.col("walk_us"), 4).alias("ratio"))


def online_by_date(spark: SparkSession, d: str) -> DataFrame:
    """The shop log in order of its dates: a graph mended from each quarter's history in turn, tested on the last third after each."""
    base, history, test, truth = _sets(spark, d, "products")
    at = F.unix_timestamp("ts")
    cuts = history.agg(F.percentile(at, F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75))).alias("p")).first()["p"] or [0, 0, 0]
    edges, parts = _base_graph(base), []
    parts.append(curve("quarter_0", base, edges, test, truth, (10, 20)))
    for i, (lo, hi) in enumerate(zip([None, *cuts], [*cuts, None], strict=True), 1):
        some = cut(history.where((at > lo if lo is not None else F.lit(True)) & (at <= hi if hi is not None else F.lit(True))))
        edges = R.run(base, edges, some, R.single(K, approach=False), CAP)
        parts.append(curve(f"quarter_{i}", base, edges, test, truth, (10, 20)))
    return reduce(DataFrame.unionByName, parts)


def history_share(spark: SparkSession, d: str) -> DataFrame:
    """Mended graphs from growing shares of the history, from as many queries as 1 % of the base, and the bridge at two sizes."""
    base, history, test, truth = _sets(spark, d)
    thin, n = _base_graph(base), history.count()
    parts = [curve("share_0", base, thin, test, truth, SHORT)]
    few = history.orderBy("query_id").limit(max(1, base.count() // 100))
    parts.append(curve("base_1", base, R.run(base, thin, few, R.single(K), CAP), test, truth, SHORT))
    for share in (1, 3, 10, 30, 100):
        some = history.orderBy("query_id").limit(max(1, n * share // 100))
        parts.append(curve(f"share_{share}", base, R.run(base, thin, some, R.single(K), CAP), test, truth, SHORT))
    for share in (10, 100):
        parts.append(curve(f"bridge_{share}", base, cut(G.query_bridge(base, history, 20, 10, 60, history_limit=max(1, n * share // 100))), test, truth, SHORT))
    return reduce(DataFrame.unionByName, parts)


def truth_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Exact truth against truth from walks at several beams."""
    base, history, test, truth = _sets(spark, d)
    thin = _base_graph(base)
    parts = [curve("exact", base, R.run(base, thin, history, R.single(K), CAP), test, truth, SHORT)]
    for beam in (50, 80, 160):
        parts.append(curve(f"index_{beam}", base, R.run(base, thin, history, R.single(K), CAP, truth="index", beam=beam, mode="visited"), test, truth, SHORT))
    return reduce(DataFrame.unionByName, parts)


def method_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Vicinity mend, overlay of the relative neighbourhood graph, and random pairs; compare at equal degree or NDC."""
    base, history, test, truth = _sets(spark, d)
    thin = _base_graph(base)
    parts = [curve("unmended", base, thin, test, truth, SHORT)]
    for method in ("vicinity", "rng", "random"):
        parts.append(curve(method, base, R.run(base, thin, history, R.single(K, approach=False), CAP, method=method), test, truth, SHORT))
    return reduce(DataFrame.unionByName, parts)


def policy_ablation(spark: SparkSession, d: str) -> DataFrame:
    """Pruning of extra arcs by hardness, at random, and by monotone thinning, under a small cap."""
    base, history, test, truth = _sets(spark, d)
    thin = _base_graph(base)
    parts = [curve(p, base, R.run(base, thin, history, R.single(K, approach=False), 4, policy=p), test, truth, SHORT) for p in M.POLICIES]
    return reduce(DataFrame.unionByName, parts)


def approach_ablation(spark: SparkSession, d: str) -> DataFrame:
    """With and without the approach mend on the text family, and stuck walks before and after."""
    base, history, test, truth = _sets(spark, d, "text")
    thin = cut(G.hnsw(base, 3, 60))
    near = cut(T.exact_blocked(base, history, K))
    plain = R.run(base, thin, history, R.single(K, approach=False), None)
    full = R.run(base, plain, history, R.single(K), None)
    parts = []
    for name, g in (("unmended", thin), ("vicinity", plain), ("full", full)):
        n = M.stuck(base, g, history, near, K, K).count()
        parts.append(curve(name, base, g, test, truth, SHORT).withColumn("n_stuck", F.lit(n)))
    return reduce(DataFrame.unionByName, parts)


def parameter_grid(spark: SparkSession, d: str) -> DataFrame:
    """Effect of the cap on extra arcs, the bound on ranks, the vicinity, the near set and the base degree."""
    base, history, test, truth = _sets(spark, d)
    thin = _base_graph(base)
    parts = [curve(f"cap_{c}", base, R.run(base, thin, history, R.single(K, approach=False), c), test, truth, (20,)) for c in (2, 6, 12)]
    parts += [curve(f"reach_{r}", base, R.run(base, thin, history, [R.Pass(K, r, 5 * K)], CAP), test, truth, (20,)) for r in (10, 20, 40)]
    parts += [curve(f"rank_{r}", base, R.run(base, thin, history, [R.Pass(K, K, r)], CAP), test, truth, (20,)) for r in (K, 2 * K, 10 * K)]
    parts += [curve(f"near_{n}", base, R.run(base, thin, history, [R.Pass(n, n, 5 * n)], CAP), test, truth, (20,)) for n in (5, 20)]
    parts += [curve(f"degree_{m}", base, R.run(base, _base_graph(base, m), history, R.single(K, approach=False), CAP), test, truth, (20,)) for m in (4, 10)]
    return reduce(DataFrame.unionByName, parts)


def insertion(spark: SparkSession, d: str) -> DataFrame:
    """Insert a fifth of the rows: plainly, with a partial refresh, and by rebuilding."""
    base, history, test, truth = _sets(spark, d)
    old, new = base.where("vec_id % 5 <> 4"), base.where("vec_id % 5 = 4")
    passes = R.single(K)
    mended = R.run(old, _base_graph(old), history, passes, CAP)
    grown = cut(U.insert(old, mended, new))
    parts = [curve("plain", base, grown, test, truth, SHORT)]
    for share in (0.2, 0.5):
        parts.append(curve(f"refresh_{share}", base, U.refresh(base, grown, history, share, passes, CAP), test, truth, SHORT))
    parts.append(curve("rebuild", base, U.rebuild(base, history, passes, CAP), test, truth, SHORT))
    return reduce(DataFrame.unionByName, parts)


def deletion(spark: SparkSession, d: str) -> DataFrame:
    """Delete a fifth of the rows: lazily, purged, healed, rebuilt; healing also on a graph never mended from history."""
    base, history, test, _ = _sets(spark, d)
    dead, live = cut(base.where("vec_id % 5 = 0").select("vec_id")), cut(base.where("vec_id % 5 <> 0"))
    truth, passes = cut(T.exact_blocked(live, test, K)), R.single(K)
    mended = R.run(base, _base_graph(base), history, passes, CAP)
    spread = cut(G.nsg(base, 60, 60, 16))
    parts = [
        curve("lazy", base, mended, test, truth, SHORT, tombstones=dead),
        curve("purged", live, cut(U.purge(mended, dead)), test, truth, SHORT),
        curve("healed", live, U.heal(base, mended, dead, R.single(K, approach=False), CAP), test, truth, SHORT),
        curve("rebuilt", live, U.rebuild(live, history, passes, CAP), test, truth, SHORT),
        curve("spreading_purged", live, cut(U.purge(spread, dead)), test, truth, SHORT),
        curve("spreading_healed", live, U.heal(base, spread, dead, R.single(K, approach=False), CAP), test, truth, SHORT),
        curve("spreading_rebuilt", live, cut(G.nsg(live, 60, 60, 16)), test, truth, SHORT),
    ]
    return reduce(DataFrame.unionByName, parts)


def synthetic_history(spark: SparkSession, d: str) -> DataFrame:
    """Noisy copies of a tenth of the history at several noise constants."""
    base, history, test, truth = _sets(spark, d)
    thin, some = _base_graph(base), history.where("query_id % 100 in (7, 8)")
    parts = [curve("real_only", base, R.run(base, thin, some, R.single(K, approach=False), CAP), test, truth, SHORT)]
    for c in (0.1, 0.2, 0.3, 0.4):
        more = cut(U.augment(some, 5, c).select("query_id", "vec"))
        parts.append(curve(f"noise_{c}", base, R.run(base, thin, more, R.single(K, approach=False), CAP), test, truth, SHORT))
    return reduce(DataFrame.unionByName, parts)


def subset_mend(spark: SparkSession, d: str) -> DataFrame:
    """Vicinity mend against mending of random subsets of a wider near set."""
    base, history, test, truth = _sets(spark, d)
    thin = _base_graph(base)
    near = cut(T.exact_blocked(base, history, 5 * K))
    plain = cut(M.admit(thin, M.vicinity(near, thin, base, K, K, 5 * K), CAP))
    wide = cut(M.admit(thin, M.vicinity(M.subset_truth(near, K, draws=5), thin, base, K, K, 2 * K), CAP))
    return curve("vicinity", base, plain, test, truth, SHORT).unionByName(curve("subsets", base, wide, test, truth, SHORT))


def connectivity(spark: SparkSession, d: str) -> DataFrame:
    """Per query of both kinds: recall on the unmended graph and reachable points of its vicinity, and their correlation."""
    parts = []
    for name, ood in (("id", False), ("ood", True)):
        base, _, test, _ = _sets(spark, d, ood=ood)
        edges = _base_graph(base)
        truth = cut(T.exact_blocked(base, test, 20))
        rec = E.recall_by_query(S.sharded(base, edges, test, K, K), truth, K)
        reach = N.mean_reachable(truth, N.extract(truth, edges, 20), 20)
        parts.append(rec.join(reach, "query_id").agg(F.lit(name).alias("queries"), F.count(F.lit(1)).alias("n"), F.round(F.avg("recall"), 4).alias("recall"), F.round(F.avg("mean_reachable"), 3).alias("reachable"), F.round(F.corr("recall", "mean_reachable"), 3).alias("corr")))
    return reduce(DataFrame.unionByName, parts)


def drift(spark: SparkSession, d: str) -> DataFrame:
    """Mend from the first half of the event log, test on the last quarter: as is, and adapted to the first half of the second."""
    base, q = D.event_log(spark, d)
    one = q.withColumn("u", F.round(F.get("vec", F.lit(0)), 9)).dropDuplicates(["u"]).drop("u")
    cuts = one.agg(F.percentile(F.unix_timestamp("ts"), F.array(F.lit(0.5), F.lit(0.75))).alias("p")).first()["p"]
    at = F.unix_timestamp("ts")
    first, second, last = (cut(x) for x in (one.where(at <= cuts[0]), one.where((at > cuts[0]) & (at <= cuts[1])), one.where(at > cuts[1])))
    base = cut(base)
    truth = cut(T.exact_blocked(base, last, K))
    mended = R.run(base, _base_graph(base), first, R.single(K, approach=False), CAP)
    adapted = U.drift_adapt(base, mended, second, R.single(K, approach=False), extra_cap=CAP)
    return curve("stale", base, mended, last, truth, SHORT).unionByName(curve("adapted", base, adapted, last, truth, SHORT))


def cache_hybrid(spark: SparkSession, d: str) -> DataFrame:
    """Share of the later half of the event log that the cache of the first half answers, and recall of both parts."""
    base, q = D.event_log(spark, d)
    base = cut(base)
    half = q.agg(F.percentile(F.unix_timestamp("ts"), 0.5)).first()[0]
    old, new = cut(q.where(F.unix_timestamp("ts") <= half)), cut(q.where(F.unix_timestamp("ts") > half))
    once = cut(U.repeats(old))
    cache = cut(U.build_cache(once, T.exact_blocked(base, once, K), K))
    # equal queries have equal answers: each distinct one is answered, and all are counted
    asked = cut(U.repeats(new))
    found = cut(U.hybrid(base, _base_graph(base), asked, cache, K, 20))
    rec = E.recall_by_query(found, T.exact_blocked(base, asked, K), K).join(found.groupBy("query_id").agg(F.first("cached").alias("cached")), "query_id").join(asked.select("query_id", "n"), "query_id")
    return rec.groupBy("cached").agg(F.sum("n").alias("n"), F.round(F.sum(F.col("recall") * F.col("n")) / F.sum("n"), 4).alias("recall"))


def beam_by_band(spark: SparkSession, d: str) -> DataFrame:
    """Smallest beam that reaches a recall of 0.9 in each band of similarity to the history, then the search with those beams."""
    base, history, test, truth = _sets(spark, d)
    edges = R.run(base, _base_graph(base), history, R.single(K), CAP)
    banded = cut(U.similarity_bands(test, history, (0.4, 0.5)))
    points = []
    for beam in (10, 20, 40, 80):
        rec = E.recall_by_query(S.sharded(base, edges, test, K, beam), truth, K).join(banded, "query_id")
        points.append(rec.groupBy("band").agg(F.avg("recall").alias("recall")).withColumn("beam", F.lit(beam)))
    table = U.calibrate(cut(reduce(DataFrame.unionByName, points)), 0.9)
    beams = U.assign_beam(banded, {b: table.get(b, 160) for b in ("high", "moderate", "low")}).select("query_id", "beam", "band")
    found = cut(S.sharded(base, edges, test.join(beams, "query_id"), K, K, beam_col="beam"))
    rec = E.recall_by_query(found, truth, K).join(beams, "query_id").join(found.groupBy("query_id").agg(F.first("ndc").alias("ndc")), "query_id")
    return rec.groupBy("band").agg(F.first("beam").alias("beam"), F.count(F.lit(1)).alias("n"), F.round(F.avg("recall"), 4).alias("recall"), F.round(F.avg("ndc"), 1).alias("ndc"))


def sizes(spark: SparkSession, d: str) -> DataFrame:
    """(method, kind, n_arcs, n_bytes): index size of the base graphs and the mended one."""
    base, history, _, _ = _sets(spark, d)
    graphs = _graphs(base, history)
    return reduce(DataFrame.unionByName, [E.index_bytes(g).withColumn("method", F.lit(n)) for n, g in graphs.items()])


WORKLOADS = {
    "curves_sphere_ood": lambda s, d: main_curves(s, d),
    "curves_sphere_id": lambda s, d: main_curves(s, d, ood=False),
    "curves_sphere_id_l2": lambda s, d: main_curves(s, d, ood=False, metric="l2"),
    "curves_text": lambda s, d: main_curves(s, d, "text"),
    "curves_products": lambda s, d: main_curves(s, d, "products", stop=0.9, names=MAIN),
    "speed_at_level": speed_at_level, "equal_latency": equal_latency, "by_similarity": by_similarity, "id_after_ood": id_after_ood,
    "edges_vs_recall": edges_vs_recall, "vicinity_pictures": vicinity_pictures, "reachable_histogram": reachable_histogram, "recall_mix": recall_mix,
    "build_times": build_times, "upkeep_times": upkeep_times, "cache_latency": cache_latency, "online_by_date": online_by_date,
    "history_share": history_share, "truth_ablation": truth_ablation, "method_ablation": method_ablation, "policy_ablation": policy_ablation,
    "approach_ablation": approach_ablation, "parameter_grid": parameter_grid, "insertion": insertion, "deletion": deletion,
    "synthetic_history": synthetic_history, "subset_mend": subset_mend, "connectivity": connectivity, "drift": drift,
    "cache_hybrid": cache_hybrid, "beam_by_band": beam_by_band, "index_sizes": sizes,
}
