"""Insertion, partial refresh, tombstones, purge, healing, drift, history, cache and per-query effort."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import vectors as V
from ..plans import rounds as R
from . import graph as G
from . import search as S
from . import truth as T


def insert(base: DataFrame, edges: DataFrame, new: DataFrame, m: int = 6, beam: int = 100, metric: str = "cosine") -> DataFrame:
    """Edges with new rows linked in: candidates by a walk, thinned to m, with reverse arcs.

    Rows inserted together see the graph before them and each other's reverse arcs only.  Extra arcs stay.
    """
    asked = new.select(F.col("vec_id").alias("query_id"), "vec")
    near = S.sharded(base, edges, asked, beam, beam, metric).select(F.col("query_id").alias("src"), F.col("vec_id").alias("dst"))
    everything = base.select("vec_id", "vec").unionByName(new.select("vec_id", "vec"))
    own = G.thinned(near, everything, m, metric)
    old = edges.where("kind = 'base'").select("src", "dst")
    back = own.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    grown = old.unionByName(back).distinct()
    wide = grown.groupBy("src").count().where(F.col("count") > 2 * m).select("src")
    slim = G.thinned(grown.join(wide, "src", "left_semi"), everything, 2 * m, metric)
    kept = grown.join(wide, "src", "left_anti").unionByName(slim).unionByName(own)
    return G.as_edges(kept).unionByName(edges.where("kind = 'extra'"))


def refresh_drop(edges: DataFrame, share: float, seed: int = 0) -> DataFrame:
    """Edges after dropping floor(share * degree) extra arcs of each row in hash order; the tags of the rest are reset to 0."""
    extra = edges.where("kind = 'extra'")
    by = Window.partitionBy("src")
    order = by.orderBy(F.md5(F.concat_ws(":", "src", "dst", F.lit(seed))))
    kept = extra.withColumn("r", F.row_number().over(order)).withColumn("n", F.count(F.lit(1)).over(by)).where(F.col("r") > F.floor(F.col("n") * share))
    return edges.where("kind = 'base'").unionByName(kept.withColumn("hardness", F.lit(0)).drop("r", "n"))


def refresh(base: DataFrame, edges: DataFrame, history: DataFrame, share: float, passes: list, extra_cap: int | None = 48, metric: str = "cosine", seed: int = 0) -> DataFrame:
    """Partial rebuild: drop a share of the extra arcs and mend with the same share of the history."""
    part = history.where(V.uniform(F.concat_ws(":", F.col("query_id"), F.lit(seed))) < share)
    return R.run(base, refresh_drop(edges, share, seed), part, passes, extra_cap, metric)


def purge(edges: DataFrame, dead: DataFrame) -> DataFrame:
    """Edges without arcs into or out of removed rows, in one pass."""
    gone = dead.select("vec_id")
    return edges.join(gone, edges["src"] == gone["vec_id"], "left_anti").join(gone, F.col("dst") == gone["vec_id"], "left_anti")


def should_purge(base: DataFrame, dead: DataFrame, threshold: float = 0.01) -> bool:
    return dead.count() >= threshold * base.count()


def heal(base: DataFrame, edges: DataFrame, dead: DataFrame, passes: list, extra_cap: int | None = 48, metric: str = "cosine", truth: str = "index", beam: int = 100) -> DataFrame:
    """Purged and mended edges: each removed vector acts as a history query on the rows that are left."""
    live = base.join(dead.select("vec_id"), "vec_id", "left_anti")
    asked = base.join(dead.select("vec_id"), "vec_id", "left_semi").select(F.col("vec_id").alias("query_id"), "vec")
    return R.run(live, purge(edges, dead), asked, passes, extra_cap, metric, truth=truth, beam=beam)


def rebuild(base: DataFrame, history: DataFrame, passes: list, extra_cap: int | None = 48, m: int = 6, ef: int = 100, metric: str = "cosine") -> DataFrame:
    """Everything anew: the baseline of upkeep."""
    return R.run(base, R.cut(G.hnsw(base, m, ef, metric)), history, passes, extra_cap, metric)


def drift_adapt(base: DataFrame, edges: DataFrame, queries: DataFrame, passes: list, drop_share: float = 0.2, newest: int | None = None, extra_cap: int | None = 48, metric: str = "cosine", seed: int = 0) -> DataFrame:
    """Drop a random share of all extra arcs, then mend with the newest queries (by ``ts``)."""
    kept = edges.where((F.col("kind") == "base") | (V.uniform(F.concat_ws(":", "src", "dst", F.lit(seed))) >= drop_share))
    recent = queries.orderBy(F.desc("ts"), F.desc("query_id")).limit(newest) if newest else queries
    return R.run(base, kept, recent, passes, extra_cap, metric)


# --- history -----------------------------------------------------------------------


def augment(history: DataFrame, copies: int, noise: float = 0.3, spread: str = "std", seed: int = 0) -> DataFrame:
    """Real queries and noisy copies: Gaussian noise of norm about ``noise`` (spread ``std``), by Box-Muller from md5.

    ``spread='variance'`` reads the square root of noise over dimension as a variance instead.
    """
    real = history.select("query_id", "vec", F.col("query_id").alias("parent_id"), F.lit(0).alias("copy"))
    grown = history.select("query_id", "vec", F.explode(F.sequence(F.lit(1), F.lit(copies))).alias("copy")) if copies else history.select("query_id", "vec", F.lit(1).alias("copy")).limit(0)
    sigma = F.sqrt(F.lit(noise) / F.size("vec"))
    sigma = F.sqrt(sigma) if spread == "variance" else sigma

    def shaken(x, j):
        u = lambda part: V.uniform(F.concat_ws(":", F.col("query_id"), F.col("copy"), j, F.lit(part), F.lit(seed)))
        return x + sigma * F.sqrt(-2 * F.log(u("a"))) * F.cos(2 * 3.141592653589793 * u("b"))

    noisy = grown.withColumn("noisy", F.transform("vec", shaken)).select((F.col("query_id") * 1000 + F.col("copy")).alias("query_id"), F.col("noisy").alias("vec"), F.col("query_id").alias("parent_id"), "copy")
    return real.unionByName(noisy)


def split(queries: DataFrame, test_n: int, mode: str = "random", seed: int = 0) -> DataFrame:
    """Queries with a role: duplicates of one key go, the first ``test_n`` by hash or by latest time are test, and no test key is in the history."""
    one = queries.withColumn("key_md5", V.key_md5(F.col("vec"))).groupBy("key_md5").agg(F.min_by(F.struct(*queries.columns), "query_id").alias("q")).select("q.*", "key_md5")
    order = F.md5(F.concat_ws(":", F.col("query_id"), F.lit(seed))) if mode == "random" else F.struct(F.desc("ts"))
    test = one.orderBy(order, "query_id") if mode == "random" else one.orderBy(F.desc("ts"), F.desc("query_id"))
    chosen = test.limit(test_n).select("key_md5", F.lit(True).alias("t"))
    return one.join(chosen, "key_md5", "left").withColumn("role", F.when(F.col("t"), "test").otherwise("history")).drop("t")


# --- cache and effort --------------------------------------------------------------


def repeats(queries: DataFrame) -> DataFrame:
    """(query_id, vec, n): each distinct vector once, under its smallest id, with the number of queries that have it."""
    return queries.groupBy("vec").agg(F.min("query_id").alias("query_id"), F.count(F.lit(1)).alias("n")).select("query_id", "vec", "n")


def build_cache(history: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(key_md5, vec_canon, ids, dists): stored answers of distinct history queries."""
    keyed = history.select("query_id", V.key_md5(F.col("vec")).alias("key_md5"), V.canonical(F.col("vec")).alias("vec_canon"))
    one = keyed.groupBy("key_md5", "vec_canon").agg(F.min("query_id").alias("query_id"))
    answers = truth.where(F.col("rank") <= k).groupBy("query_id").agg(F.sort_array(F.collect_list(F.struct("rank", "vec_id", "dist"))).alias("a"))
    return one.join(answers, "query_id").select("key_md5", "vec_canon", F.transform("a", lambda x: x["vec_id"]).alias("ids"), F.transform("a", lambda x: x["dist"]).alias("dists"))


def cache_split(queries: DataFrame, cache: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(hits with ids, misses): the canonical text is compared too, so a collision of keys is a miss."""
    keys = queries.select("vec").distinct().withColumn("vec_canon", V.canonical(F.col("vec"))).withColumn("key_md5", F.md5("vec_canon"))
    keyed = queries.join(keys, "vec")
    hits = keyed.join(cache, ["key_md5", "vec_canon"])
    return hits, keyed.join(cache, ["key_md5", "vec_canon"], "left_anti")


def hybrid(base: DataFrame, edges: DataFrame, queries: DataFrame, cache: DataFrame, k: int, beam: int, metric: str = "cosine") -> DataFrame:
    """(query_id, rank, vec_id, dist, cached): exact repeats from the cache, the rest by walks."""
    hits, misses = cache_split(queries, cache)
    stored = hits.select("query_id", F.posexplode(F.arrays_zip("ids", "dists")).alias("p", "a")).select("query_id", (F.col("p") + 1).alias("rank"), F.col("a.ids").alias("vec_id"), F.col("a.dists").alias("dist"), F.lit(True).alias("cached")).where(F.col("rank") <= k)
    walked = S.sharded(base, edges, misses, k, beam, metric).select("query_id", "rank", "vec_id", "dist", F.lit(False).alias("cached"))
    return stored.unionByName(walked)


def lookup_times(queries: DataFrame, cache: DataFrame, part_bytes: int = 64 << 20) -> DataFrame:
    """(n, cache_us): mean microseconds to make a query's key and to find its answer in a dictionary, one a range of keys.

    Queries and answers are dealt by key to as many tasks as keep a dictionary and its queries small.
    """
    import numpy as np
    import pandas as pd

    held = (cache.agg(F.sum(F.length("vec_canon") + 16 * F.size("ids"))).first()[0] or 0) + (queries.agg(F.sum(8 * F.size("vec"))).first()[0] or 0)
    parts = int(held // part_bytes) + 1
    by = F.pmod(F.xxhash64("key_md5"), F.lit(parts)).alias("part")
    asked = queries.select(by, F.lit(None).cast("string").alias("key_md5"), "vec", F.lit(None).cast("array<bigint>").alias("ids"))
    stored = cache.select(by, "key_md5", F.lit(None).cast("array<double>").alias("vec"), "ids")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        import hashlib
        from time import perf_counter

        known = pdf["key_md5"].notna().to_numpy()
        table = dict(zip(pdf["key_md5"][known], pdf["ids"][known], strict=True))
        vecs = [np.asarray(v) for v in pdf["vec"][~known]]
        began, found = perf_counter(), 0
        for v in vecs:
            key = hashlib.md5(",".join(map(str, np.floor(v * 1e6 + 0.5).astype(np.int64).tolist())).encode()).hexdigest()
            found += table.get(key) is not None
        return pd.DataFrame({"n": [len(vecs)], "found": [found], "us": [1e6 * (perf_counter() - began)]})

    rows = asked.unionByName(stored).groupBy("part").applyInPandas(run, "n bigint, found bigint, us double")
    return rows.agg(F.sum("n").alias("n"), F.sum("found").alias("found"), (F.sum("us") / F.sum("n")).alias("cache_us"))


def similarity_bands(test: DataFrame, history: DataFrame, cuts: tuple[float, float] = (0.05, 0.1), metric: str = "cosine") -> DataFrame:
    """(query_id, gap, band): distance to the nearest history query and its band."""
    near = T.exact_blocked(history.select(F.col("query_id").alias("vec_id"), "vec"), test, 1, metric)
    band = F.when(F.col("dist") <= cuts[0], "high").when(F.col("dist") <= cuts[1], "moderate").otherwise("low")
    return near.select("query_id", F.col("dist").alias("gap"), band.alias("band"))


def assign_beam(banded: DataFrame, table: dict[str, int]) -> DataFrame:
    beam = F.coalesce(*[F.when(F.col("band") == k, v) for k, v in table.items()])
    return banded.withColumn("beam", beam)


def calibrate(curves: DataFrame, want: float) -> dict[str, int]:
    """Smallest beam of each band whose mean recall is as wanted, from (band, beam, recall)."""
    rows = curves.where(F.col("recall") >= want).groupBy("band").agg(F.min("beam").alias("beam")).collect()
    return {r["band"]: r["beam"] for r in rows}


# --- drift, containment, distribution distances ---------------------------------------


def novelty(old: DataFrame, new: DataFrame, threshold: float, metric: str = "cosine") -> DataFrame:
    """(n_new, n_novel, share): new queries farther than the threshold from every older one."""
    near = T.exact_blocked(old.select(F.col("query_id").alias("vec_id"), "vec"), new, 1, metric)
    return near.agg(F.count(F.lit(1)).alias("n_new"), F.count_if(F.col("dist") > threshold).alias("n_novel")).withColumn("share", F.col("n_novel") / F.col("n_new"))


def containment(test_truth: DataFrame, history_truth: DataFrame, k: int, wide: int) -> DataFrame:
    """(test_id, history_id, equal): pairs whose top-k is contained in the other's top-``wide``; equal if in its top-k.

    ``containment_gaps`` adds how far apart the two queries are.
    """
    t = test_truth.where(F.col("rank") <= k).select(F.col("query_id").alias("test_id"), "vec_id")
    h = history_truth.where(F.col("rank") <= wide).select(F.col("query_id").alias("history_id"), "vec_id", F.col("rank").alias("hr"))
    both = t.join(h, "vec_id").groupBy("test_id", "history_id").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("hr") <= k).alias("n_k"))
    return both.where(F.col("n") == k).select("test_id", "history_id", (F.col("n_k") == k).alias("equal"))


def containment_gaps(pairs: DataFrame, test: DataFrame, history: DataFrame, metric: str = "cosine") -> DataFrame:
    """(test_id, history_id, equal, gap): contained pairs with the distance between their queries."""
    t = test.select(F.col("query_id").alias("test_id"), F.col("vec").alias("tv"))
    h = history.select(F.col("query_id").alias("history_id"), F.col("vec").alias("hv"))
    return pairs.join(t, "test_id").join(h, "history_id").select("test_id", "history_id", "equal", V.distance(F.col("tv"), F.col("hv"), metric).alias("gap"))


def by_modality(queries: DataFrame, base: DataFrame) -> DataFrame:
    """(query_id, modality, ood): a query is out of distribution if no base row has its modality."""
    own = base.select("modality").distinct().withColumn("known", F.lit(True))
    return queries.join(own, "modality", "left").select("query_id", "modality", F.col("known").isNull().alias("ood"))


def ball_union(test: DataFrame, history: DataFrame, history_truth: DataFrame, eps: float, k: int, metric: str = "cosine") -> DataFrame:
    """(query_id, n_history, n_union): history queries within eps of a test query and the size of the union of their top-k."""
    near = T.within(history.select(F.col("query_id").alias("vec_id"), "vec"), test, eps, metric).select("query_id", F.col("vec_id").alias("hist"))
    tops = history_truth.where(F.col("rank") <= k).select(F.col("query_id").alias("hist"), "vec_id")
    return near.join(tops, "hist").groupBy("query_id").agg(F.countDistinct("hist").alias("n_history"), F.countDistinct("vec_id").alias("n_union"))


def profile(base: DataFrame, vec: str = "vec") -> DataFrame:
    """(j, n, mean, var): moments of each coordinate."""
    return base.select(F.posexplode(vec).alias("j", "x")).groupBy("j").agg(F.count("x").alias("n"), F.avg("x").alias("mean"), F.var_pop("x").alias("var"))


def mahalanobis_diagonal(queries: DataFrame, base_profile: DataFrame, ridge: float = 0.0) -> DataFrame:
    """(query_id, distance) to a distribution by its diagonal covariance."""
    cells = queries.select("query_id", F.posexplode("vec").alias("j", "x")).join(base_profile, "j")
    return cells.groupBy("query_id").agg(F.sqrt(F.sum(F.pow(F.col("x") - F.col("mean"), 2) / (F.col("var") + ridge))).alias("distance"))


def mahalanobis(queries: DataFrame, base: DataFrame, ridge: float = 1e-6) -> DataFrame:
    """(query_id, distance) by the full covariance: sums of outer products in the tasks, a dim x dim inverse on the driver."""
    import numpy as np
    import pandas as pd

    def sums(batches):
        n, s, c = 0, 0.0, 0.0
        for pdf in batches:
            if len(pdf):
                x = np.stack(pdf["vec"].to_numpy())
                n, s, c = n + len(x), s + x.sum(0), c + x.T @ x
        if n:
            yield pd.DataFrame({"n": [n], "s": [s.tolist()], "c": [c.ravel().tolist()]})

    parts = base.select("vec").mapInPandas(sums, "n bigint, s array<double>, c array<double>").collect()
    n = sum(r["n"] for r in parts)
    mean = sum(np.array(r["s"]) for r in parts) / n
    d = len(mean)
    cov = sum(np.array(r["c"]) for r in parts).reshape(d, d) / n - np.outer(mean, mean)
    inverse = np.linalg.inv(cov + ridge * np.eye(d))

    def far(batches):
        for pdf in batches:
            x = np.stack(pdf["vec"].to_numpy()) - mean if len(pdf) else np.zeros((0, d))
            yield pd.DataFrame({"query_id": pdf["query_id"], "distance": np.sqrt(np.maximum(np.einsum("ij,jk,ik->i", x, inverse, x), 0))})

    return queries.select("query_id", "vec").mapInPandas(far, "query_id bigint, distance double")


def wasserstein_1d(a: DataFrame, b: DataFrame, j: int, steps: int = 50) -> DataFrame:
    """(distance): mean gap between the quantiles of one coordinate of two sets, at ``steps`` levels."""
    levels = [(i + 0.5) / steps for i in range(steps)]
    qa, qb = (df.agg(F.percentile(F.get("vec", F.lit(j)), F.array(*[F.lit(x) for x in levels])).alias("q")) for df in (a, b))
    both = qa.withColumnRenamed("q", "qa").join(qb, how="cross")
    return both.select((F.aggregate(F.zip_with("qa", "q", lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x) / steps).alias("distance"))




def sliced_wasserstein(a: DataFrame, b: DataFrame, n_proj: int = 16, steps: int = 50, seed: int = 0, accuracy: int | None = None) -> DataFrame:
    """(direction, distance): gaps between the quantiles of two sets along directions with signs from md5, one pass over each set.

    Exact quantiles keep a direction's distinct values in one task; ``accuracy`` takes sketches of bounded size instead.
    """
    dim = V.assert_dim(a)
    signs = F.transform(F.sequence(F.lit(0), F.lit(dim - 1)), lambda j: F.when(V.hash32(F.concat_ws(":", F.lit(str(seed)), F.col("direction").cast("string"), j.cast("string"))) % 2 == 0, 1.0).otherwise(-1.0) / math.sqrt(dim))
    lines = a.sparkSession.range(n_proj).select(F.col("id").cast("int").alias("direction")).withColumn("line", signs)
    levels = F.array(*[F.lit((i + 0.5) / steps) for i in range(steps)])

    def quantiles(df: DataFrame, name: str) -> DataFrame:
        shadow = df.select("vec").join(F.broadcast(lines), how="cross").select("direction", V.dot(F.col("vec"), F.col("line")).alias("x"))
        got = F.percentile("x", levels) if accuracy is None else F.percentile_approx("x", levels, accuracy)
        return shadow.groupBy("direction").agg(got.alias(name))

    both = quantiles(a, "qa").join(quantiles(b, "qb"), "direction")
    return both.select("direction", (F.aggregate(F.zip_with("qa", "qb", lambda x, y: F.abs(x - y)), F.lit(0.0), lambda s, x: s + x) / steps).alias("distance"))


def sinkhorn(a: DataFrame, b: DataFrame, blur: float = 0.05, rounds: int = 200, block: int = 1024, cells: int = 1 << 19, many: int = 1 << 27) -> DataFrame:
    """(n_a, n_b, distance): entropic transport cost between all rows of two sets.

    The rows of ``b`` are broadcast in blocks of bounded size.  A round is one pass over ``a``, all tasks side by side: a task finds the potential
    of its rows and sums each row of ``b`` over them; the driver merges one number a row of ``b`` and task.
    Distances and exponentials of about ``cells`` pairs are found once a round, and serve both sums.

    After ``PLAIN`` rounds the next potentials are mixed from the last ones (``mixed``), which has the same fixed point and gets there in fewer rounds.
    From ``many`` pairs on, rounds are in single precision while that brings the potentials on; those after them, which decide the
    result, and the cost itself are in double precision.
    """
    import numpy as np
    import pyarrow as pa

    spark = a.sparkSession
    x = R.cut(a.select("vec"))
    blocks = T.query_blocks(b.select("vec").withColumn("query_id", F.lit(0).cast("bigint")))
    sizes, shared = [], []
    for _, vecs, _ in blocks:
        sizes.append(len(vecs))
        shared.append(spark.sparkContext.broadcast(vecs))
    n_a, n_b = x.count(), sum(sizes)
    schema = "n_a bigint, n_b bigint, distance double"
    if not n_a or not n_b:
        return spark.createDataFrame([(n_a, n_b, None)], schema)
    few = min(block, max(16, cells // n_b))
    x = R.cut(x.repartition(max(1, min(spark.sparkContext.defaultParallelism, n_a * n_b >> 20))))
    ends = np.cumsum(sizes).tolist()

    def merged(top, total, new_top, new_total):
        up = np.maximum(top, new_top)
        return up, total * np.exp(top - up) + new_total * np.exp(new_top - up)

    def one_pass(g, last, kind=np.float64):
        sent = spark.sparkContext.broadcast(g)

        def run(batches):
            g = sent.value
            top, total, cost = np.full(n_b, -np.inf), np.zeros(n_b), 0.0
            seen, sums, held = False, np.zeros(n_b), {}

            def gaps(rows, kind):
                """Distances to all rows of b: squares by one product a block, with the squared lengths as two more coordinates."""
                if kind not in held:
                    others = [np.hstack([-2.0 * y.value, (y.value**2).sum(1)[:, None], np.ones((len(y.value), 1))]).astype(kind) for y in shared]
                    held[kind] = others, np.empty((few, n_b), dtype=kind)
                others, room = held[kind]
                own, d = np.hstack([rows, np.ones((len(rows), 1)), (rows**2).sum(1)[:, None]]).astype(kind), room[: len(rows)]
                for y, end in zip(others, ends, strict=True):
                    d[:, end - len(y) : end] = own @ y.T
                np.maximum(d, 0, out=d)
                return np.sqrt(d, out=d)

            scaled, ones = (g / blur).astype(kind), np.ones(n_b, dtype=kind)
            for batch in batches:
                vecs = batch.column(0).to_numpy(zero_copy_only=False)
                for i in range(0, len(vecs), few):
                    rows = np.stack(vecs[i : i + few]).astype(np.float64)
                    seen = True
                    m = gaps(rows, kind)
                    c = m.copy() if last else None
                    m *= kind(-1.0 / blur)
                    m += scaled
                    high = m.max(1)
                    m -= high[:, None]
                    np.exp(m, out=m)
                    own = m @ ones
                    if last:  # exp((f + g - c) / blur) is n_b of each row's share
                        cost += float(((m * c).sum(1) / own).sum() * n_b)
                        continue
                    # exp((f - c) / blur) is n_b of a row's share, times exp(-g / blur)
                    by_row = m.T @ (n_b / own)
                    if by_row.min() > (1e-200 if kind is np.float64 else 1e-25):
                        sums += by_row
                        continue
                    f = -blur * (high + np.log(own / n_b))
                    m = (f[:, None] - gaps(rows, np.float64)) / blur
                    high = m.max(0)
                    top, total = merged(top, total, high, np.exp(m - high[None, :]).sum(0))
            if seen:
                if sums.any():
                    top, total = merged(top, total, -g / blur, sums)
                yield pa.RecordBatch.from_arrays([pa.array([top.tobytes()], pa.binary()), pa.array([total.tobytes()], pa.binary()), pa.array([cost])], names=["top", "total", "cost"])

        top, total, cost = np.full(n_b, -np.inf), np.zeros(n_b), 0.0
        for r in x.mapInArrow(run, "top binary, total binary, cost double").collect():
            cost += r["cost"]
            if not last:
                top, total = merged(top, total, np.frombuffer(r["top"]), np.frombuffer(r["total"]))
        sent.unpersist()
        return cost / (n_a * n_b) if last else -blur * (top + np.log(total / n_a))

    g, past, best, at, kind = np.zeros(n_b), [], np.inf, 0, np.float32 if n_a * n_b >= many else np.float64
    for n in range(rounds):
        now = one_pass(g, False, kind)
        change = np.abs(now - g).max()
        if change < 1e-9 * blur:  # further rounds change nothing
            g = now
            break
        if kind is np.float32 and (change < 3e-5 * blur or n - at >= PLAIN or n >= rounds // 2):
            g, kind, past, best = now, np.float64, [], np.inf
            continue
        if change > 10 * best:  # the mix has led away
            past = []
        best, at = (change, n) if change < best else (best, at)
        past = [*past, (now, now - g)][-DEPTH - 1 :] if n >= PLAIN else []
        g = now if n == rounds - 1 else mixed(past, now)
    return spark.createDataFrame([(n_a, n_b, float(one_pass(g, True)))], schema)


#: Rounds of ``sinkhorn`` before potentials are mixed, and how many earlier ones are mixed in.
PLAIN, DEPTH = 10, 10


def mixed(past: list, now):
    """The sum of the last potentials, by weights that add up to one, whose changes cancel out best; ``past`` has (potentials, change) of each round."""
    import numpy as np

    if len(past) < 2:
        return now
    (_, change), earlier = past[-1], past[:-1]
    weights = np.linalg.lstsq(np.stack([c - change for _, c in earlier], axis=1), -change, rcond=1e-10)[0]
    return now + np.stack([p - now for p, _ in earlier], axis=1) @ weights


def from_training(history: DataFrame, training: DataFrame) -> DataFrame:
    """(query_id, vec, origin): history with training queries whose keys it lacks; one row a key, the smallest id first."""
    both = history.select("query_id", "vec", F.lit("history").alias("origin")).unionByName(training.select("query_id", "vec", F.lit("training").alias("origin")))
    least = both.groupBy(V.key_md5(F.col("vec")).alias("k")).agg(F.min(F.struct("origin", "query_id", "vec")).alias("r"))
    return least.select("r.query_id", "r.vec", "r.origin")
