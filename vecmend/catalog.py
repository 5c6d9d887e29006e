"""Registered queries of the graph engine and the DuckDB SQL that checks them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import vectors as V
from .operators import graph as G
from .operators import joins as J
from .operators import mend as M
from .operators import metrics as E
from .operators import search as S
from .operators import truth as T
from .operators import upkeep as U
from .operators import vicinity as N
from .plans import experiments as X
from .plans import rounds as R
from .sources import families as D
from .streaming import online as O

#: Scaled-down parameters of the registered queries.
K, NEAR, MAX_RANK, DEGREE = 10, 6, 30, 6

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def _query(sql: str | None = None):
    def register(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return register


def _r(c: str, alias: str | None = None):
    return F.round(c, 6).alias(alias or c)


# --- SQL pieces ----------------------------------------------------------------------

_U = "('0x' || substr(md5({0}), 1, 8))::BIGINT"
_BASE = f"""
g AS (SELECT [CASE WHEN {_U.format('j::VARCHAR')} % 2 = 0 THEN 0.125 ELSE -0.125 END::DOUBLE FOR j IN range(64)] AS g),
base AS (SELECT vec_id, embedding::DOUBLE[] AS vec, label FROM embeddings WHERE vec_id % 10 < 7),
q0 AS (SELECT vec_id AS query_id, [embedding[i]::DOUBLE + 0.6::DOUBLE * g[i] FOR i IN range(1, 65)] AS w, CASE WHEN vec_id % 10 = 9 THEN 'test' ELSE 'history' END AS role FROM embeddings, g WHERE vec_id % 10 >= 7),
q AS (SELECT query_id, role, [x / sqrt(list_inner_product(w, w)) FOR x IN w] AS vec FROM q0)"""
_COS = "1 - list_inner_product({0}, {1}) / (sqrt(list_inner_product({0}, {0})) * sqrt(list_inner_product({1}, {1})))"


def _truth_cte(k: int, role: str, metric: str = _COS, base: str = "base", name: str = "truth") -> str:
    return f"{name} AS (SELECT * FROM (SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id))::INT AS rank, vec_id, dist FROM (SELECT query_id, b.vec_id, {metric.format('b.vec', 'q.vec')} AS dist FROM q, {base} b WHERE role = '{role}')) WHERE rank <= {k})"


_KNN = f"knn AS (SELECT * FROM (SELECT src, dst, (row_number() OVER (PARTITION BY src ORDER BY dist, dst))::INT AS rank, dist FROM (SELECT a.vec_id AS src, b.vec_id AS dst, {_COS.format('b.vec', 'a.vec')} AS dist FROM base a, base b WHERE a.vec_id <> b.vec_id)) WHERE rank <= {DEGREE})"
_VIC = "vic AS (SELECT s.query_id, s.rank AS src_rank, d.rank AS dst_rank FROM truth s JOIN knn e ON e.src = s.vec_id JOIN truth d ON d.query_id = s.query_id AND d.vec_id = e.dst)"
_HARD = f"""
reach(query_id, i, j, b) AS (SELECT query_id, src_rank, dst_rank, greatest(src_rank, dst_rank) FROM vic UNION SELECT r.query_id, r.i, v.dst_rank, greatest(r.b, v.dst_rank) FROM reach r JOIN vic v ON v.query_id = r.query_id AND v.src_rank = r.j),
best AS (SELECT query_id, i, j, min(b) AS h FROM reach GROUP BY ALL),
hard AS (SELECT a.query_id, a.rank AS i, c.rank AS j, CASE WHEN a.rank = c.rank THEN a.rank ELSE coalesce(h, 32767) END AS h FROM truth a JOIN truth c ON a.query_id = c.query_id AND a.rank <= {NEAR} AND c.rank <= {NEAR} LEFT JOIN best ON best.query_id = a.query_id AND best.i = a.rank AND best.j = c.rank)"""
_MEND = f"""
pairs AS (SELECT h.query_id, h.i, h.j, h.h, {_COS.format('x.vec', 'y.vec')} AS gap, a.vec_id AS src, b.vec_id AS dst FROM hard h JOIN truth a ON a.query_id = h.query_id AND a.rank = h.i JOIN truth b ON b.query_id = h.query_id AND b.rank = h.j JOIN base x ON x.vec_id = a.vec_id JOIN base y ON y.vec_id = b.vec_id),
bad AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY round(gap, 12), i, j) AS n FROM pairs WHERE h > {NEAR}),
start AS (SELECT query_id, list(h <= {NEAR} ORDER BY i, j) AS ok FROM hard GROUP BY query_id),
steps(query_id, n, ok, added) AS (
  SELECT query_id, 0::BIGINT, ok, FALSE FROM start
  UNION ALL
  SELECT s.query_id, b.n, CASE WHEN s.ok[(b.i - 1) * {NEAR} + b.j] THEN s.ok ELSE [s.ok[x + 1] OR (s.ok[(x // {NEAR}) * {NEAR} + b.i] AND (s.ok[(b.j - 1) * {NEAR} + x % {NEAR} + 1] OR x % {NEAR} + 1 = b.j)) FOR x IN range({NEAR * NEAR})] END, NOT s.ok[(b.i - 1) * {NEAR} + b.j]
  FROM steps s JOIN bad b ON b.query_id = s.query_id AND b.n = s.n + 1),
added AS (SELECT b.query_id, b.src, b.dst, b.h AS hardness, b.n FROM steps s JOIN bad b ON b.query_id = s.query_id AND b.n = s.n WHERE s.added),
props AS (SELECT query_id, src, dst, hardness, query_id * 100000 + row_number() OVER (PARTITION BY query_id ORDER BY n) - 1 AS seq FROM added)"""


def _with(*ctes: str, recursive: bool = False) -> str:
    return f"WITH {'RECURSIVE ' if recursive else ''}{', '.join(c.strip() for c in ctes)} "


_SEEN = _truth_cte(MAX_RANK, "history")
_CHAIN = (_BASE, _SEEN, _KNN, _VIC)


def _ws(spark: SparkSession, d: str, role: str | None = None, ood: bool = True):
    base, q = D.sphere(spark, d, ood)
    return base, q if role is None else q.where(F.col("role") == role)


def _frozen(spark: SparkSession, d: str):
    base, history = _ws(spark, d, "history")
    truth = R.cut(T.exact_blocked(base, history, MAX_RANK))
    edges = R.cut(G.as_edges(G.knn(base, DEGREE)))
    return base, history, truth, edges


# --- vectors and ground truth ----------------------------------------------------------


@_query(_with(_BASE) + "SELECT count(*) AS n, min(len(vec))::INT AS dim_min, max(len(vec))::INT AS dim_max, round(avg(sqrt(list_inner_product(vec, vec))), 6) AS mean_norm FROM base")
def vec_profile(spark, d):
    base, _ = _ws(spark, d)
    return base.select(F.size("vec").alias("dim"), V.norm(F.col("vec")).alias("norm")).agg(F.count(F.lit(1)).alias("n"), F.min("dim").alias("dim_min"), F.max("dim").alias("dim_max"), F.round(F.avg("norm"), 6).alias("mean_norm"))


@_query(_with(_BASE) + "SELECT j::INT AS j, round(avg(vec[j + 1]), 6) AS mean, round(var_pop(vec[j + 1]), 6) AS var FROM base, range(64) t(j) GROUP BY j")
def centroid_dims(spark, d):
    return U.profile(_ws(spark, d)[0]).select("j", _r("mean"), _r("var"))


@_query(_with(_BASE, "c AS (SELECT list(m ORDER BY j) AS c FROM (SELECT j, avg(vec[j + 1]) AS m FROM base, range(64) t(j) GROUP BY j))") + f"SELECT vec_id FROM base, c ORDER BY {_COS.format('vec', 'c')}, vec_id LIMIT 1")
def entry_centroid(spark, d):
    base, _ = _ws(spark, d)
    return spark.createDataFrame([(S.entry_centroid(base),)], "vec_id bigint")


def _knn_query(name: str, metric: str, sql: str, blocked: bool) -> None:
    def run(spark, d):
        base, q = _ws(spark, d, "test")
        return (T.exact_blocked if blocked else T.exact_sql)(base, q, K, metric).select("query_id", "rank", "vec_id", _r("dist"))

    run.__name__ = name
    _query(_with(_BASE, _truth_cte(K, "test", sql)) + "SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")(run)


_knn_query("knn_cosine", "cosine", _COS, False)
_knn_query("knn_ip", "ip", "1 - list_inner_product({0}, {1})", False)
_knn_query("knn_l2", "l2", "list_distance({0}, {1})", False)
_knn_query("knn_blocked", "cosine", _COS, True)
_knn_query("knn_blocked_l2", "l2", "list_distance({0}, {1})", True)


@_query(_with(_BASE, "few AS (SELECT * FROM base WHERE label < 3)", _truth_cte(K, "test", base="few")) + "SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")
def knn_filtered(spark, d):
    base, q = _ws(spark, d, "test")
    return S.filtered(base, None, q, F.col("label") < 3, K, K, mode="pre").select("query_id", "rank", "vec_id", _r("dist"))


@_query(_with(_BASE) + f"SELECT query_id, vec_id, round({_COS.format('b.vec', 'q.vec')}, 6) AS dist FROM q, base b WHERE role = 'test' AND {_COS.format('b.vec', 'q.vec')} <= 0.8")
def radius_join(spark, d):
    base, q = _ws(spark, d, "test")
    return T.within(base, q, 0.8).select("query_id", "vec_id", _r("dist"))


_PREFIX = f"pb AS (SELECT vec_id, vec[1:32] AS vec FROM base), pq AS (SELECT query_id, role, vec[1:32] AS vec FROM q), approx AS (SELECT * FROM (SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY p, vec_id))::INT AS rank, vec_id, dist FROM (SELECT pq.query_id, pb.vec_id, {_COS.format('pb.vec', 'pq.vec')} AS p, {_COS.format('b.vec', 'q.vec')} AS dist FROM pq JOIN q ON q.query_id = pq.query_id, pb JOIN base b ON b.vec_id = pb.vec_id WHERE q.role = 'test')) WHERE rank <= {K})"
_RECALL = f"rec AS (SELECT t.query_id, sum(CASE WHEN a.vec_id IS NULL THEN 0 ELSE 1 END) / count(*) AS recall FROM truth t LEFT JOIN approx a ON a.query_id = t.query_id AND a.vec_id = t.vec_id GROUP BY t.query_id)"


def _approximate(spark, d):
    base, q = _ws(spark, d, "test")
    half = T.exact_blocked(base.withColumn("vec", V.prefix(F.col("vec"), 32)), q.withColumn("vec", V.prefix(F.col("vec"), 32)), K).drop("dist")
    full = half.join(base.select("vec_id", "vec"), "vec_id").join(q.select("query_id", F.col("vec").alias("qvec")), "query_id")
    return full.select("query_id", "rank", "vec_id", V.distance(F.col("vec"), F.col("qvec")).alias("dist")), T.exact_blocked(base, q, K)


@_query(_with(_BASE, _truth_cte(K, "test"), _PREFIX, _RECALL) + "SELECT query_id, round(recall, 6) AS recall FROM rec")
def approx_prefix_recall(spark, d):
    results, truth = _approximate(spark, d)
    return E.recall_by_query(results, truth, K).select("query_id", _r("recall"))


@_query(_with(_BASE, _truth_cte(K, "test"), _PREFIX) + "SELECT t.query_id, round(avg(a.dist / t.dist - 1), 6) AS rderr FROM truth t JOIN approx a ON a.query_id = t.query_id AND a.rank = t.rank GROUP BY t.query_id")
def approx_prefix_rderr(spark, d):
    results, truth = _approximate(spark, d)
    return E.rderr(results, truth, K).select("query_id", _r("rderr"))


@_query(_with(_BASE, _truth_cte(K, "test"), _PREFIX, _RECALL) + "SELECT band, n_queries, round(n_queries / sum(n_queries) OVER (), 6) AS share FROM (SELECT CASE WHEN recall = 0 THEN 0 ELSE ceil(recall * 5)::INT END AS band, count(*) AS n_queries FROM rec GROUP BY 1)")
def recall_bands(spark, d):
    results, truth = _approximate(spark, d)
    return E.bands(E.recall_by_query(results, truth, K)).select("band", "n_queries", _r("share"))


@_query(_with(_BASE, _truth_cte(K, "test"), _PREFIX, _truth_cte(K + 1, "test", name="wide")) + """SELECT a.query_id, bool_and(a.dist <= 1.2 * b + 1e-12) AS ok
FROM approx a JOIN (SELECT w.query_id, min(w.dist) AS b FROM wide w ANTI JOIN approx x ON x.query_id = w.query_id AND x.vec_id = w.vec_id GROUP BY 1) o ON o.query_id = a.query_id GROUP BY 1""")
def epsilon_answers(spark, d):
    results, _ = _approximate(spark, d)
    base, q = _ws(spark, d, "test")
    return E.epsilon_answers(results, T.exact_blocked(base, q, K + 1), K, 0.2)


# --- graphs ----------------------------------------------------------------------------


@_query(_with(_BASE, _KNN) + "SELECT src, dst, rank, round(dist, 6) AS dist FROM knn")
def graph_knn(spark, d):
    return G.knn(_ws(spark, d)[0], DEGREE).select("src", "dst", "rank", _r("dist"))


_PAIRS = f"pair AS MATERIALIZED (SELECT a.vec_id AS src, b.vec_id AS dst, {_COS.format('b.vec', 'a.vec')} AS dist FROM base a, base b WHERE a.vec_id <> b.vec_id)"


@_query(_with(_BASE, _PAIRS) + "SELECT src, dst FROM pair p WHERE NOT EXISTS (SELECT 1 FROM pair a JOIN pair b ON a.dst = b.dst AND b.src = p.dst WHERE a.src = p.src AND a.dst <> p.dst AND greatest(a.dist, b.dist) < p.dist - 1e-12)")
def graph_rng(spark, d):
    return G.rng(_ws(spark, d)[0]).select("src", "dst")


def _thin_sql(test: str) -> str:
    wide = _KNN.replace(f"rank <= {DEGREE}", "rank <= 20")
    return _with(_BASE, _PAIRS, wide, f"""keep(src, rank, kept) AS (
  SELECT src, 0, []::BIGINT[] FROM knn WHERE rank = 1
  UNION ALL
  SELECT k.src, k.rank, CASE WHEN len(t.kept) < 6 AND NOT EXISTS (SELECT 1 FROM pair p WHERE p.src = k.dst AND list_contains(t.kept, p.dst) AND {test}) THEN list_append(t.kept, k.dst) ELSE t.kept END
  FROM keep t JOIN knn k ON k.src = t.src AND k.rank = t.rank + 1)""", recursive=True) + "SELECT src, unnest(kept) AS dst FROM keep WHERE rank = 20"


@_query(_thin_sql("p.dist <= k.dist"))
def graph_mrng(spark, d):
    base, _ = _ws(spark, d)
    return G.thinned(G.knn(base, 20), base, 6)


@_query(_thin_sql("p.dist < k.dist - 3 * 0.01"))
def graph_tau_thinned(spark, d):
    base, _ = _ws(spark, d)
    return G.thinned(G.knn(base, 20), base, 6, slack=0.01)


@_query(_with(_BASE, _KNN) + "SELECT src, dst FROM knn UNION SELECT dst, src FROM knn")
def graph_symmetrized(spark, d):
    return G.symmetrize(G.knn(_ws(spark, d)[0], DEGREE))


@_query(_with(_BASE, _KNN) + "SELECT degree, count(*) AS n FROM (SELECT dst, count(*) AS degree FROM knn GROUP BY dst) GROUP BY degree")
def in_degree_histogram(spark, d):
    return G.knn(_ws(spark, d)[0], DEGREE).groupBy("dst").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


@_query(_with(_BASE, _KNN.replace(f"rank <= {DEGREE}", "rank <= 1"), "s AS (SELECT src, dst FROM knn UNION SELECT dst, src FROM knn)", "r(node, other) AS (SELECT src, dst FROM s UNION SELECT r.node, s.dst FROM r JOIN s ON s.src = r.other)", recursive=True) + "SELECT node, least(node, min(other)) AS component FROM r GROUP BY node")
def graph_components(spark, d):
    return G.components(G.knn(_ws(spark, d)[0], 1)).select("node", "component")


# --- vicinity and hardness ---------------------------------------------------------------


@_query(_with(*_CHAIN) + "SELECT * FROM vic")
def vicinity_edges(spark, d):
    _, _, truth, edges = _frozen(spark, d)
    return N.extract(truth, edges, MAX_RANK)


@_query(_with(*_CHAIN) + "SELECT t.query_id, count(*) FILTER (NOT EXISTS (SELECT 1 FROM vic v WHERE v.query_id = t.query_id AND (v.src_rank = t.rank OR v.dst_rank = t.rank))) AS n_isolated FROM truth t GROUP BY 1")
def vicinity_isolated(spark, d):
    _, _, truth, edges = _frozen(spark, d)
    return N.isolated(truth, N.extract(truth, edges, MAX_RANK), MAX_RANK)


@_query(_with(*_CHAIN, "r(query_id, i, j) AS (SELECT query_id, src_rank, dst_rank FROM vic UNION SELECT r.query_id, r.i, v.dst_rank FROM r JOIN vic v ON v.query_id = r.query_id AND v.src_rank = r.j)", recursive=True) + f"SELECT t.query_id, round(1 + coalesce(n, 0) / {MAX_RANK}, 6) AS mean_reachable FROM (SELECT DISTINCT query_id FROM truth) t LEFT JOIN (SELECT query_id, count(*) AS n FROM r WHERE i <> j GROUP BY 1) c ON c.query_id = t.query_id")
def vicinity_reachable(spark, d):
    _, _, truth, edges = _frozen(spark, d)
    return N.mean_reachable(truth, N.extract(truth, edges, MAX_RANK), MAX_RANK).select("query_id", _r("mean_reachable"))


def _hard(spark, d):
    _, _, truth, edges = _frozen(spark, d)
    return truth, N.extract(truth, edges, MAX_RANK)


_HARD_SQL = _with(*_CHAIN, _HARD, recursive=True)


@_query(_HARD_SQL + "SELECT query_id, i, j, h FROM hard")
def hardness_matrix(spark, d):
    return N.hardness(*_hard(spark, d), NEAR, MAX_RANK)


@_query(_HARD_SQL + "SELECT query_id, i, j, h FROM hard")
def hardness_fixpoint(spark, d):
    return N.hardness_fixpoint(*_hard(spark, d), NEAR, MAX_RANK)


@_query(_HARD_SQL + f"SELECT query_id, i, j, h <= {NEAR} AS ok FROM hard")
def ok_matrix(spark, d):
    return N.ok_pairs(N.hardness(*_hard(spark, d), NEAR, MAX_RANK), NEAR).select("query_id", "i", "j", "ok")


@_query(_HARD_SQL + f"SELECT query_id, max(h) AS max_h, round(avg(h) FILTER (h < 32767), 6) AS mean_h, count(*) FILTER (h = 32767) AS n_never, count(*) FILTER (h > {NEAR}) AS n_bad FROM hard GROUP BY 1")
def hardness_summary(spark, d):
    return N.summary(N.hardness(*_hard(spark, d), NEAR, MAX_RANK), NEAR).select("query_id", "max_h", _r("mean_h"), "n_never", "n_bad")


# --- mending -------------------------------------------------------------------------------

_MEND_SQL = _with(*_CHAIN, _HARD, _MEND, recursive=True)


def _proposals(spark, d, method="vicinity"):
    base, _, truth, edges = _frozen(spark, d)
    return M.vicinity(truth, edges, base, NEAR, NEAR, MAX_RANK, method=method), edges


@_query(_MEND_SQL + "SELECT query_id, seq, src, dst, hardness FROM props")
def mend_frozen(spark, d):
    return _proposals(spark, d)[0].select("query_id", "seq", "src", "dst", "hardness")


@_query(_MEND_SQL + f"SELECT query_id, count(*) AS n_arcs, count(*) <= {2 * (NEAR - 1)} AS in_bound FROM props GROUP BY 1")
def mend_edge_counts(spark, d):
    return _proposals(spark, d)[0].groupBy("query_id").agg(F.count(F.lit(1)).alias("n_arcs")).withColumn("in_bound", F.col("n_arcs") <= 2 * (NEAR - 1))


@_query(_MEND_SQL + "SELECT src, dst, hardness FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY hardness DESC, seq, dst) AS r FROM (SELECT src, dst, max(hardness) AS hardness, min(seq) AS seq FROM props GROUP BY 1, 2)) p WHERE r <= 4")
def admit_cap(spark, d):
    proposals, edges = _proposals(spark, d)
    return M.admit(edges, proposals, 4).where("kind = 'extra'").select("src", "dst", "hardness")


_ADMITTED = """keep1 AS (SELECT src, dst, hardness, seq FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY hardness DESC, seq, dst) AS r FROM (SELECT p.src, p.dst, max(hardness) AS hardness, min(seq) AS seq FROM props p ANTI JOIN knn k ON k.src = p.src AND k.dst = p.dst GROUP BY 1, 2)) WHERE r <= 4)"""


@_query(_with(*_CHAIN, _HARD, _MEND, _ADMITTED, recursive=True) + "SELECT degree, count(*) AS n FROM (SELECT b.vec_id, count(e.src) AS degree FROM base b LEFT JOIN (SELECT src, dst FROM knn UNION ALL SELECT src, dst FROM keep1) e ON e.src = b.vec_id GROUP BY 1) GROUP BY 1")
def degree_histogram(spark, d):
    proposals, edges = _proposals(spark, d)
    return E.out_degrees(M.admit(edges, proposals, 4), _ws(spark, d)[0])


@_query(_with(*_CHAIN, f"near AS (SELECT t.query_id, t.rank, t.vec_id, b.vec FROM truth t JOIN base b ON b.vec_id = t.vec_id WHERE rank <= {NEAR})", f"gap AS (SELECT a.query_id, a.rank AS i, b.rank AS j, a.vec_id AS src, b.vec_id AS dst, {_COS.format('a.vec', 'b.vec')} AS g FROM near a JOIN near b ON a.query_id = b.query_id AND a.rank <> b.rank)") + "SELECT p.query_id, p.src, p.dst FROM gap p WHERE NOT EXISTS (SELECT 1 FROM gap a JOIN gap b ON a.query_id = b.query_id AND a.j = b.j AND b.i = p.j WHERE a.query_id = p.query_id AND a.i = p.i AND a.j <> p.j AND greatest(a.g, b.g) < p.g) AND NOT EXISTS (SELECT 1 FROM knn k WHERE k.src = p.src AND k.dst = p.dst)")
def mend_rng_overlay(spark, d):
    return _proposals(spark, d, "rng")[0].select("query_id", "src", "dst")


_RANDOM = _MEND.replace("ORDER BY round(gap, 12), i, j", "ORDER BY md5('0:' || (i - 1) || ':' || (j - 1))")


@_query(_with(*_CHAIN, _HARD, _RANDOM, recursive=True) + "SELECT query_id, src, dst, hardness FROM props")
def mend_random_pairs(spark, d):
    return _proposals(spark, d, "random")[0].select("query_id", "src", "dst", "hardness")


@_query()
def mend_subsets(spark, d):
    base, _, truth, edges = _frozen(spark, d)
    return M.vicinity(M.subset_truth(truth, NEAR, draws=5), edges, base, NEAR, NEAR, 2 * NEAR).select("query_id", "src", "dst", "hardness")


@_query(_with(*_CHAIN, _HARD, _MEND, recursive=True) + """SELECT src, dst, hardness, epoch FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY hardness DESC, epoch, seq, dst) AS r FROM (
  SELECT src, dst, max(hardness) AS hardness, min(epoch)::INT AS epoch, arg_min(seq, (epoch, seq)) AS seq FROM (
    SELECT src, dst, hardness, seq, CASE WHEN query_id % 20 = 8 THEN 0 ELSE 1 END AS epoch FROM props) GROUP BY 1, 2) p ANTI JOIN knn k ON k.src = p.src AND k.dst = p.dst) WHERE r <= 2""")
def admit_two_rounds(spark, d):
    """Proposals of one frozen graph admitted in two rounds under a small cap: those of the larger ids may come first."""
    proposals, edges = _proposals(spark, d)
    proposals = R.cut(proposals)
    once = R.cut(M.admit(edges, proposals.where("query_id % 20 = 8"), None))
    twice = M.admit(once, proposals.where("query_id % 20 <> 8"), 2)
    return twice.where("kind = 'extra'").select("src", "dst", "hardness", "epoch")


@_query(_with(*_CHAIN, _HARD, _MEND, recursive=True) + "SELECT query_id, count(*) AS n_arcs FROM props GROUP BY 1")
def mend_arcs_per_query(spark, d):
    return _proposals(spark, d)[0].groupBy("query_id").agg(F.count(F.lit(1)).alias("n_arcs"))


# --- search --------------------------------------------------------------------------------


@_query(_with(_BASE, _truth_cte(K, "test")) + "SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")
def search_full_beam(spark, d):
    base, q = _ws(spark, d, "test")
    edges = G.nsg(base, 30, 30, 12)
    return S.sharded(base, edges, q, K, base.count()).select("query_id", "rank", "vec_id", _r("dist"))


def _mended_history(spark, d, family):
    base, q = family(spark, d)
    base, history = R.cut(G.with_shards(base, 4)), R.cut(q.where("role = 'history'"))
    edges = R.run(base, R.cut(G.hnsw(base, 6, 100)), history, R.single(K), extra_cap=None)
    return S.sharded(base, edges, history, K, K).select("query_id", "rank", "vec_id", _r("dist"))


@_query(_with(_BASE, _truth_cte(K, "history")) + "SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")
def search_history_after_mend(spark, d):
    return _mended_history(spark, d, D.sphere)


@_query()
def search_history_after_mend_text(spark, d):
    return _mended_history(spark, d, D.text)


@_query()
def search_rounds(spark, d):
    base, q = _ws(spark, d, "test")
    edges = R.cut(G.hnsw(base, 6, 60))
    return S.rounds(base, edges, q, 5, 5, S.entry_centroid(base)).select("query_id", "rank", "vec_id", _r("dist"))


@_query(_with(_BASE, _truth_cte(K, "history")) + "SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")
def search_history_one_shard(spark, d):
    """The same guarantee on a base that is one shard, whose queries several tasks walk."""
    base, q = _ws(spark, d)
    base, history = R.cut(base), R.cut(q.where("role = 'history'"))
    edges = R.run(base, R.cut(G.hnsw(base, 6, 100)), history, R.single(K), extra_cap=None)
    return S.sharded(base, edges, history, K, K).select("query_id", "rank", "vec_id", _r("dist"))


@_query(_with(_BASE, "few AS (SELECT * FROM base WHERE label < 3)", _truth_cte(K, "test", base="few")) + "SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")
def search_filtered_walk(spark, d):
    """The same filter by walks over all rows that hide the others, at a beam that visits everything."""
    base, q = _ws(spark, d, "test")
    found = S.filtered(base, R.cut(G.nsg(base, 30, 30, 12)), q, F.col("label") < 3, K, base.count())
    return found.select("query_id", "rank", "vec_id", _r("dist"))


@_query(_with(_BASE, f"stop AS (SELECT query_id, vec_id AS stop, dist AS stop_dist FROM ({_with(_truth_cte(40, 'test', name='t40'))} SELECT * FROM t40 WHERE rank = 40))") + f"SELECT q.query_id, stop, b.vec_id FROM q JOIN stop ON stop.query_id = q.query_id, base b WHERE b.vec_id <> stop AND {_COS.format('b.vec', 'q.vec')} < stop_dist")
def approach_candidates(spark, d):
    base, q = _ws(spark, d, "test")
    stops = R.cut(T.exact_blocked(base, q, 40).where("rank = 40").select("query_id", F.col("vec_id").alias("stop"), F.col("dist").alias("stop_dist")))
    return M.approach_candidates(base, None, q, stops)


@_query(_with(_BASE, f"stop AS (SELECT query_id, vec_id AS stop, dist AS stop_dist FROM ({_with(_truth_cte(40, 'test', name='t40'))} SELECT * FROM t40 WHERE rank = 40))",
              f"cand AS (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY d, vec_id) AS n FROM (SELECT q.query_id, stop, b.vec_id, b.vec, {_COS.format('b.vec', 'o.vec')} AS d FROM q JOIN stop ON stop.query_id = q.query_id JOIN base o ON o.vec_id = stop, base b WHERE b.vec_id <> stop AND {_COS.format('b.vec', 'q.vec')} < stop_dist))",
              f"near AS MATERIALIZED (SELECT a.query_id, a.n AS i, b.n AS j, {_COS.format('a.vec', 'b.vec')} AS gap FROM cand a JOIN cand b ON a.query_id = b.query_id AND a.n > b.n)",
              """keep(query_id, n, kept) AS (
  SELECT query_id, 0::BIGINT, []::BIGINT[] FROM cand WHERE n = 1
  UNION ALL
  SELECT c.query_id, c.n, CASE WHEN len(k.kept) < 8 AND NOT EXISTS (SELECT 1 FROM near x WHERE x.query_id = c.query_id AND x.i = c.n AND list_contains(k.kept, x.j) AND x.gap <= c.d) THEN list_append(k.kept, c.n) ELSE k.kept END
  FROM keep k JOIN cand c ON c.query_id = k.query_id AND c.n = k.n + 1)""",
              "last AS (SELECT query_id, unnest(arg_max(kept, n)) AS n FROM keep GROUP BY query_id)", recursive=True)
        + "SELECT c.query_id, c.stop AS src, c.vec_id AS dst, 32767 AS hardness FROM last JOIN cand c ON c.query_id = last.query_id AND c.n = last.n")
def approach_thinned(spark, d):
    base, q = _ws(spark, d, "test")
    stops = R.cut(T.exact_blocked(base, q, 40).where("rank = 40").select("query_id", F.col("vec_id").alias("stop"), F.col("dist").alias("stop_dist")))
    return M.approach_arcs(base, M.approach_candidates(base, None, q, stops), 8).select("query_id", "src", "dst", "hardness")


@_query()
def arrival_detect(spark, d):
    base, q = _ws(spark, d, "history")
    return M.stuck(base, G.hnsw(base, 3, 60), q, T.exact_blocked(base, q, K), K, K).select("query_id", "stop", _r("stop_dist"))


# --- upkeep ----------------------------------------------------------------------------------


@_query(_with(_BASE, _KNN) + "SELECT src, dst FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY md5(src || ':' || dst || ':0')) AS r, count(*) OVER (PARTITION BY src) AS n FROM knn) k WHERE r > floor(n * 0.4)")
def refresh_drop(spark, d):
    edges = G.as_edges(G.knn(_ws(spark, d)[0], DEGREE), "extra")
    return U.refresh_drop(edges, 0.4).select("src", "dst")


@_query(_with(_BASE, "live AS (SELECT * FROM base WHERE vec_id % 5 <> 0)", _truth_cte(K, "test", base="live")) + "SELECT query_id, rank, vec_id, round(dist, 6) AS dist FROM truth")
def tombstone_topk(spark, d):
    base, q = _ws(spark, d, "test")
    return S.sharded(base, G.nsg(base, 30, 30, 12), q, K, base.count(), tombstones=base.where("vec_id % 5 = 0")).select("query_id", "rank", "vec_id", _r("dist"))


@_query(_with(_BASE, _KNN) + "SELECT src, dst FROM knn WHERE src % 5 <> 0 AND dst % 5 <> 0")
def purge_edges(spark, d):
    base, _ = _ws(spark, d)
    return U.purge(G.as_edges(G.knn(base, DEGREE)), base.where("vec_id % 5 = 0")).select("src", "dst")


@_query(_with(_BASE) + f"SELECT query_id * 1000 + c AS query_id, query_id AS parent_id, i::INT AS j, round(vec[i + 1] + sqrt(0.3 / 64) * sqrt(-2 * ln(({_U.format(chr(39) * 0 + 'concat_ws(chr(58), query_id, c, i, chr(97), 0)')} + 0.5) / 4294967296)) * cos(2 * 3.141592653589793 * (({_U.format('concat_ws(chr(58), query_id, c, i, chr(98), 0)')} + 0.5) / 4294967296)), 6) AS x FROM q, range(1, 3) r(c), range(64) t(i) WHERE role = 'history'")
def augment_noise(spark, d):
    _, q = _ws(spark, d, "history")
    return U.augment(q, 2).where("copy > 0").select("query_id", "parent_id", F.posexplode("vec").alias("j", "x")).select("query_id", "parent_id", "j", _r("x"))


@_query(_with(_BASE) + "SELECT query_id, md5(list_aggregate([floor(x * 1000000 + 0.5)::BIGINT FOR x IN vec], 'string_agg', ',')) AS key_md5 FROM q")
def canonical_keys(spark, d):
    return _ws(spark, d)[1].select("query_id", V.key_md5(F.col("vec")).alias("key_md5"))


@_query(_with(_BASE, "h AS (SELECT query_id, vec FROM q WHERE role = 'history')") + f"SELECT t.query_id, round(min({_COS.format('h.vec', 't.vec')}), 6) AS gap, CASE WHEN min({_COS.format('h.vec', 't.vec')}) <= 0.4 THEN 'high' WHEN min({_COS.format('h.vec', 't.vec')}) <= 0.5 THEN 'moderate' ELSE 'low' END AS band FROM q t, h WHERE t.role = 'test' GROUP BY 1")
def similarity_bands(spark, d):
    _, q = _ws(spark, d)
    return U.similarity_bands(q.where("role = 'test'"), q.where("role = 'history'"), (0.4, 0.5)).select("query_id", _r("gap"), "band")


@_query(_with(_BASE, "h AS (SELECT query_id, vec FROM q WHERE role = 'history')") + f"SELECT count(*) AS n_new, count(*) FILTER (gap > 0.5) AS n_novel, round(count(*) FILTER (gap > 0.5) / count(*), 6) AS share FROM (SELECT t.query_id, min({_COS.format('h.vec', 't.vec')}) AS gap FROM q t, h WHERE t.role = 'test' GROUP BY 1)")
def novelty(spark, d):
    _, q = _ws(spark, d)
    return U.novelty(q.where("role = 'history'"), q.where("role = 'test'"), 0.5).select("n_new", "n_novel", _r("share"))


@_query(_with(_BASE, _truth_cte(3, "test"), _truth_cte(12, "history", name="ht")) + "SELECT t.query_id AS test_id, h.query_id AS history_id, count(*) FILTER (h.rank <= 3) = 3 AS equal FROM truth t JOIN ht h ON h.vec_id = t.vec_id GROUP BY 1, 2 HAVING count(*) = 3")
def containment(spark, d):
    base, q = _ws(spark, d)
    return U.containment(T.exact_blocked(base, q.where("role = 'test'"), 3), T.exact_blocked(base, q.where("role = 'history'"), 12), 3, 12)


@_query(_with(_BASE, _truth_cte(3, "test"), _truth_cte(12, "history", name="ht"), "c AS (SELECT t.query_id AS test_id, h.query_id AS history_id, count(*) FILTER (h.rank <= 3) = 3 AS equal FROM truth t JOIN ht h ON h.vec_id = t.vec_id GROUP BY 1, 2 HAVING count(*) = 3)")
        + f"SELECT equal, count(*) AS n, round(max({_COS.format('h.vec', 't.vec')}), 6) AS max_gap, round(avg({_COS.format('h.vec', 't.vec')}), 6) AS mean_gap FROM c JOIN q t ON t.query_id = test_id JOIN q h ON h.query_id = history_id GROUP BY 1")
def containment_distance(spark, d):
    """How near two queries are whose answers contain one another."""
    base, q = _ws(spark, d)
    test, history = q.where("role = 'test'"), q.where("role = 'history'")
    pairs = U.containment(T.exact_blocked(base, test, 3), T.exact_blocked(base, history, 12), 3, 12)
    return U.containment_gaps(pairs, test, history).groupBy("equal").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("gap"), 6).alias("max_gap"), F.round(F.avg("gap"), 6).alias("mean_gap"))


@_query("SELECT modality, modality <> 'document' AS ood, count(*) AS n FROM (SELECT 'document' AS modality FROM benchmark UNION ALL SELECT 'chat' FROM conversations WHERE role = 'user' UNION ALL SELECT 'page' FROM pages) GROUP BY 1")
def ood_by_modality(spark, d):
    """Passages, chat turns and pages as queries on a base of documents: the last two are of another modality."""
    t = lambda name: D.table(spark, d, name)
    asked = t("benchmark").select(F.col("item_id").alias("query_id"), F.lit("document").alias("modality"))
    asked = asked.union(t("conversations").where("role = 'user'").select(F.col("conv_id") * 1000 + F.col("turn"), F.lit("chat"))).union(t("pages").select("page_id", F.lit("page")))
    base = t("documents").select(F.lit("document").alias("modality"))
    return U.by_modality(asked, base).groupBy("modality", "ood").agg(F.count(F.lit(1)).alias("n"))


_PREFIXES = (8, 16, 32, 48, 64)


def _prefix_rows(m: int) -> str:
    return f"""SELECT {m} AS beam, avg(hit) AS recall FROM (SELECT t.query_id, count(a.vec_id) / {K} AS hit FROM truth t LEFT JOIN (
  SELECT * FROM (SELECT q.query_id, b.vec_id, row_number() OVER (PARTITION BY q.query_id ORDER BY {_COS.format(f'b.vec[1:{m}]', f'q.vec[1:{m}]')}, b.vec_id) AS rank FROM q, base b WHERE role = 'test') WHERE rank <= {K}) a ON a.query_id = t.query_id AND a.vec_id = t.vec_id GROUP BY 1)"""


@_query(_with(_BASE, _truth_cte(K, "test"), "curve AS MATERIALIZED (" + " UNION ALL ".join(_prefix_rows(m) for m in _PREFIXES) + ")",
              "step AS (SELECT *, lag(beam) OVER (ORDER BY beam) AS b0, lag(recall) OVER (ORDER BY beam) AS r0 FROM curve)")
        + "SELECT level::DOUBLE AS level, round(arg_min(CASE WHEN r0 IS NULL THEN beam ELSE b0 + (level - r0) / (recall - r0) * (beam - b0) END, beam), 4) AS dims FROM step, (VALUES (0.3), (0.5), (0.9)) v(level) WHERE recall >= level GROUP BY level")
def value_at_level(spark, d):
    """Coordinates of a cut embedding that reach a recall, between the measured points of a curve."""
    base, q = _ws(spark, d, "test")
    truth, curve = T.exact_blocked(base, q, K), None
    for m in _PREFIXES:
        found = T.exact_blocked(base.withColumn("vec", V.prefix(F.col("vec"), m)), q.withColumn("vec", V.prefix(F.col("vec"), m)), K)
        point = E.recall_by_query(found, truth, K).agg(F.lit("prefix").alias("method"), F.lit(m).alias("beam"), F.avg("recall").alias("recall"), F.lit(float(m)).alias("dims"))
        curve = point if curve is None else curve.unionByName(point)
    curve, rows = R.cut(curve), None
    for x in (0.3, 0.5, 0.9):
        row = E.at_level(curve, "recall", "dims", x).select(F.lit(x).alias("level"), F.round("dims", 4).alias("dims"))
        rows = row if rows is None else rows.unionByName(row)
    return rows


@_query(_with(_BASE, _truth_cte(K, "history")) + f"SELECT t.query_id, count(DISTINCT h.query_id) AS n_history, count(DISTINCT truth.vec_id) AS n_union FROM q t JOIN q h ON t.role = 'test' AND h.role = 'history' AND {_COS.format('h.vec', 't.vec')} <= 0.6 JOIN truth ON truth.query_id = h.query_id GROUP BY 1")
def ball_union(spark, d):
    base, q = _ws(spark, d)
    history = q.where("role = 'history'")
    return U.ball_union(q.where("role = 'test'"), history, T.exact_blocked(base, history, K), 0.6, K)


@_query(_with(_BASE, "p AS (SELECT j, avg(vec[j + 1]) AS m, var_pop(vec[j + 1]) AS v FROM base, range(64) t(j) GROUP BY j)") + "SELECT query_id, round(sqrt(sum((vec[j + 1] - m) ** 2 / v)), 6) AS distance FROM q, p WHERE role = 'test' GROUP BY 1")
def ood_diag_mahalanobis(spark, d):
    base, q = _ws(spark, d, "test")
    return U.mahalanobis_diagonal(q, U.profile(base)).select("query_id", _r("distance"))


@_query()
def ood_mahalanobis(spark, d):
    base, q = _ws(spark, d, "test")
    return U.mahalanobis(q, base).select("query_id", _r("distance"))


@_query(_with(_BASE, "l AS (SELECT [(i + 0.5) / 50 FOR i IN range(50)] AS l)") + f"SELECT round(avg(abs(a - b)), 6) AS distance FROM (SELECT unnest(x) AS a, unnest(y) AS b FROM (SELECT quantile_cont(vec[1], [{', '.join(str((i + 0.5) / 50) for i in range(50))}]) AS x FROM base), (SELECT quantile_cont(vec[1], [{', '.join(str((i + 0.5) / 50) for i in range(50))}]) AS y FROM q WHERE role = 'test'))")
def ood_wasserstein_1d(spark, d):
    base, q = _ws(spark, d, "test")
    return U.wasserstein_1d(base, q, 0).select(_r("distance"))


_LINES = f"lines AS (SELECT p::INT AS direction, [CASE WHEN {_U.format("'0:' || p || ':' || j")} % 2 = 0 THEN 0.125 ELSE -0.125 END::DOUBLE FOR j IN range(64)] AS line FROM range(4) t(p))"
_LEVELS = ", ".join(str((i + 0.5) / 50) for i in range(50))


@_query(_with(_BASE, _LINES, f"qa AS (SELECT direction, quantile_cont(list_inner_product(vec, line), [{_LEVELS}]) AS a FROM base, lines GROUP BY direction)", f"qb AS (SELECT direction, quantile_cont(list_inner_product(vec, line), [{_LEVELS}]) AS b FROM q, lines WHERE role = 'test' GROUP BY direction)")
        + "SELECT direction, round(list_avg([abs(a[i] - b[i]) FOR i IN range(1, 51)]), 6) AS distance FROM qa JOIN qb USING (direction)")
def ood_sliced_wasserstein(spark, d):
    base, q = _ws(spark, d, "test")
    return U.sliced_wasserstein(base, q, 4).select("direction", _r("distance"))


@_query()
def ood_sinkhorn(spark, d):
    base, q = _ws(spark, d, "test")
    return U.sinkhorn(base, q)


@_query()
def hardness_steiner(spark, d):
    _, _, truth, edges = _frozen(spark, d)
    return N.steiner_proxy(truth, N.extract(truth, edges, MAX_RANK), MAX_RANK, K)


@_query(_with(_BASE, "c AS (SELECT shard, list(m ORDER BY j) AS c FROM (SELECT label % 4 AS shard, j, avg(vec[j + 1]) AS m FROM base, range(64) t(j) GROUP BY ALL) GROUP BY shard)",
              f"near AS (SELECT query_id, vec, shard, row_number() OVER (PARTITION BY query_id ORDER BY {_COS.format('c', 'vec')}, shard) AS n FROM q, c WHERE role = 'test')",
              f"hit AS (SELECT query_id, vec_id, {_COS.format('b.vec', 'near.vec')} AS dist FROM near JOIN base b ON b.label % 4 = shard WHERE n <= 2)")
        + f"SELECT * FROM (SELECT query_id, (row_number() OVER (PARTITION BY query_id ORDER BY dist, vec_id))::INT AS rank, vec_id, round(dist, 6) AS dist FROM hit) WHERE rank <= {K}")
def search_routed(spark, d):
    base, q = _ws(spark, d, "test")
    base = base.withColumn("shard", (F.col("label") % 4).cast("int"))
    edges = R.cut(G.nsg(base))
    return S.sharded(base, edges, q, K, base.count(), probe_shards=2).select("query_id", "rank", "vec_id", _r("dist"))


@_query()
def min_beam(spark, d):
    base, history, truth, edges = _frozen(spark, d)
    return S.min_beam(base, edges, history, truth.where(F.col("rank") <= 3), [10, 20, 40, 80])


@_query(_with(_BASE) + "SELECT role AS origin, count(*) AS n FROM (SELECT query_id, 'history' AS role FROM q WHERE role = 'history' UNION ALL SELECT query_id, 'training' FROM q WHERE role = 'test') GROUP BY role")
def history_from_training(spark, d):
    _, q = _ws(spark, d)
    history = q.where("role = 'history'")
    both = U.from_training(history, q.where("role = 'test'").unionByName(history))
    return both.groupBy("origin").agg(F.count(F.lit(1)).alias("n"))


# --- streams, windows and reports ---------------------------------------------------------------

_EV = "SELECT event_id, ts, event_type, user_id, value FROM events"


@_query("SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY ALL")
def stream_tumbling_replay(spark, d):
    return O.tumbling_replay(spark, d)


@_query()
def stream_mend_replay(spark, d):
    return O.mend_replay(spark, d)


@_query("SELECT count(DISTINCT event_id * 7919 % (SELECT count(*) FROM embeddings) || event_type) AS n_keys, count(*) AS n FROM events")
def cache_repeats(spark, d):
    _, q = D.event_log(spark, d)
    return U.repeats(q).select(V.key_md5(F.col("vec")).alias("k"), "n").agg(F.countDistinct("k").alias("n_keys"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"))


@_query("SELECT event_type, ts::DATE AS day, count(*) AS n FROM events GROUP BY ALL")
def events_daily(spark, d):
    return D.table(spark, d, "events").groupBy("event_type", F.to_date("ts").alias("day")).agg(F.count(F.lit(1)).alias("n"))


@_query("""SELECT user_id, event_id, lag(event_id) OVER w AS before, row_number() OVER w AS n, round(sum(value) OVER (w ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS last_three,
  count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS in_a_day FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def window_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    day = Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-86_400_000_000, 0)
    return D.table(spark, d, "events").select("user_id", "event_id", F.lag("event_id").over(w).alias("before"), F.row_number().over(w).cast("bigint").alias("n"),
                                              F.round(F.sum("value").over(w.rowsBetween(-2, 0)), 4).alias("last_three"), F.count(F.lit(1)).over(day).alias("in_a_day"))


@_query("SELECT e.event_id, e.user_id, b.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') e ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events WHERE event_type = 'view' GROUP BY 1, 2) b ON b.user_id = e.user_id AND b.ts <= e.ts")
def as_of_join(spark, d):
    e = D.table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    bought, seen = e.where("event_type = 'purchase'").drop("event_type"), e.where("event_type = 'view'").drop("event_type")
    return J.as_of(bought, seen, "user_id", "ts", "event_id", "last_view").select("event_id", "user_id", "last_view")


_NEXT = "SELECT a.event_id, b.event_id AS next_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 24 HOURS"


@_query(_NEXT)
def interval_join(spark, d):
    e = D.table(spark, d, "events").select("event_id", "user_id", "ts", "event_type")
    seen, bought = e.where("event_type = 'view'").drop("event_type"), e.where("event_type = 'purchase'").drop("event_type")
    return J.within_span(seen, bought, "user_id", "ts", 86_400).select("event_id", F.col("event_id_r").alias("next_id"))


@_query(_NEXT)
def stream_interval_join(spark, d):
    return O.followed(spark, d)


@_query("SELECT DISTINCT event_id, user_id FROM events")
def stream_distinct(spark, d):
    return O.first_of_event(spark, d)


@_query("SELECT user_id, count(*) AS n, count(DISTINCT event_type) AS n_types FROM events GROUP BY 1")
def stream_state_by_user(spark, d):
    return O.repeats_by_user(spark, d)


@_query("SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q1, round(quantile_cont(value, 0.5), 6) AS q2, round(quantile_cont(value, 0.75), 6) AS q3 FROM events GROUP BY 1")
def value_quantiles(spark, d):
    q = lambda p: F.round(F.percentile("value", F.lit(p)), 6)
    return D.table(spark, d, "events").groupBy("event_type").agg(q(0.25).alias("q1"), q(0.5).alias("q2"), q(0.75).alias("q3"))


@_query("SELECT 'both' AS side, count(*) AS n FROM (SELECT user_id FROM events WHERE event_type = 'view' INTERSECT SELECT user_id FROM events WHERE event_type = 'error') UNION ALL SELECT 'only', count(*) FROM (SELECT user_id FROM events WHERE event_type = 'view' EXCEPT SELECT user_id FROM events WHERE event_type = 'error') UNION ALL SELECT 'all', count(DISTINCT user_id) FROM events WHERE event_type IN ('view', 'error')")
def set_operations(spark, d):
    e = D.table(spark, d, "events")
    one, two = (e.where(F.col("event_type") == x).select("user_id") for x in ("view", "error"))
    parts = {"both": one.intersect(two), "only": one.subtract(two), "all": one.union(two).distinct()}
    rows = [df.agg(F.lit(n).alias("side"), F.count(F.lit(1)).alias("n")) for n, df in parts.items()]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


@_query(_with(_BASE) + f"SELECT query_id, round(sqrt(list_inner_product(vec, vec)), 6) AS norm, round(min({_COS.format('b.vec', 'q.vec')}), 6) AS nearest FROM q, (SELECT vec_id, vec AS vec FROM base) b WHERE role = 'test' GROUP BY query_id, vec".replace("sqrt(list_inner_product(vec, vec)), 6) AS norm", "sqrt(list_inner_product(q.vec, q.vec)), 6) AS norm").replace("GROUP BY query_id, vec", "GROUP BY query_id, q.vec"))
def sql_vector_functions(spark, d):
    """The vector functions from SQL text, inlined by Catalyst, on each query and its nearest row among all."""
    V.register(spark)
    base, q = _ws(spark, d, "test")
    near = T.exact_blocked(base, q, 1)
    return spark.sql("SELECT query_id, round(vec_norm(q.vec), 6) AS norm, round(vec_cos(b.vec, q.vec), 6) AS nearest FROM {near} n JOIN {q} q USING (query_id) JOIN {b} b USING (vec_id)", near=near, q=q, b=base)


@_query("SELECT event_type, map_extract_value(counts, 'Monday') AS mondays, cardinality(counts)::INT AS n_days FROM (SELECT event_type, map(list(d), list(n)) AS counts FROM (SELECT event_type, dayname(ts) AS d, count(*) AS n FROM events GROUP BY ALL) GROUP BY 1)")
def weekday_maps(spark, d):
    by_day = D.table(spark, d, "events").groupBy("event_type", F.date_format("ts", "EEEE").alias("day")).agg(F.count(F.lit(1)).alias("n"))
    counts = by_day.groupBy("event_type").agg(F.map_from_entries(F.collect_list(F.struct("day", "n"))).alias("counts"))
    return counts.select("event_type", F.try_element_at("counts", F.lit("Monday")).alias("mondays"), F.size("counts").alias("n_days"))


@_query("SELECT event_type, json_extract_string(props, '$.k')::BIGINT % 5 AS k, count(*) AS n FROM events GROUP BY ROLLUP (1, 2)")
def rollup_report(spark, d):
    e = D.table(spark, d, "events").select("event_type", (F.get_json_object("props", "$.k").cast("bigint") % 5).alias("k"))
    return e.rollup("event_type", "k").agg(F.count(F.lit(1)).alias("n"))


# --- experiments --------------------------------------------------------------------------------

for _name, _run in X.WORKLOADS.items():
    QUERIES[_name] = _run
