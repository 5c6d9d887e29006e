"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def recall_by_query(results: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(query_id, recall): share of the true k nearest among the answer's first k."""
    want = truth.where(F.col("rank") <= k).select("query_id", "vec_id")
    got = results.where(F.col("rank") <= k).select("query_id", "vec_id", F.lit(1).alias("hit"))
    return want.join(got, ["query_id", "vec_id"], "left").groupBy("query_id").agg((F.sum(F.coalesce("hit", F.lit(0))) / F.count(F.lit(1))).alias("recall"))


def recall(results: DataFrame, truth: DataFrame, k: int) -> float:
    return recall_by_query(results, truth, k).agg(F.avg("recall")).first()[0] or 0.0


#: Distances up to here are zero but for rounding.
ZERO = 1e-12


def distance_error(answer: Column, true: Column) -> Column:
    """Answer distance over true distance, less one; 0 where both are zero, null where only the true one is, or where it is negative."""
    return F.when(true > ZERO, answer / true - 1).when((F.abs(true) <= ZERO) & (F.abs(answer) <= ZERO), F.lit(0.0))


def rderr(results: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """(query_id, rderr): mean over ranks of answer distance over true distance, less one.

    0 where both distances are zero, and null where only the true one is, or where it is negative.  An answer of
    fewer than k rows has the value null, since a mean over the ranks it has would look better than a full one.
    """
    a = results.where(F.col("rank") <= k).select("query_id", "rank", F.col("dist").alias("a"))
    t = truth.where(F.col("rank") <= k).select("query_id", "rank", F.col("dist").alias("t"))
    e = distance_error(F.col("a"), F.col("t"))
    return t.join(a, ["query_id", "rank"], "left").groupBy("query_id").agg(F.when(F.count("a") == F.count(F.lit(1)), F.avg(e)).alias("rderr"))


def epsilon_answers(results: DataFrame, truth: DataFrame, k: int, eps: float) -> DataFrame:
    """(query_id, ok): every answer lies within (1 + eps) of each vector that is not an answer.

    The nearest vector outside an answer of k rows is among the k + 1 nearest, so ``truth`` holds ranks up to k + 1.
    """
    answer = results.where(F.col("rank") <= k).select("query_id", "vec_id", F.col("dist").alias("a"))
    outside = truth.where(F.col("rank") <= k + 1).join(answer, ["query_id", "vec_id"], "left_anti").groupBy("query_id").agg(F.min("dist").alias("b"))
    return answer.join(outside, "query_id").groupBy("query_id").agg(F.bool_and(F.col("a") <= (1 + eps) * F.col("b") + 1e-12).alias("ok"))


def bands(per_query: DataFrame, steps: int = 5) -> DataFrame:
    """(band, n_queries, share): queries by band of recall; band 0 holds those with recall 0 exactly."""
    band = F.when(F.col("recall") == 0, 0).otherwise(F.ceil(F.col("recall") * steps).cast("int"))
    counts = per_query.groupBy(band.alias("band")).agg(F.count(F.lit(1)).alias("n_queries"))
    return counts.withColumn("share", F.col("n_queries") / F.sum("n_queries").over(Window.partitionBy()))


def index_bytes(edges: DataFrame, id_bytes: int = 4) -> DataFrame:
    """(kind, n_arcs, n_bytes): memory of the arcs; an extra arc carries a 16-bit tag."""
    return edges.groupBy("kind").agg(F.count(F.lit(1)).alias("n_arcs")).withColumn("n_bytes", F.col("n_arcs") * (id_bytes + F.when(F.col("kind") == "extra", 2).otherwise(0)))


def at_level(curve: DataFrame, x: str, y: str, level: float) -> DataFrame:
    """(method, y): value of ``y`` where ``x`` first reaches a level, linear between neighbouring points of a curve (method, beam, ...)."""
    order = Window.partitionBy("method").orderBy("beam")
    both = curve.withColumn("x0", F.lag(x).over(order)).withColumn("y0", F.lag(y).over(order)).where(F.col(x) >= level)
    first = both.withColumn("r", F.row_number().over(order)).where("r = 1")
    part = (F.lit(level) - F.col("x0")) / (F.col(x) - F.col("x0"))
    return first.select("method", F.when(F.col("x0").isNull(), F.col(y)).otherwise(F.col("y0") + part * (F.col(y) - F.col("y0"))).alias(y))


def out_degrees(edges: DataFrame, base: DataFrame) -> DataFrame:
    """(degree, n): rows of the base by the number of arcs of the bottom layer that go out of them."""
    counts = edges.where("layer = 0").groupBy(F.col("src").alias("vec_id")).agg(F.count(F.lit(1)).alias("degree"))
    return base.select("vec_id").join(counts, "vec_id", "left").groupBy(F.coalesce("degree", F.lit(0)).alias("degree")).agg(F.count(F.lit(1)).alias("n"))


def arrival_share(per_query: DataFrame) -> DataFrame:
    """(n, n_arrived, share): queries whose answer holds a true neighbour at all, from (query_id, recall)."""
    return per_query.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("recall") > 0).alias("n_arrived")).withColumn("share", F.col("n_arrived") / F.col("n"))
