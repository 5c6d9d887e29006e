"""Vector families on the test tables: base, history and test queries of four workloads."""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import vectors as V

DIM = 64
#: Length of the constant offset that stands for a gap between modalities.
GAP = 0.6


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def offset_direction(prefix: str = "") -> Column:
    """Fixed direction of +-1/8 coordinates, signs from hashes of the coordinate numbers."""
    return F.transform(F.sequence(F.lit(0), F.lit(DIM - 1)), lambda j: F.when(V.hash32(F.concat(F.lit(prefix), j.cast("string"))) % 2 == 0, F.lit(0.125)).otherwise(F.lit(-0.125)))


def sphere(spark: SparkSession, sf_dir: str, ood: bool = True) -> tuple[DataFrame, DataFrame]:
    """Base rows and queries (query_id, vec, role) from ``embeddings``; out-of-distribution queries are shifted."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", V.as_double(F.col("embedding")).alias("vec"), "label")
    base = e.where("vec_id % 10 < 7")
    vec = V.normalise(V.add(F.col("vec"), V.scale(offset_direction(), F.lit(GAP)))) if ood else F.col("vec")
    role = F.when(F.col("vec_id") % 10 == 9, "test").otherwise("history")
    return base, e.where("vec_id % 10 >= 7").select(F.col("vec_id").alias("query_id"), vec.alias("vec"), role.alias("role"), "label")


def _token_vectors(rows: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """Signed hashing of ASCII tokens into 64 coordinates, unit length; rows without tokens drop out."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        class Cells(dict):
            """Coordinate of a token, DIM more where it counts down; each is hashed once while it is known."""

            def __missing__(self, token: bytes) -> int:
                if len(self) > 1 << 20:
                    self.clear()
                h = int(hashlib.md5(token).hexdigest()[:8], 16)
                self[token] = c = h % DIM + h // DIM % 2 * DIM
                return c

        cells, find = Cells(), re.compile(rb"[a-z]+").findall
        for batch in batches:
            ids, texts = batch.column(0), batch.column(1).cast(pa.binary())
            for i in range(0, batch.num_rows, 1024):
                found = [find((t.as_py() or b"").lower()) for t in texts[i : i + 1024]]
                counts = [np.bincount([cells[w] for w in words], minlength=2 * DIM) for words in found if words]
                if counts:
                    raw = np.stack(counts).astype(np.float64)
                    raw = raw[:, :DIM] - raw[:, DIM:]
                    lists = pa.ListArray.from_arrays(np.arange(0, raw.size + 1, DIM, dtype=np.int32), pa.array(raw.ravel()))
                    yield pa.RecordBatch.from_arrays([ids[i : i + 1024].filter(pa.array([bool(w) for w in found])), lists], names=["id", "raw"])

    source = rows.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    sums = source.mapInArrow(run, f"id {dict(source.dtypes)['id']}, raw array<double>").groupBy(F.col("id").alias(id_col)).agg(F.array(*[F.sum(F.get("raw", F.lit(i))) for i in range(DIM)]).alias("raw"))
    return sums.where(V.norm(F.col("raw")) > 0).select(id_col, V.normalise(F.col("raw")).alias("vec"))


def text(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Base: first document of each text.  Queries: user turns, even ones history and odd ones test."""
    docs = table(spark, sf_dir, "documents").groupBy("text").agg(F.min("doc_id").alias("vec_id"))
    base = _token_vectors(docs, "vec_id", "text").withColumn("label", F.lit(0))
    asked = table(spark, sf_dir, "conversations").where("role = 'user'").select((F.col("conv_id") * 1000 + F.col("turn")).alias("query_id"), "text")
    queries = _token_vectors(asked, "query_id", "text")
    from pyspark.sql import Window

    order = F.row_number().over(Window.partitionBy(F.pmod("query_id", F.lit(97))).orderBy("query_id"))
    return base, queries.select("query_id", "vec", F.when(order % 2 == 0, "history").otherwise("test").alias("role"), F.lit(0).alias("label"))


def products(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Base: parts as sums of token patterns.  Queries: orders as sums of their parts; the latest third is test."""
    part = table(spark, sf_dir, "part")
    words = F.split("p_name", " ")
    tokens = F.array(F.get(words, 0), F.get(words, 1), F.col("p_brand"), F.col("p_type"), F.concat(F.lit("size"), F.floor(F.col("p_size") / 10)), F.concat(F.lit("id"), F.col("p_partkey")))
    cell = lambda t, j: F.when(V.hash32(F.concat_ws(":", t, j.cast("string"))) % 2 == 0, 1.0).otherwise(-1.0)
    kept = F.filter(tokens, lambda t: t.isNotNull())
    raw = F.transform(F.sequence(F.lit(0), F.lit(DIM - 1)), lambda j: F.aggregate(kept, F.lit(0.0), lambda s, t: s + cell(t, j)))
    base = part.select(F.col("p_partkey").alias("vec_id"), V.normalise(raw).alias("vec"), F.lit(0).alias("label"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", F.col("l_partkey").alias("vec_id")).join(base.select("vec_id", "vec"), "vec_id")
    sums = lines.groupBy("l_orderkey").agg(F.array(*[F.sum(F.get("vec", F.lit(i))) for i in range(DIM)]).alias("raw"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_orderdate").cast("timestamp").alias("ts"))
    cut = orders.agg(F.percentile(F.unix_timestamp("ts"), 2 / 3)).first()[0] or 0
    queries = sums.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select(
        F.col("o_orderkey").alias("query_id"), V.normalise(F.col("raw")).alias("vec"), F.when(F.unix_timestamp("ts") > cut, "test").otherwise("history").alias("role"), F.lit(0).alias("label"), "ts"
    )
    return base, queries


def event_log(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Base of the sphere family.  Queries: one an event in time order, offset by its type; many repeat exactly."""
    base, _ = sphere(spark, sf_dir)
    e = table(spark, sf_dir, "embeddings").select("vec_id", V.as_double(F.col("embedding")).alias("v"))
    n = e.count()
    events = table(spark, sf_dir, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"), "event_type", "user_id", (F.col("event_id") * 7919 % n).alias("vec_id"))
    kinds = events.select("event_type").distinct()
    directions = kinds.withColumn("g", F.transform(F.sequence(F.lit(0), F.lit(DIM - 1)), lambda j: F.when(V.hash32(F.concat_ws(":", F.col("event_type"), j.cast("string"))) % 2 == 0, F.lit(0.125)).otherwise(F.lit(-0.125))))
    # a vector is reckoned once for each row and type, not for each event
    own = e.join(F.broadcast(directions)).select("vec_id", "event_type", V.normalise(V.add(F.col("v"), V.scale(F.col("g"), F.lit(GAP)))).alias("vec"))
    joined = events.join(own, ["vec_id", "event_type"])
    return base, joined.select(F.col("event_id").alias("query_id"), "vec", F.lit("history").alias("role"), F.lit(0).alias("label"), "ts", "event_type", "user_id")


FAMILIES = {"sphere": sphere, "text": text, "products": products, "event_log": event_log}
