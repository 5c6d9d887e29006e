"""Index store: edges of numbered epochs beside a manifest, written by Spark and read by the newest committed epoch."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

MANIFEST = "epoch int, metric string, config map<string,string>, n_arcs bigint, committed_at timestamp"


def _exists(spark: SparkSession, path: str) -> bool:
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(place)


def manifest(spark: SparkSession, root: str) -> DataFrame:
    """One row a committed epoch; none where nothing was saved."""
    if not _exists(spark, f"{root}/manifest"):
        return spark.createDataFrame([], MANIFEST)
    return spark.read.schema(MANIFEST).parquet(f"{root}/manifest")


def newest(spark: SparkSession, root: str) -> int | None:
    return manifest(spark, root).agg(F.max("epoch")).first()[0]


def save(edges: DataFrame, root: str, metric: str = "cosine", config: dict[str, str] | None = None, epoch: int | None = None) -> int:
    """Write edges as the next epoch, by kind of arc; an epoch counts once its manifest row is there.

    Base arcs and extra arcs lie in partitions of their own, so that a refresh and an insertion write apart.  Saving a given
    epoch again, as a repeated batch does, replaces its edges and adds no second row.
    """
    spark = edges.sparkSession
    last = newest(spark, root)
    number = (0 if last is None else last + 1) if epoch is None else epoch
    edges.write.mode("overwrite").partitionBy("kind").parquet(f"{root}/edges/epoch_{number}")
    if epoch is None or manifest(spark, root).where(F.col("epoch") == number).isEmpty():
        n = spark.read.parquet(f"{root}/edges/epoch_{number}").count()
        row = spark.createDataFrame([(number, metric, config or {}, n)], "epoch int, metric string, config map<string,string>, n_arcs bigint")
        row.withColumn("committed_at", F.current_timestamp()).coalesce(1).write.mode("append").parquet(f"{root}/manifest")
    return number


def load(spark: SparkSession, root: str, epoch: int | None = None, kind: str | None = None) -> DataFrame:
    """Edges of an epoch, by default the newest committed one; a kind reads its partition alone."""
    number = newest(spark, root) if epoch is None else epoch
    rows = spark.read.option("basePath", f"{root}/edges/epoch_{number}").parquet(f"{root}/edges/epoch_{number}")
    rows = rows if kind is None else rows.where(F.col("kind") == kind)
    return rows.select("src", "dst", "kind", "layer", "hardness", "seq", "epoch")


def prune(spark: SparkSession, root: str, keep: int = 2) -> list[int]:
    """Delete the edges of all but the newest epochs; their manifest rows stay as a record."""
    numbers = sorted((r["epoch"] for r in manifest(spark, root).select("epoch").distinct().collect()), reverse=True)
    conf, jvm = spark.sparkContext._jsc.hadoopConfiguration(), spark.sparkContext._jvm
    gone = [n for n in numbers[keep:] if _exists(spark, f"{root}/edges/epoch_{n}")]
    for n in gone:
        place = jvm.org.apache.hadoop.fs.Path(f"{root}/edges/epoch_{n}")
        place.getFileSystem(conf).delete(place, True)
    return gone
