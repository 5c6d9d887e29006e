"""Structured Streaming: replay of tables as streams, windowed counts, and online mending."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import graph as G
from ..operators import mend as M
from ..operators import truth as T
from ..plans.lineage import cut
from ..sources import families as D
from ..sources import store as I


def _place(spark: SparkSession) -> str:
    cut(spark.range(1))  # names the shared folder where the session has none
    return f"{spark.sparkContext.getCheckpointDir()}/stream-{uuid.uuid4().hex}"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream with event time."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*").parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def _daily(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("total"))


def tumbling_counts(events: DataFrame, place: str, late: str = "1 hour") -> DataFrame:
    """(day, event_type, n, total) of a stream of events, after all that is there was read.

    A row counts while its day is open: until the watermark, ``late`` behind the newest time seen, has passed the day's end.  Later
    rows are dropped and the state of closed days is let go.  Each micro-batch writes the days that it changed in a
    directory named by its number, and a day's last row counts, so that a repeated batch changes nothing.
    """

    def keep(batch: DataFrame, number: int) -> None:
        rows = batch.select(F.col("window.start").cast("timestamp_ntz").alias("day"), "event_type", "n", "total", F.lit(number).cast("bigint").alias("batch"))
        rows.write.mode("overwrite").parquet(f"{place}/out/batch_{number}")

    query = _daily(events, late).writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    seen = events.sparkSession.read.option("recursiveFileLookup", "true").schema("day timestamp_ntz, event_type string, n bigint, total double, batch bigint").parquet(f"{place}/out")
    return seen.groupBy("day", "event_type").agg(F.max_by(F.struct("n", "total"), "batch").alias("x")).select("day", "event_type", "x.n", "x.total")


def tumbling_replay(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts and sums by type from a replay of the whole stream."""
    return tumbling_counts(event_stream(spark, sf_dir), _place(spark))


def _written(rows: DataFrame, place: str, mode: str = "append") -> DataFrame:
    """All rows of a stream after what is there was read, through a file sink that counts each once."""
    query = rows.writeStream.outputMode(mode).format("parquet").option("path", f"{place}/out").option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    return rows.sparkSession.read.schema(rows.schema).parquet(f"{place}/out")


def followed(spark: SparkSession, sf_dir: str, first: str = "view", then: str = "purchase", hours: int = 24) -> DataFrame:
    """(event_id, next_id): events of one type and those of another by the same user within some hours after, as a join of two streams."""
    one = event_stream(spark, sf_dir).where(F.col("event_type") == first).select("event_id", "user_id", "ts").withWatermark("ts", "1 hour")
    two = event_stream(spark, sf_dir).where(F.col("event_type") == then).select(F.col("event_id").alias("next_id"), F.col("user_id").alias("next_user"), F.col("ts").alias("next_ts")).withWatermark("next_ts", "1 hour")
    near = F.expr(f"user_id = next_user AND next_ts > ts AND next_ts <= ts + INTERVAL {hours} HOURS")
    return _written(one.join(two, near).select("event_id", "next_id"), _place(spark))


def first_of_event(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_id, user_id): events of a stream in which every event is read twice, each kept once within the watermark."""
    twice = event_stream(spark, sf_dir).select("event_id", "user_id", "ts")
    return _written(twice.union(twice).withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"), _place(spark))


def repeats_by_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, n, n_types): events of each user and the types among them, held as state of the user's own."""
    import pandas as pd

    place = _place(spark)
    events = event_stream(spark, sf_dir).select("user_id", "event_type")

    def count(key, frames, state):
        n, seen = state.get if state.exists else (0, [])
        kinds = set(seen)
        for pdf in frames:
            n += len(pdf)
            kinds |= set(pdf["event_type"].dropna())
        state.update((n, sorted(kinds)))
        yield pd.DataFrame({"user_id": [key[0]], "n": [n], "n_types": [len(kinds)]})

    rows = events.groupBy("user_id").applyInPandasWithState(count, "user_id bigint, n bigint, n_types bigint", "n bigint, kinds array<string>", "update", "NoTimeout")

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{place}/out/batch_{number}")

    rows.writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start().awaitTermination()
    seen = spark.read.option("recursiveFileLookup", "true").schema("user_id bigint, n bigint, n_types bigint, batch int").parquet(f"{place}/out")
    return seen.groupBy("user_id").agg(F.max_by(F.struct("n", "n_types"), "batch").alias("x")).select("user_id", "x.n", "x.n_types")


def mend_stream(queries: DataFrame, base: DataFrame, root: str, n_near: int, max_rank: int, extra_cap: int, place: str, metric: str = "cosine"):
    """Mend a stored graph from a stream of (query_id, vec): each micro-batch sees the epoch before it and saves the next.

    The epoch at which a checkpoint folder begins is kept beside it.  A repeated batch replaces its own epoch, and a new
    checkpoint goes on from the newest epoch of the store.
    """
    spark = queries.sparkSession
    if not I._exists(spark, f"{place}/origin"):
        spark.createDataFrame([(I.newest(spark, root),)], "epoch int").coalesce(1).write.parquet(f"{place}/origin")
    origin = spark.read.parquet(f"{place}/origin").first()["epoch"]

    def mend(batch: DataFrame, number: int) -> None:
        edges = I.load(batch.sparkSession, root, origin + number)
        one = cut(batch.dropDuplicates(["query_id"]).select("query_id", "vec"))
        truth = cut(T.exact_blocked(base, one, max_rank, metric))
        proposals = M.vicinity(truth, edges, base, n_near, n_near, max_rank, metric)
        I.save(M.admit(edges, proposals, extra_cap), root, metric, epoch=origin + number + 1)

    return queries.writeStream.foreachBatch(mend).option("checkpointLocation", f"{place}/state").trigger(availableNow=True).start()


def mend_replay(spark: SparkSession, sf_dir: str, files: int = 3) -> DataFrame:
    """(kind, n_arcs): graph after an online replay of all history queries in a few micro-batches."""
    place = _place(spark)
    base, q = D.sphere(spark, sf_dir)
    base = cut(base)
    history = q.where("role = 'history'").select("query_id", "vec")
    history.repartition(files, "query_id").write.parquet(f"{place}/in")
    I.save(G.as_edges(G.knn(base, 6)), f"{place}/index")
    stream = spark.readStream.schema("query_id bigint, vec array<double>").option("maxFilesPerTrigger", 1).parquet(f"{place}/in")
    mend_stream(stream, base, f"{place}/index", 6, 30, 12, place).awaitTermination()
    return I.load(spark, f"{place}/index").groupBy("kind").agg(F.count(F.lit(1)).alias("n_arcs"))
