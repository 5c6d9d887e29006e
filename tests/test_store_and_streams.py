"""The index store, vector files, late rows of a stream, and online mending over several checkpoints."""

import datetime as dt
import struct

import pytest
from pyspark.sql import functions as F

from vecmend.operators import graph as G
from vecmend.sources import families as D
from vecmend.sources import store as I
from vecmend.sources import vector_files
from vecmend.streaming import online as O


def test_store_counts_committed_epochs(spark, tmp_path):
    root = str(tmp_path / "index")
    edges = spark.createDataFrame([(1, 2, "base", 0, 0, -1, -1), (1, 3, "extra", 0, 9, 0, 0)], G.EDGES)
    assert I.newest(spark, root) is None and I.save(edges, root, config={"cap": "2"}) == 0
    more = spark.createDataFrame([(1, 2, "base", 0, 0, -1, -1), (1, 4, "extra", 0, 9, 0, 0), (1, 5, "extra", 0, 9, 1, 1)], G.EDGES)
    assert I.save(more, root) == 1 and I.save(more, root, epoch=1) == 1 and I.manifest(spark, root).count() == 2
    assert I.load(spark, root).count() == 3 and I.load(spark, root, 0).count() == 2
    only = I.load(spark, root, kind="extra")
    assert {r.dst for r in only.collect()} == {4, 5}
    assert I.save(more, root) == 2 and I.prune(spark, root, 1) == [1, 0] and I.load(spark, root).count() == 3


def test_vector_files_read_by_ranges(spark, tmp_path):
    path = tmp_path / "v.fvecs"
    rows = [[float(i), i / 2, -1.0] for i in range(25)]
    path.write_bytes(b"".join(struct.pack("<i3f", 3, *r) for r in rows))
    vector_files.register(spark)
    got = spark.read.format("float_vectors").option("path", str(path)).option("records", "10").load()
    assert got.rdd.getNumPartitions() == 3
    assert {r.vec_id: list(r.vec) for r in got.collect()} == dict(enumerate(rows))
    empty = tmp_path / "none.fvecs"
    empty.write_bytes(b"")
    assert spark.read.format("float_vectors").load(str(empty)).count() == 0


def test_rows_after_the_watermark_are_dropped(spark, tmp_path):
    place = str(tmp_path)
    at = lambda d, h: dt.datetime(2024, 1, d, h)
    batches = [[(at(1, 10), "a", 1.0)], [(at(3, 12), "a", 1.0)], [(at(1, 11), "a", 5.0), (at(3, 1), "a", 2.0)]]
    schema = "ts timestamp, event_type string, value double"
    counts = None
    for b in batches:  # one file a run, so that each run is a micro-batch with the watermark of those before
        spark.createDataFrame(b, schema).coalesce(1).write.mode("append").parquet(f"{place}/in")
        counts = O.tumbling_counts(spark.readStream.schema(schema).parquet(f"{place}/in"), f"{place}/run")
    got = {(r.day.day, r.n, r.total) for r in counts.collect()}
    # the late row of day 1 came after its day was closed; that of day 3 is in time
    assert got == {(1, 1, 1.0), (3, 2, 3.0)}


def test_online_mend_goes_on_after_a_new_checkpoint(spark, tiny, tmp_path):
    place, root = str(tmp_path), str(tmp_path / "index")
    base, q = D.sphere(spark, tiny)
    base = base.where("vec_id < 100").cache()
    history = q.where("role = 'history'").select("query_id", "vec").limit(20).cache()
    I.save(G.as_edges(G.knn(base, 3)), root)
    for n, part in enumerate((history.where("query_id % 2 = 0"), history.where("query_id % 2 = 1"))):
        part.coalesce(1).write.parquet(f"{place}/in{n}")
        stream = spark.readStream.schema("query_id bigint, vec array<double>").parquet(f"{place}/in{n}")
        O.mend_stream(stream, base, root, 5, 20, 4, f"{place}/run{n}").awaitTermination()
    sizes = [I.load(spark, root, e).where("kind = 'extra'").count() for e in range(3)]
    assert I.newest(spark, root) == 2 and sizes[0] == 0 < sizes[1] <= sizes[2]
    assert I.load(spark, root).where("kind = 'extra'").agg(F.max("epoch")).first()[0] == 1


@pytest.mark.parametrize("hours", (1, 24))
def test_stream_join_equals_batch_join(spark, tiny, hours):
    from vecmend.operators import joins as J

    e = D.table(spark, tiny, "events").select("event_id", "user_id", "ts", "event_type")
    want = J.within_span(e.where("event_type = 'view'").drop("event_type"), e.where("event_type = 'purchase'").drop("event_type"), "user_id", "ts", 3600 * hours)
    pairs = {(r.event_id, r.event_id_r) for r in want.collect()}
    assert {(r.event_id, r.next_id) for r in O.followed(spark, tiny, hours=hours).collect()} == pairs
