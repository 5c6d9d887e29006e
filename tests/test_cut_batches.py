"""Batches that Spark hands to Python while lineage is cut, and batches of neighbours that go back."""

import pyarrow as pa
from pyspark.sql import functions as F

from vecmend.plans import lineage as L


def test_cut_tables_give_python_small_batches(spark):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], names=["n", "size"])

    before = spark.conf.get(L.BATCH_LIMIT)
    rows = spark.range(0, 3000, 1, 1).select(F.repeat(F.lit("x"), 10_000).alias("text"))
    got = L.cut(rows.mapInArrow(sizes, "n bigint, size bigint")).collect()
    assert sum(r.n for r in got) == 3000 and max(r["size"] for r in got) <= 2 * L.BATCH_BYTES
    assert spark.conf.get(L.BATCH_LIMIT) == before
