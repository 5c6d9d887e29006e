"""Batches that Spark hands to Python while a table is written."""

import pyarrow as pa
from pyspark.sql import functions as F

from vecmend.llm import common as C


def test_written_tables_give_python_small_batches(spark):
    def sizes(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([b.nbytes])], names=["n", "size"])

    before = spark.conf.get(C.BATCH_LIMIT)
    rows = spark.range(0, 3000, 1, 1).select(F.repeat(F.lit("x"), 10_000).alias("text"))
    got = C.durable(rows.mapInArrow(sizes, "n bigint, size bigint")).collect()
    assert sum(r.n for r in got) == 3000 and max(r["size"] for r in got) <= 2 * C.BATCH_BYTES
    assert spark.conf.get(C.BATCH_LIMIT) == before
