"""Cutting lineage in the shared checkpoint folder."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame


#: Bytes of a batch that Spark hands to Python while a table is written; its own limit is 64 MB, which Python objects multiply.
BATCH_BYTES, BATCH_LIMIT = 4 << 20, "spark.sql.execution.arrow.maxBytesPerBatch"


def cut(df: DataFrame) -> DataFrame:
    """Checkpoint in the folder that ``spark.checkpoint.dir`` names; one of our own only where it is unset."""
    context = df.sparkSession.sparkContext
    if not context.getCheckpointDir():
        named = context.getConf().get("spark.checkpoint.dir", None)
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="vecmend-checkpoint-"))
    conf = df.sparkSession.conf
    limit = conf.get(BATCH_LIMIT)
    conf.set(BATCH_LIMIT, BATCH_BYTES)
    try:
        return df.checkpoint(eager=True)
    finally:
        conf.set(BATCH_LIMIT, limit)
