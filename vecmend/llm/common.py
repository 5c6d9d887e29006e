"""Helpers shared by the corpus operators."""

from __future__ import annotations

import atexit
import gc
import sys
import tempfile
import types
import uuid
from collections.abc import Callable, Iterator
from typing import Any

import numpy as np
import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: What the contracts call white space: space and the ASCII controls 9 to 13.
WHITE = "[ \\t-\\r]+"
#: Bytes of a batch that Spark hands to Python.  By Spark's own limit, 64 MB, a batch is held by the JVM outside its heap and again by the worker.
BATCH_BYTES, BATCH_LIMIT = 4 << 20, "spark.sql.execution.arrow.maxBytesPerBatch"


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share, as the session names it.

    ``spark.checkpoint.dir`` is read from the session; only where it is unset
    (tests on one machine) a folder of our own is set.
    """
    context = spark.sparkContext
    if not context.getCheckpointDir():
        named = context.getConf().get("spark.checkpoint.dir", None)
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="vecmend-checkpoint-"))
    return context.getCheckpointDir()


def durable(df: DataFrame) -> DataFrame:
    """Cut the lineage: write the rows as a Parquet table in the shared folder and read it again.

    The table is smaller than a checkpoint of rows, keeps its columns apart, and
    outlives any executor.  It is deleted when the session's process ends.  While it is
    written, batches for Python are limited to ``BATCH_BYTES``.  What is such a table already is not written again.
    """
    spark = df.sparkSession
    if getattr(df, "_vecmend_table", None) in getattr(spark, "_vecmend_tables", []):
        return df
    path = f"{shared_folder(spark)}/table-{uuid.uuid4().hex}"
    limit = spark.conf.get(BATCH_LIMIT)
    spark.conf.set(BATCH_LIMIT, BATCH_BYTES)
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(BATCH_LIMIT, limit)
    if not hasattr(spark, "_vecmend_tables"):
        spark._vecmend_tables = []
        atexit.register(_forget, spark)
    spark._vecmend_tables.append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._vecmend_table = path
    return out


def let_go(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of finished jobs now: its cleaner waits for the driver to collect garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def tables_written(spark: SparkSession) -> int:
    """Number of tables that ``durable`` has written in this session, as a mark for ``forget_since``."""
    return len(getattr(spark, "_vecmend_tables", []))


def forget_since(spark: SparkSession, mark: int) -> None:
    """Delete the tables written after the mark but the last, from which the result of the work between was read."""
    done = getattr(spark, "_vecmend_tables", [])[mark:-1]
    _delete(spark, done)
    for path in done:
        spark._vecmend_tables.remove(path)


def _delete(spark: SparkSession, paths: list[str]) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for path in paths:
        place = jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(conf).delete(place, True)


def _forget(spark: SparkSession) -> None:
    if spark.sparkContext._jsc is None:  # the session is gone; what stays lies in its checkpoint folder
        return
    try:
        _delete(spark, spark._vecmend_tables)
    except (Py4JError, OSError):  # its process ended first
        return


# --- range partitioning by sampled splitters -----------------------------------------


def splitters(sample: DataFrame, parts: int) -> np.ndarray:
    """Quantiles of a bounded sample of long columns, as rows that cut the key space into ``parts`` ranges."""
    rows = sample.toPandas().to_numpy(dtype=np.int64).reshape(-1, len(sample.columns))
    rows = rows[np.lexsort(rows.T[::-1])]
    if not len(rows):
        return rows
    return rows[np.unique(np.linspace(0, len(rows), parts + 1).astype(np.int64)[1:-1])]


def deal(keys: list[np.ndarray], cuts: np.ndarray) -> np.ndarray:
    """Range of each key row; the later columns decide where the first equals a cut."""
    low, high = (np.searchsorted(cuts[:, 0], keys[0], side) for side in ("left", "right"))
    out = low.astype(np.int64)
    tied = np.flatnonzero(low < high)
    step = 0
    while len(tied):
        cut = cuts[low[tied] + step]
        above = np.zeros(len(tied), dtype=bool)
        same = np.ones(len(tied), dtype=bool)
        for k in range(1, len(keys)):
            value = keys[k][tied]
            above |= same & (value > cut[:, k])
            same &= value == cut[:, k]
        out[tied[above]] += 1
        step += 1
        tied = tied[above & (low[tied] + step < high[tied])]
    return out


def dealt(rows: DataFrame, parts: int, keys: list[str]) -> DataFrame:
    """Rows with a ``bucket`` column, each bucket in a partition of its own, sorted by ``keys``."""
    return rows.repartitionById(parts, F.col("bucket").cast("int")).select(*[c for c in rows.columns if c != "bucket"]).sortWithinPartitions(*keys)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def once_per_worker(key: str, make: Callable[[], Any]) -> Any:
    """Build a value once in each Python worker process.

    The operators' functions are shipped by value, so module globals do not
    outlive a task; the cache hangs on a module of its own instead.
    """
    cache = sys.modules.setdefault("_vecmend_worker_cache", types.ModuleType("_vecmend_worker_cache"))
    if not hasattr(cache, key):
        setattr(cache, key, make())
    return getattr(cache, key)


def bound(name: str, body: Callable, value) -> Any:
    """Evaluate ``value`` once and use it many times inside ``body``.

    Catalyst may repeat a column expression wherever it is named; the variable
    of a one-element transform is computed once per row.
    """
    return F.get(F.transform(F.array(value), lambda x: body(x)), F.lit(0)).alias(name)


# --- vectorised hashing of words inside Arrow batches ------------------------------

_ODD = 0x9E3779B97F4A7C15
_STEP = 0xD6E8FEB86659FD93


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser of 64-bit hashes (xor-shift and multiply, a bijection)."""
    x = x ^ (x >> np.uint64(32))
    x = x * np.uint64(_STEP)
    x = x ^ (x >> np.uint64(29))
    x = x * np.uint64(_ODD)
    return x ^ (x >> np.uint64(32))


def _powers(n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Powers of an odd multiplier, of its inverse modulo 2**64, and a code for each byte."""

    def make() -> list:
        return [0, None, None, mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(_ODD))]

    kept = once_per_worker("hash_powers", make)
    if kept[0] < n:
        size = max(n, 1 << 20)
        multiplier = 0x5851F42D4C957F2D
        inverse = pow(multiplier, -1, 1 << 64)
        for slot, value in ((1, multiplier), (2, inverse)):
            steps = np.full(size, value, dtype=np.uint64)
            steps[0] = 1
            kept[slot] = np.multiply.accumulate(steps)
        kept[0] = size
    return kept[1], kept[2], kept[3]


def prefix_hashes(data: np.ndarray) -> np.ndarray:
    """Running polynomial hash of bytes; entry i covers the first i bytes."""
    up, _, codes = _powers(len(data) + 1)
    out = np.zeros(len(data) + 1, dtype=np.uint64)
    np.cumsum(codes[data] * up[: len(data)], out=out[1:])
    return out


def span_hashes(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Position-free hashes of the byte spans [start, end)."""
    _, down, _ = _powers(len(prefix))
    return mix((prefix[end] - prefix[start]) * down[start])


def byte_slices(ids: list, texts: list[bytes], most: int = 1 << 20) -> Iterator[tuple[list, list[bytes]]]:
    """Cut a batch into runs of whole texts of about ``most`` bytes, to bound temporaries."""
    start, held = 0, 0
    for i, text in enumerate(texts):
        held += len(text)
        if held >= most:
            yield ids[start : i + 1], texts[start : i + 1]
            start, held = i + 1, 0
    if start < len(texts):
        yield ids[start:], texts[start:]


def in_slices(run: Callable) -> Callable:
    """Wrap a function of Arrow batches so that it sees slices of 1024 rows and about 4 MB, and gives memory back.

    Workers live on between tasks, so what the allocators keep would add up over stages.
    """

    def sliced(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = max(1, min(1024, int(batch.num_rows * (4 << 20) / max(batch.nbytes, 1))))
            for i in range(0, batch.num_rows, rows):
                yield batch.slice(i, rows)

    def wrapped(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import ctypes

        trim = once_per_worker("trim", lambda: getattr(ctypes.CDLL(None), "malloc_trim", lambda _: 0))
        sent = 0
        for out in run(sliced(batches)):
            yield out
            sent += 1
            if sent % 16 == 0:
                trim(0)
        pa.default_memory_pool().release_unused()
        trim(0)

    return wrapped


def utf8(column: pa.Array) -> list[bytes]:
    """Texts of an Arrow column as UTF-8 bytes; null counts as empty."""
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]


def to_frame(columns: dict, schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) for f in schema], schema=schema)
