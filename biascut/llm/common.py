"""Shared plumbing of the operators: the scratch folder, materialised tables, Arrow text access.

Scratch tables live in the folder that ``spark.checkpoint.dir`` names, because that is the one
place the driver and every executor can see.  A table written there cuts lineage: a lost executor
costs a re-read, never a recomputation of an earlier stage.
"""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """The shared scratch folder; a private one only where none is set and Spark runs locally."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    master = spark.sparkContext.master
    if not master.startswith("local") or master.startswith("local-cluster"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
    own = tempfile.mkdtemp(prefix="biascut-")
    spark.sparkContext.setCheckpointDir(own)
    return spark.sparkContext._jsc.sc().getCheckpointDir().get().rstrip("/")


_made: list[str] = []


def scratch_path(spark: SparkSession, name: str) -> str:
    _made.append(f"{shared_root(spark)}/biascut-{name}-{uuid.uuid4().hex[:12]}")
    return _made[-1]


def sweep(spark: SparkSession) -> None:
    """Delete every scratch table of this process; only when no result that reads them is wanted any more."""
    while _made:
        discard(spark, _made[-1])


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to a scratch table and return a DataFrame that reads it back."""
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._scratch = path
    return out


def drop(*tables: DataFrame) -> None:
    """Delete tables of ``materialize`` that no later plan reads."""
    for t in tables:
        discard(t.sparkSession, t._scratch)


def discard(spark: SparkSession, path: str) -> None:
    """Delete a scratch table that no later plan reads."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(conf).delete(p, True)
    if path in _made:
        _made.remove(path)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def row_id(*columns) -> list:
    """Two longs (_u1, _u2) that name a row by its values: 128 bits, so that no corpus holds a clash."""
    return [F.xxhash64(*columns).alias("_u1"), F.xxhash64(F.lit(11), *columns).alias("_u2")]


def held_out(modulus: int, doc_id: str = "doc_id"):
    """True where crc32 of the id's decimal text is divisible by ``modulus`` (null ids: false)."""
    return F.coalesce((F.crc32(F.col(doc_id).cast("string").cast("binary")) % modulus) == 0, F.lit(False))


def hashed_head(df: DataFrame, n: int, *keys: str) -> DataFrame:
    """The ``n`` rows of least key hash.  A bound on the hash, from the row count, leaves about 2n rows to
    order, so what meets in one place does not grow with the table."""
    share = F.shiftrightunsigned(F.xxhash64(*keys), 1)
    bound = min(1.0, 2 * n / max(df.count(), 1)) * float(1 << 63)
    return df.where(share.cast("double") <= bound).orderBy(share, *keys).limit(n)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(offsets, bytes) of a string column, nulls as empty texts, without copying the characters."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type)
    _, offsets, data = column.buffers()
    kind = np.int64 if wide else np.int32
    n = len(column)
    if n == 0 or offsets is None:
        return np.zeros(n + 1, np.int64), np.zeros(0, np.uint8)
    off = np.frombuffer(offsets, kind, n + 1, column.offset * kind().itemsize).astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return off - off[0], raw[off[0] : off[-1]]


def slices(offsets: np.ndarray, most: int):
    """Ranges of documents whose texts hold about ``most`` bytes together (one at least)."""
    i, n = 0, len(offsets) - 1
    while i < n:
        j = int(np.searchsorted(offsets, offsets[i] + most, side="right")) - 1
        j = min(max(j, i + 1), n)
        yield i, j
        i = j


_worker: dict = {}


def give_back() -> None:
    """Return freed memory to the system: Arrow's, and what the C library keeps between live blocks, which
    would stay in a reused worker beside the next stage's tables."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries lack the call
        ctypes.CDLL(None).malloc_trim(0)


def worker_state(module: str, key, make):
    """What an operator (a module) keeps in a Python worker between tasks.  There is one place for it: whoever
    asks for another state drops this one, so a reused worker holds nothing of an earlier stage."""
    if _worker.get("of") != (module, key):
        if _worker:
            _worker.clear()
            give_back()
        _worker.update(state=make(), of=(module, key))
        give_back()
    return _worker["state"]


def tidy(run):
    """Wraps a function over Arrow batches: drops what other operators left in the worker, and gives
    freed memory back when the task's rows end."""
    module = run.__module__

    def wrapped(batches):
        if _worker and _worker["of"][0] != module:
            _worker.clear()
            give_back()
        yield from run(batches)
        give_back()

    return wrapped


def batch(columns: dict[str, tuple[object, pa.DataType]]) -> pa.RecordBatch:
    """A record batch from (values, type) by column name."""
    return pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in columns.values()], names=list(columns))
