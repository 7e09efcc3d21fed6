"""Pieces shared by the text operators: shared storage, sized joins, byte-bounded batches."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A side of a join is broadcast up to this many bytes; beyond it the join shuffles.
BROADCAST_BYTES = 24 << 20
#: Kernels see slices of about this many bytes of text, so that numpy scratch stays in cache.
CHUNK_BYTES = 1 << 19
#: Bytes of one Arrow batch between an executor and its Python workers where :func:`small_batches` holds.
BATCH_BYTES = 4 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only in a single-machine session that names none."""
    sc = spark.sparkContext
    base = spark.conf.get("spark.checkpoint.dir", None) or sc.getConf().get("spark.checkpoint.dir") or sc.getCheckpointDir()
    if not base:
        if sc.master != "local" and not sc.master.startswith("local["):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="shared-")
        sc.setCheckpointDir(base)
    return base.rstrip("/")


_SCRATCH: list[list[tuple[SparkSession, str]]] = []


@contextmanager
def scratch() -> Iterator[None]:
    """What :func:`materialize` writes inside is removed at the end, but for what is to be kept."""
    _SCRATCH.append([])
    try:
        yield
    finally:
        for spark, path in _SCRATCH.pop():
            place = spark._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)


def new_path(spark: SparkSession, tag: str, keep: bool = True) -> str:
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    if _SCRATCH and not keep:
        _SCRATCH[-1].append((spark, path))
    return path


def release() -> None:
    """Let Spark's cleaner drop shuffle files of plans that are no longer referenced."""
    gc.collect()
    session = SparkSession.getActiveSession()
    if session is not None:
        session.sparkContext._jvm.System.gc()


def materialize(df: DataFrame, tag: str, keep: bool = False) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage is cut and survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, tag, keep)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    release()
    return out


@contextmanager
def small_batches(spark: SparkSession, limit: int = BATCH_BYTES) -> Iterator[None]:
    """Jobs that run inside exchange Arrow batches of about ``limit`` bytes; Spark's 64 MB are held by the executor, as it grows them, and by the worker."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(key)
    spark.conf.set(key, str(limit))
    try:
        yield
    finally:
        spark.conf.set(key, before)


def give_back() -> None:
    """Return free memory of this process to the system; allocators keep it otherwise, and workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc alone has it
    if trim is not None:
        trim(0)


def map_batches(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema) -> DataFrame:
    """``df.mapInArrow(run, schema)`` whose workers give memory back after each task."""

    def lean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return df.mapInArrow(lean, schema)


def stored_bytes(df: DataFrame) -> int:
    """Bytes of the files behind a materialized frame, as Catalyst's own statistics have them."""
    return int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))


def sized(df: DataFrame, limit: int = BROADCAST_BYTES, inflation: int = 4) -> DataFrame:
    """Mark a materialized frame for broadcast when its files, inflated to rows, fit the limit."""
    return F.broadcast(df) if stored_bytes(df) * inflation <= limit else df


#: Rows of one key from which it is joined apart from the others.
HOT_ROWS = 100_000


def label_rows(rows: DataFrame, label: DataFrame, key: str, hot: int = HOT_ROWS) -> DataFrame:
    """Join materialized ``label`` (key, labels, n), one row a key with its number of rows, to the rows.

    A small label table is broadcast.  Of a large one only the keys of at least
    ``hot`` rows are: they are at most one for each ``hot`` rows, and their rows
    stay where they are, so no key puts more than that into one task.
    """
    if stored_bytes(label) * 4 <= BROADCAST_BYTES:
        return rows.join(F.broadcast(label.drop("n")), key)
    many, few = (label.where(c).drop("n") for c in (F.col("n") >= hot, F.col("n") < hot))
    return rows.join(F.broadcast(many), key).unionByName(rows.join(F.broadcast(many.select(key)), key, "left_anti").join(few, key))


def extended(schema: T.StructType, ddl: str) -> T.StructType:
    """The schema with the DDL's columns after its own."""
    return T.StructType([*schema.fields, *T.StructType.fromDDL(ddl).fields])


def null_safe(left: DataFrame, right: DataFrame, keys: list[str]):
    cond = None
    for k in keys:
        c = left[k].eqNullSafe(right[k])
        cond = c if cond is None else cond & c
    return cond


def text_slices(batch: pa.RecordBatch, column: str, limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Zero-copy slices of a batch that hold about ``limit`` bytes of text, at least one row each."""
    if batch.num_rows == 0:
        return
    col = batch.column(batch.schema.get_field_index(column))
    ends = np.cumsum(pc.fill_null(pc.binary_length(col), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    lo = 0
    while lo < len(ends):
        base = ends[lo - 1] if lo else 0
        hi = max(lo + 1, int(np.searchsorted(ends, base + limit, "right")))
        yield batch.slice(lo, hi - lo)
        lo = hi


def texts_of(batch: pa.RecordBatch, column: str) -> list[str]:
    """Texts of a batch with nulls as empty strings."""
    return [t or "" for t in batch.column(batch.schema.get_field_index(column)).to_pylist()]


#: Words that a worker process remembers for one operator.
MEMORY = 800_000
#: Operators that work word by word take larger slices, which repeat more of their words.
WORD_BYTES = 4 << 20


class Memory:
    """What a worker process has worked out for words; results do not depend on what it holds.

    Common words come early and stay; once full, what the next slices need
    beside it is worked out for each slice alone and forgotten at the next call.
    """

    def __init__(self, work: Callable[[list[str]], list], limit: int = MEMORY):
        self.work, self.limit, self.known, self.passing = work, limit, {}, ()

    def __call__(self, words: set[str]) -> dict:
        for w in self.passing:
            del self.known[w]
        self.passing = ()
        new = list(words.difference(self.known))
        if new:
            full = len(self.known) + len(new) > self.limit
            self.known.update(zip(new, self.work(new)))
            self.passing = new if full else ()
        return self.known
