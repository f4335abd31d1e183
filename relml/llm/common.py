"""Shared plumbing of the training-data operators: inputs, shared storage, Arrow helpers."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import threading
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


_BATCH_BYTES = 4 << 20


def bound_batches(spark: SparkSession) -> None:
    """Bound the bytes of Arrow batches in this session, so that memory does not grow with the length of texts."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(key)) > _BATCH_BYTES:
        spark.conf.set(key, f"{_BATCH_BYTES}b")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    bound_batches(spark)
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """Folder that the driver and all executors see: spark.checkpoint.dir of the session.  Where it is unset, one of our
    own, but only if the executors run within the driver; on a cluster a local folder would lose files, so that is an error."""
    held = spark.conf.get("spark.checkpoint.dir", None)
    if held:
        return held.rstrip("/")
    jsc = spark.sparkContext._jsc.sc()
    if jsc.getCheckpointDir().isEmpty():
        if not jsc.isLocal():
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="relml-"))
    return jsc.getCheckpointDir().get().rstrip("/")


_scopes: list[list[str]] = []


def new_path(spark: SparkSession, label: str) -> str:
    path = f"{shared_dir(spark)}/relml-{label}-{uuid.uuid4().hex[:12]}"
    for scope in _scopes:
        scope.append(path)
    return path


@contextlib.contextmanager
def scratch(spark: SparkSession):
    """What is written to the shared folder within goes at the end: for results that are stored elsewhere before."""
    paths: list[str] = []
    _scopes.append(paths)
    try:
        yield
    finally:
        _scopes.remove(paths)
        for path in paths:
            delete(spark, path)


def delete(spark: SparkSession, path: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(path)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def settle(df: DataFrame, label: str, path: str | None = None) -> DataFrame:
    """Write df to the shared folder and read it back: cuts lineage and survives lost executors."""
    spark = df.sparkSession
    path = path or new_path(spark, label)
    df.write.option("compression", "zstd").parquet(path)
    spark.sparkContext._jvm.System.gc()  # lets Spark's cleaner delete shuffle files that nothing refers to any more
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Delete the files of a table that settle() wrote and that nothing reads any more."""
    spark = df.sparkSession
    for parent in {f.rsplit("/", 1)[0] for f in df.inputFiles() if "/relml-" in f}:
        delete(spark, parent)


def held_out(doc_id: str | Column, mod: int, rest: int) -> Column:
    """True where crc32 of the id as text leaves that remainder; a null id counts as the text ''."""
    c = F.col(doc_id) if isinstance(doc_id, str) else doc_id
    return (F.crc32(F.coalesce(c.cast("string"), F.lit("")).cast("binary")) % mod) == rest


def map_batches(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema: str, rows: int | None = None) -> DataFrame:
    """mapInArrow with one set-up call for each task.  rows: most rows of a batch that are taken at a time; after the last,
    freed memory goes back to the system, as the worker outlives its task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for batch in batches:
            for at in range(0, batch.num_rows, rows or batch.num_rows or 1):
                yield step(batch.slice(at, rows))
        del step
        give_back()

    bound_batches(df.sparkSession)
    return df.mapInArrow(run, schema)


_kept: dict = {}
_lock = threading.RLock()
CACHE_BYTES = 48 << 20
LARGE_CACHE_BYTES = 256 << 20  # where misses are dear and nothing else runs in the worker


def kept_by_worker(key, make: Callable):
    """The one thing that a worker process keeps between tasks; another key takes its place, so that what one operator
    holds does not stay while the next runs."""
    with _lock:
        if key not in _kept:
            _kept.clear()
            give_back()
            _kept[key] = make()
            give_back()
        return _kept[key]


class Known(dict):
    """Results by key, worked out on first use.  Beyond a number of bytes the later half is forgotten: what came first is what
    comes often."""

    def __init__(self, learn: Callable | None = None, limit: int = CACHE_BYTES, size: Callable = len):
        super().__init__()
        self.learn, self.limit, self.size, self.bytes = learn, limit, size, 0

    def __missing__(self, key):
        got = self.learn(key)
        self.keep(key, got)
        return got

    def keep(self, key: str, value) -> None:
        if self.bytes > self.limit:
            keys = list(self)[len(self) // 2 :]
            for k in keys:
                del self[k]
            self.bytes //= 2
        self.bytes += 200 + 2 * len(key) + self.size(value)  # headers of two objects and a slot
        self[key] = value

    def clear(self) -> None:
        super().clear()
        self.bytes = 0


def give_back() -> None:
    """Return memory that Arrow and the C library hold unused, where the C library can."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def texts_of(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    return [x or "" for x in batch.column(name).to_pylist()]


def keep(batch: pa.RecordBatch, mask) -> pa.RecordBatch:
    return batch.filter(pa.array(mask, pa.bool_()))
