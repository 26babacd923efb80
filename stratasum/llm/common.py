"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import ctypes
import gc
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Python code works on slices of about so many bytes of text, whatever the size of Spark's batches.
SLICE_BYTES = 4 << 20
#: Bytes of a batch between Spark and a Python worker, where the session sets no limit; a longer row is a batch of its own.
BATCH_BYTES = 8 << 20
BATCH_LIMIT = "spark.sql.execution.arrow.maxBytesPerBatch"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; the path may be in any store that Spark's readers know."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A new folder name under the checkpoint folder of the session, which driver and executors share, in a folder of this application.

    Only in local mode, where they are one process, a session without one gets a temporary folder.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + tempfile.mkdtemp(prefix="stratasum-")
        spark.sparkContext.setCheckpointDir(base)
    return f"{base.rstrip('/')}/tables/{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """The same rows from a table written in the shared folder: lost executors do not lose it."""
    spark, path = df.sparkSession, shared_dir(df.sparkSession)
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_at = path
    return out


def drop(*tables: DataFrame | str) -> None:
    """Removes tables that `cut` has written, or folders; nothing may read them after that."""
    spark = SparkSession.active()
    for t in tables:
        path = t if isinstance(t, str) else getattr(t, "_cut_at", None)
        if path:
            place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)


def drop_all(spark: SparkSession) -> None:
    """Removes all tables of this application. For the end of a job, when its results are elsewhere."""
    drop(shared_dir(spark).rpartition("/")[0])


def remainder(column: str, m: int) -> Column:
    """crc32 of the column's decimal text, modulo m; a null counts as the empty text."""
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit(""))) % m


def as_bytes(column: pa.Array) -> list[bytes | None]:
    return column.cast(pa.binary()).to_pylist()


def slices(batch: pa.RecordBatch, column: str = "text", most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Zero-copy parts of a batch whose texts have about `most` bytes together; one long text is a part of its own."""
    lengths = pa.compute.binary_length(batch.column(column)).fill_null(0).to_pylist()
    start, size = 0, 0
    for i, n in enumerate(lengths):
        if i > start and size + n > most:
            yield batch.slice(start, i - start)
            start, size = i, 0
        size += n
    if len(lengths) > start:
        yield batch.slice(start)


#: What this Python worker keeps from one task to the next: one object at most, by its name.
_kept: dict[tuple, object] = {}


def kept_in_worker(name: tuple | None, make: Callable[[], object] | None = None) -> object:
    """The object of that name that this worker has built before, or a new one.

    Workers outlive tasks and serve all operators in turn, so a task drops what another operator has
    left, and gives free memory back, before it builds its own; a task that keeps nothing (no name) does so, too.
    """
    if name not in _kept:
        _kept.clear()
        gc.collect()
        pa.default_memory_pool().release_unused()
        if hasattr(libc := ctypes.CDLL(None), "malloc_trim"):
            libc.malloc_trim(0)
    if name is None:
        return None
    if name not in _kept:
        _kept[name] = make()
    return _kept[name]


def map_texts(df: DataFrame, schema: str | T.StructType, make: Callable[..., Callable[[pa.RecordBatch], pa.RecordBatch | None]], column: str = "text", keeps: tuple[tuple, Callable[[], object]] | None = None) -> DataFrame:
    """mapInArrow in slices of bounded size. `make` runs once a task and gives the function of a slice.

    keeps: the name and the maker of an object that workers keep between tasks; `make` gets it.
    Batches are bounded by their bytes for the whole session, unless it has its own limit: texts have
    no usual length, and Spark's default of 10,000 rows may be any size.
    """
    if df.sparkSession.conf.get(BATCH_LIMIT, None) is None:
        df.sparkSession.conf.set(BATCH_LIMIT, str(BATCH_BYTES))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if keeps is None:
            kept_in_worker(None)
            one = make()
        else:
            one = make(kept_in_worker(*keeps))
        for batch in batches:
            for part in slices(batch, column):
                if (out := one(part)) is not None and out.num_rows:
                    yield out

    return df.mapInArrow(run, schema)
