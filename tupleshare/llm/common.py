"""Helpers shared by the operators of this subpackage."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import tempfile
import uuid
import weakref
from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ascii_lower(c: Column) -> Column:
    """Lower-cases A-Z only, unlike lower(), which folds all of Unicode."""
    return F.translate(c, UPPER, LOWER)


def held_out(doc_id: Column) -> Column:
    """True for rows whose labels are never learnt from: crc32 of the id as text is 2 modulo 4. Null ids are not held out."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, as the session names it; a temporary one only where none is set (local tests)."""
    d = spark.conf.get("spark.checkpoint.dir", None)
    if d:
        return d.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    d = "file://" + tempfile.mkdtemp(prefix="tupleshare-")
    spark.conf.set("spark.checkpoint.dir", d)
    return d


def delete_path(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session may have gone; the folder is scratch
        pass


def materialize(df: DataFrame, name: str) -> DataFrame:
    """Writes a table in the shared folder and reads it back, which cuts lineage and survives lost executors.

    The columnar form is smaller than checkpoint()'s and is computed once. Removed when the driver ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/tupleshare-{name}-{uuid.uuid4().hex}"
    schema = df.schema
    df.write.parquet(path)
    atexit.register(delete_path, spark, path)
    out = spark.read.schema(schema).parquet(path)
    _WRITTEN[id(out)] = (weakref.ref(out), path)
    return out


_WRITTEN: dict[int, tuple[weakref.ref, str]] = {}


def discard(*tables: DataFrame) -> None:
    """Deletes what materialize() wrote for these; only for tables that nothing reads any more."""
    for df in tables:
        ref, path = _WRITTEN.pop(id(df), (lambda: None, ""))
        if ref() is df:
            delete_path(df.sparkSession, path)


#: Rows of an Arrow batch that become Python objects at once, and rows and bytes of a batch of texts.
SLICE, BATCH_ROWS, BATCH_BYTES = 256, 2000, 16 << 20


def bound_batches() -> None:
    """Lowers the session's Arrow batch size: a batch of texts is held by the JVM and by Python, in each running task."""
    spark = SparkSession.getActiveSession()
    if spark is not None:
        if int(spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")) > BATCH_ROWS:
            spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS)
        if spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch", "67108864b") in ("67108864b", "64m", "64MB"):  # the default
            spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", f"{BATCH_BYTES}b")


def release() -> None:
    """Gives freed memory back to the system: workers are used again, and what one stage held would count in the next."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library can trim
        ctypes.CDLL(None).malloc_trim(0)


def text_function(fn: Callable[[list], list], spark_type: str, arrow_type: pa.DataType) -> Callable[[Column], Column]:
    """A column function of texts as UTF-8 bytes; only a slice of a batch becomes Python objects at a time."""
    bound_batches()

    @F.arrow_udf(spark_type)
    def run(texts: pa.Array) -> pa.Array:
        parts = [pa.array(fn(texts.slice(at, SLICE).to_pylist()), type=arrow_type) for at in range(0, len(texts), SLICE)]
        release()
        return pa.concat_arrays(parts) if parts else pa.array([], type=arrow_type)

    return lambda text: run(text.cast("string").cast("binary"))


def over_slices(run: Callable[[Iterator[tuple[list, list]]], Iterator[pd.DataFrame]], schema: pa.Schema):
    """For mapInArrow over (id, text): hands `run` small lists of ids and texts, and types the frames it yields."""
    bound_batches()

    def adapted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def lists() -> Iterator[tuple[list, list]]:
            for b in batches:
                for at in range(0, b.num_rows, SLICE):
                    part = b.slice(at, SLICE)
                    yield part.column(0).to_pylist(), part.column(1).to_pylist()

        for frame in run(lists()):
            yield pa.RecordBatch.from_pandas(frame, schema=schema, preserve_index=False)
        release()

    return adapted
