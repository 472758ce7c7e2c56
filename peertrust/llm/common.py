"""Small helpers shared by the training-data operators."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import re
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: ``spark.checkpoint.dir``.

    Only where the session names none and all runs on one machine (tests), a temporary
    folder is made and set as the checkpoint folder; elsewhere that is an error.
    """
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        sc = spark.sparkContext
        current = sc._jsc.sc().getCheckpointDir()
        if current.isDefined():
            path = current.get()
        elif re.match(r"local(\[|$)", sc.master):
            path = tempfile.mkdtemp(prefix="peertrust-")
            atexit.register(shutil.rmtree, path, ignore_errors=True)
            sc.setCheckpointDir(path)
        else:
            raise RuntimeError("spark.checkpoint.dir has to name a folder that all executors share")
    return path.rstrip("/")


def saved(df: DataFrame) -> DataFrame:
    """``df`` written once as Parquet in the shared folder and read back.

    Cuts the lineage, so a lost executor costs a re-read and not a recompute.  The files
    go when the session ends.
    """
    spark = df.sparkSession
    folder = f"{shared_dir(spark)}/peertrust-{uuid.uuid4().hex}"
    target = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = target.getFileSystem(spark._jsc.hadoopConfiguration())
    fs.mkdirs(target)
    fs.deleteOnExit(target)
    df.write.parquet(f"{folder}/data")
    return spark.read.schema(df.schema).parquet(f"{folder}/data")


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(name: str = "text") -> Column:
    """Null texts count as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def id_and_text(docs: DataFrame, *more: Column) -> DataFrame:
    """Just ``doc_id`` and a non-null ``text`` (plus ``more``): extra columns of
    the caller's table never meet the operators' own names."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"), *more)


def fresh(df: DataFrame, name: str) -> str:
    """A column name that ``df`` does not have, whatever its own columns are called."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of an Arrow string column, and the ``len + 1`` offsets of its
    values in them; nulls are empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_string())
    offsets = np.frombuffer(column.buffers()[1], dtype=np.int64)[column.offset : column.offset + len(column) + 1]
    data = column.buffers()[2]
    data = np.frombuffer(data, dtype=np.uint8) if data is not None else np.empty(0, np.uint8)
    if not len(offsets):
        return data[:0], np.zeros(1, np.int64)
    return data[offsets[0] : offsets[-1]], offsets - offsets[0]


def trim() -> None:
    """Gives freed memory back: idle workers stay, and should hold little."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def slices(batch: pa.RecordBatch, column: str, limit: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in pieces of consecutive rows of about ``limit`` text bytes (a
    longer text is a piece of its own), so that memory follows ``limit``."""
    _, offsets = utf8(batch.column(batch.schema.get_field_index(column)))
    n, at = len(offsets) - 1, 0
    while at < n:
        end = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        end = min(max(end, at + 1), n)
        yield batch.slice(at, end - at)
        at = end
    trim()


def unit_hash(*parts) -> Column:
    """A uniform number in (0, 1) from a hash of ``parts``: the same on every run."""
    bits = F.shiftrightunsigned(F.xxhash64(*parts), 11)
    return (bits.cast("double") + 0.5) / F.lit(float(1 << 53))
