"""What the corpus operators share: the cluster's shared folder, tables cut loose from lineage, table access."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import re
import sys
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from coltypes.shipping import ship

#: Rows and bytes in one Arrow batch sent to a Python worker; what a worker holds at once follows from it.
BATCH_ROWS = 1000
BATCH_BYTES = 2 << 20


def prepare(spark: SparkSession) -> SparkSession:
    """Bound the Arrow batches of this session (runtime settings; smaller ones stay), and let its workers import this package."""
    ship(spark)
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        now = spark.conf.get(key, None)
        if now is None or not str(now).isdigit() or not 0 < int(now) <= most:
            spark.conf.set(key, str(most))
    # small tables become few files: each file that is written forks the executor's JVM where Hadoop's native library is missing
    spark.conf.set("spark.sql.adaptive.coalescePartitions.parallelismFirst", "false")
    return spark


def lean() -> None:
    """Called by an operator in a worker: free what the encoders of another one keep in it, as workers are used again."""
    held = sys.modules.get("coltypes.llm.bpe")
    if held is not None and held.READY:
        held.READY.clear()
        gc.collect()
        with contextlib.suppress(OSError, AttributeError):
            ctypes.CDLL("libc.so.6").malloc_trim(0)


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; only where that is unset and all runs on one machine (tests) a folder of this machine."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="coltypes-")
        spark.conf.set("spark.checkpoint.dir", folder) if spark.conf.isModifiable("spark.checkpoint.dir") else None
        _OWN.setdefault(spark.sparkContext.applicationId, folder)
        folder = _OWN[spark.sparkContext.applicationId]
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(folder)
    return folder.rstrip("/")


_OWN: dict[str, str] = {}


def fresh_path(spark: SparkSession, tag: str) -> str:
    """A path in the shared folder that nothing else uses."""
    return f"{shared_dir(spark)}/coltypes/{tag}-{uuid.uuid4().hex[:12]}"


def remove(spark: SparkSession, *paths: str) -> None:
    """Delete tables that no later plan reads."""
    jvm = spark.sparkContext._jvm
    for path in paths:
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def stored(df: DataFrame, tag: str) -> tuple[DataFrame, str]:
    """Write a frame to the shared folder and read it again: its lineage ends there, so a lost executor costs no recomputation."""
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def settled(df: DataFrame) -> DataFrame:
    """A result as an eager checkpoint: what it was made from may be deleted, and Spark may clean it once nothing refers to it."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_remainder(doc_id: Column, modulus: int) -> Column:
    """crc32 of the decimal id, modulo; null for a null id."""
    return F.crc32(doc_id.cast("string")) % modulus


def texts_of(column: pa.ChunkedArray | pa.Array) -> list[str]:
    """Python strings, null as empty."""
    return [t or "" for t in column.to_pylist()]


def pieces(batch: pa.RecordBatch, column: str, most: int = 1 << 19):
    """Slices of a batch with at most so many bytes of text each, one row at least."""
    sizes = batch.column(column).cast(pa.large_string())
    lengths = pa.compute.fill_null(pa.compute.binary_length(sizes), 0).to_numpy(zero_copy_only=False)
    first = held = 0
    for at, size in enumerate(lengths):
        if at > first and held + size > most:
            yield batch.slice(first, at - first)
            first, held = at, 0
        held += int(size)
    if batch.num_rows > first:
        yield batch.slice(first)
