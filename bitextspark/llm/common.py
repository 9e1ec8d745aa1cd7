"""Helpers that the operators of this folder share."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

#: Code points of words' separators; bytes.split() without arguments splits at the same six bytes.
SEPARATORS = "\x20\x09\x0a\x0b\x0c\x0d"

_own_dir: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder for cut tables: spark.checkpoint.dir, or one of our own where that is unset (tests)."""
    base = spark.conf.get("spark.checkpoint.dir", "") or spark.sparkContext.getConf().get("spark.checkpoint.dir", "")
    if base:
        return base.rstrip("/")
    if not _own_dir:
        _own_dir.append(tempfile.mkdtemp(prefix="bitextspark-"))
    return _own_dir[0]


def cut(df: DataFrame, tag: str) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back.

    Cuts the lineage: a lost executor only costs the tasks that ran on it, and
    what was computed is read, not computed again, by each later use. The
    tables stay until the folder is cleared, since results are lazy.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/cut-{uuid.uuid4().hex}/{tag}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def as_bytes(column: pa.Array | pa.ChunkedArray) -> list[bytes | None]:
    """Texts as UTF-8 bytes, None for null."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return column.cast(kind).to_pylist()


def slices(batch: pa.RecordBatch, column: str, most_bytes: int = 4 << 20):
    """A batch in runs of rows whose texts hold about most_bytes, so memory doesn't follow the texts' lengths."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
    start = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > most_bytes:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield batch.slice(start)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tidy(run, cycles: bool = True):
    """run for mapInArrow, with a worker's free memory given back when a task ends: workers are reused, and what a task has freed would stay with them.

    cycles=False is for a run whose rows leave no reference cycles behind: the
    collector, which would walk its memos again and again, rests until the task ends.
    """

    def tidied(batches):
        if not cycles:
            gc.disable()
        try:
            yield from run(batches)
        finally:
            gc.enable()
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL("libc.so.6").malloc_trim(0)
            except (OSError, AttributeError):
                pass  # another C library; memory stays with the worker

    return tidied
