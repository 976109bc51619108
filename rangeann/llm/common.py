"""Plumbing shared by the corpus operators: staging tables, Arrow helpers, bounded worker caches."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid
from collections.abc import Iterable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``, which driver and executors share.

    Only where neither that setting nor a checkpoint folder exists and the master is local (as in
    tests) a folder of this machine is made and set; on a cluster that is an error.
    """
    path = spark.conf.get("spark.checkpoint.dir", None)
    if path:
        return path.rstrip("/")
    sc = spark.sparkContext
    found = sc._jsc.sc().getCheckpointDir()
    if found.isDefined():
        return found.get().rstrip("/")
    if not sc.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    sc.setCheckpointDir(tempfile.mkdtemp(prefix="rangeann-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def staged(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage ends here and a lost executor costs nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Deletes a staged table that nothing will read again."""
    spark = df.sparkSession
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def binary_column(batch: pa.RecordBatch, name: str) -> list[bytes]:
    """UTF-8 bytes of a string column; null reads as empty."""
    return [b"" if x is None else x for x in batch.column(batch.schema.get_field_index(name)).cast(pa.binary()).to_pylist()]


def slices(sizes: Iterable[int], most: int) -> Iterator[tuple[int, int]]:
    """Index ranges whose sizes add up to about ``most`` (one item alone may exceed it)."""
    start = total = i = 0
    for i, n in enumerate(sizes, 1):
        total += n
        if total >= most:
            yield start, i
            start, total = i, 0
    if start < i:
        yield start, i


def column_slices(batch: pa.RecordBatch, name: str, most: int) -> Iterator[tuple[int, int, pa.Array]]:
    """A string column, some ``most`` bytes at a time."""
    column = batch.column(batch.schema.get_field_index(name))
    for a, b in slices(pc.fill_null(pc.binary_length(column), 0).to_pylist(), most):
        yield a, b, column.slice(a, b - a)


def text_slices(batch: pa.RecordBatch, name: str, most: int) -> Iterator[tuple[int, int, list[bytes]]]:
    """A string column as UTF-8 bytes, some ``most`` bytes at a time, so that only those are held as objects."""
    for a, b, column in column_slices(batch, name, most):
        yield a, b, [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


_HELD: dict[str, tuple[dict, ...]] = {}


def release() -> None:
    """Gives what is free back to the system, where the C library can do that: an idle worker then holds little of what its largest group took."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim:
        trim(0)


def released(use):
    """``use``, a function of a group, with ``release`` behind it."""

    def run(group: pa.Table) -> pa.Table:
        try:
            return use(group)
        finally:
            release()

    return run


def claim(owner: str, *caches: dict) -> None:
    """Names a worker's caches and empties those of other operators: a worker, which outlives its tasks, holds one operator's at a time."""
    for other, held in _HELD.items():
        if other != owner:
            for c in held:
                c.clear()
    _HELD[owner] = caches
    gc.collect()
    release()
