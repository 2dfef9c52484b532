"""Shared plumbing of the text operators: batches of bounded size, word bytes, checkpoints."""

from __future__ import annotations

import ctypes
import gc
import tempfile
from collections.abc import Iterator
from functools import cache
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

#: Text bytes that one step of a vectorised kernel holds at a time.
CHUNK_BYTES = 2 << 20
#: Entries of a per-worker word cache before it is emptied.
CACHE_WORDS = 150_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder the session names; make one only for a session (a test) that names none."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoints-"))


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared checkpoint folder and forget the lineage."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def cut_free(df: DataFrame) -> DataFrame:
    """``cut``, after which the shuffle files behind the table go: the engine keeps them until the driver happens to collect its garbage."""
    out = cut(df)
    del df
    gc.collect()
    out.sparkSession.sparkContext._jvm.System.gc()
    return out


def spread(df: DataFrame) -> DataFrame:
    """Short rows over as many partitions as a shuffle has, before they multiply."""
    return df.repartition(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), *df.columns[:1])


def fresh(name: str, columns: list[str]) -> str:
    """A column name that clashes with none of ``columns``."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name += "_"
    return name


def slices(batches: Iterator[pa.RecordBatch], column: str, limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that a slice holds about ``limit`` bytes of ``column``; a longer single text is one slice."""
    for batch in batches:
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
        start, held = 0, 0
        for row, size in enumerate(sizes):
            if held and held + size > limit:
                yield batch.slice(start, row - start)
                start, held = row, 0
            held += size + 64
        if batch.num_rows > start:
            yield batch.slice(start)


@cache
def one_blas_thread() -> bool:
    """Keep a worker's matrix products on its own core: idle helper threads of the numeric library spin and double the CPU time.

    Whether the library that numpy ships was found; results don't depend on it.
    """
    for path in (Path(np.__file__).parent.parent / "numpy.libs").glob("*openblas*"):
        library = ctypes.CDLL(str(path))
        for name in ("scipy_openblas_set_num_threads64_", "openblas_set_num_threads64_", "openblas_set_num_threads"):
            if hasattr(library, name):
                getattr(library, name)(1)
                return True
    return False


def utf8(batch: pa.RecordBatch, column: str) -> list[bytes]:
    """The column's UTF-8 bytes; a null is an empty text."""
    return [x or b"" for x in batch.column(column).cast(pa.binary()).to_pylist()]


def strings(batch: pa.RecordBatch, column: str) -> list[str]:
    """The column as str; a null is an empty text, a broken byte becomes the replacement character."""
    return [x.decode("utf-8", "replace") for x in utf8(batch, column)]


class WordCache(dict):
    """Word to value for one Python worker; emptied when full, so its memory is bounded."""

    def __init__(self, limit: int = CACHE_WORDS):
        super().__init__()
        self.limit = limit

    def missing(self, words: set) -> list:
        if len(self) > self.limit:
            self.clear()
        return [w for w in words if w not in self]  # set.difference would walk the whole cache
