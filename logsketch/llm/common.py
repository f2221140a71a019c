"""What the operators of this subpackage share: the library's tables in the shared folder and checked size bounds, and workers that give memory back."""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..tables import bounded_bytes, read, release, shared_folder, sweep, table

__all__ = ["bounded_bytes", "keep", "lean", "likely", "read", "release", "shared_folder", "small_batches", "sweep", "table"]


def trim() -> None:
    """Gives freed memory back to the system: workers are reused by later stages, which have other needs."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        return


#: What a worker keeps from task to task, by the module that needs it.
_kept: dict[str, dict] = {}


def keep(module: str, memory: dict) -> dict:
    """A worker's memory for the tasks of one module: it is emptied when the worker turns to another module's."""
    _kept[module] = memory
    return memory


def forget(module: str) -> None:
    """Empties what other modules' tasks have left in this worker."""
    for owner, memory in _kept.items():
        if owner != module and memory:
            memory.clear()
            trim()


@contextmanager
def small_batches(spark: SparkSession, size: int = 8 << 20) -> Iterator[None]:
    """Arrow batches to Python of about `size` bytes at most, for what is written inside: Spark holds a batch two or three times."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(size))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def likely(df: DataFrame, size: int, *key: str | Column) -> DataFrame:
    """About twice `size` rows, chosen by a hash of `key`, or all where there are fewer: the first `size` in the order of
    that hash are among them, so that what an ordered limit gathers does not grow with the number of tasks."""
    n = df.count()
    return df.where(F.pmod(F.xxhash64(*key), F.lit(1 << 30)) < int((1 << 30) * 2 * size / n)) if n > 2 * size else df


def lean(f: Callable) -> Callable:
    """A function for mapInArrow before whose first batch the worker drops what other modules keep, and after whose last
    it gives back what it no longer uses."""

    @functools.wraps(f)
    def run(batches):
        forget(f.__module__)
        yield from f(batches)
        trim()

    return run
