"""Tables of fixed size that every task fills: counters, and marks of one bit. What is broadcast does not grow with the data."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import lean, table

SLICE = 1 << 14
FAN_IN = 256  # tasks whose counters are added up in one step
APART = 1 << 24  # cells of parted()


def sliced(counts: np.ndarray) -> list[tuple[int, bytes]]:
    """The slices of a table of counters that are not all zero, with their numbers."""
    parts = counts.reshape(-1, min(SLICE, len(counts)))
    return [(int(k), parts[k].tobytes()) for k in np.flatnonzero(parts.any(axis=1))]


def add_keys(counts: np.ndarray, h: np.ndarray) -> None:
    counts += np.bincount((h & np.uint64(len(counts) - 1)).astype(np.int64), minlength=len(counts)).astype(np.uint32)


def _fill(cells: int, keys: Callable[[pa.RecordBatch], Iterator[np.ndarray]]):
    def run(batches):
        counts = np.zeros(cells, np.uint32)
        for batch in batches:
            for h in keys(batch):
                add_keys(counts, h)
        found = sliced(counts)
        group = TaskContext.get().partitionId() // FAN_IN
        yield pa.RecordBatch.from_arrays(
            [pa.array([k for k, _ in found], pa.int32()), pa.array(np.full(len(found), group, np.int32)), pa.array([x for _, x in found], pa.binary())], names=["slice", "part", "counts"]
        )

    return run


def _add(rows: pd.DataFrame) -> pd.DataFrame:
    total = np.zeros(len(rows["counts"].iloc[0]) // 4, np.uint64)
    for x in rows["counts"]:
        total += np.frombuffer(x, np.uint32)
    return pd.DataFrame({"slice": [rows["slice"].iloc[0]], "part": [np.int32(0)], "counts": [np.minimum(total, (1 << 32) - 1).astype(np.uint32).tobytes()]})


def summed(slices: DataFrame, cells: int) -> np.ndarray:
    """Rows (slice, part, counts) of many tasks -> the counters."""
    schema = "slice int, part int, counts binary"
    once = slices.select("slice", "part", "counts").groupBy("slice", "part").applyInPandas(_add, schema)
    rows = once.groupBy("slice").applyInPandas(_add, schema).collect()  # cells * 4 bytes, whatever the input
    out = np.zeros(cells, np.uint32).reshape(-1, min(SLICE, cells))
    for r in rows:
        out[r["slice"]] = np.frombuffer(r["counts"], np.uint32)
    return out.ravel()


def count_sketch(df: DataFrame, cells: int, keys: Callable[[pa.RecordBatch], Iterator[np.ndarray]]) -> np.ndarray:
    """Counts of 64-bit keys by their low bits: never less than a key's own count. cells is a power of two."""
    return summed(df.mapInArrow(lean(_fill(cells, keys)), "slice int, part int, counts binary"), cells)


def _mark(cells: int, keys: Callable[[pa.RecordBatch], Iterator[np.ndarray]]):
    def run(batches):
        seen = np.zeros(cells, bool)
        for batch in batches:
            for h in keys(batch):
                seen[(h & np.uint64(cells - 1)).astype(np.int64)] = True
        words = np.packbits(seen).view(np.int64)
        at = np.flatnonzero(words)
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(words[at])], names=["place", "bits"])

    return run


def marks(df: DataFrame, cells: int, keys: Callable[[pa.RecordBatch], Iterator[np.ndarray]]) -> np.ndarray:
    """Which cells some 64-bit key falls in, by its low bits. cells is a power of two, 64 at least."""
    found = df.mapInArrow(lean(_mark(cells, keys)), "place int, bits long").groupBy("place").agg(F.bit_or("bits").alias("bits")).toPandas()  # cells / 64 rows at most
    words = np.zeros(cells // 64, np.int64)
    words[found["place"].to_numpy(np.int64)] = found["bits"].to_numpy(np.int64)
    return np.unpackbits(words.view(np.uint8)).astype(bool)


def parted(rows: DataFrame, key: Column, keys: DataFrame, cells: int = APART) -> tuple[DataFrame, DataFrame]:
    """rows in two: those whose key is surely none of keys, and all others, which an exact step has to follow.

    key: a 64-bit hash over rows; keys: one column of such hashes. Every task gets cells / 64 rows at most, however many
    keys there are, so that large rows are not shuffled for the few of them that keys are about. A power of two."""
    own = [F.col(f"`{c}`") for c in rows.columns]
    bit = lambda at: F.call_function("shiftleft", F.lit(1).cast("long"), at.bitwiseAND(F.lit(63)).cast("int"))
    at = keys.select(F.col(keys.columns[0]).bitwiseAND(F.lit(cells - 1)).alias("at"))
    marked = table(at.groupBy(F.shiftright("at", 6).cast("int").alias("_place")).agg(F.bit_or(bit(F.col("at"))).alias("_bits")), "marks")
    both = rows.withColumn("_at", key.bitwiseAND(F.lit(cells - 1)))
    both = both.join(F.broadcast(marked), F.shiftright("_at", 6).cast("int") == F.col("_place"), "left")
    hit = F.coalesce(F.col("_bits").bitwiseAND(bit(F.col("_at"))) != 0, F.lit(False))
    return both.where(~hit).select(*own), both.where(hit).select(*own)
