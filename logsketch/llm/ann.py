"""Nearest neighbours by randomly rotated one-bit codes.

Vectors are centred and rotated by one random rotation; the signs are a code of one bit for each dimension, beside two
scalars: the length, and how far the code points along the vector. From a packed code, its scalars and the rotated
query comes an estimate of the inner product, and with it a range that holds the true distance but for a chosen
chance. Vectors whose range reaches below the best known upper ends are measured exactly, in double precision.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import likely, table

K, BOUND = 10, 4.5  # neighbours; deviations of the estimate that the range spans
BLOCK = 8192  # candidates in a block
QUERIES = 2048  # queries that meet a block at once: their bytes, not the table's, bound what is broadcast
SAMPLE = 100_000  # vectors that the centre is taken from


def rotation(d: int, seed: int = 5) -> np.ndarray:
    q, r = np.linalg.qr(np.random.default_rng(seed).normal(size=(d, d)))
    return q * np.sign(np.diag(r))


class Codes:
    """One-bit codes of a block of vectors (double precision, rows)."""

    def __init__(self, x: np.ndarray, centre: np.ndarray, turn: np.ndarray):
        y = (x - centre) @ turn
        self.d = y.shape[1]
        self.length = np.sqrt((y**2).sum(axis=1))
        bits = y > 0
        self.packed = np.packbits(bits, axis=1)
        unit = np.where(self.length[:, None] > 0, y / np.maximum(self.length, 1e-300)[:, None], 0)
        self.along = np.abs(unit).sum(axis=1) / np.sqrt(self.d)  # inner product of the code's and the vector's directions
        self.along[self.length == 0] = 1.0

    def ranges(self, q: np.ndarray, centre: np.ndarray, turn: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Lower and upper ends of the squared distances to one query."""
        z = (q - centre) @ turn
        size = float(np.sqrt((z**2).sum()))
        signed = z.astype(np.float64)
        # Sum of z over the set bits, byte by byte from a table of 256 sums each; the code's entries are +-1/sqrt(d).
        padded = np.zeros(self.packed.shape[1] * 8)
        padded[: self.d] = signed
        table_ = (np.unpackbits(np.arange(256, dtype=np.uint8)[:, None], axis=1).astype(np.float64) @ padded.reshape(-1, 8).T).T
        dot = np.zeros(len(self.packed))
        for k in range(self.packed.shape[1]):
            dot += table_[k][self.packed[:, k]]
        dot = (2 * dot - signed.sum()) / np.sqrt(self.d)
        unit = dot / self.along  # estimate of <vector's direction, z>
        slack = BOUND * size * np.sqrt(np.maximum(1 - self.along**2, 0)) / (self.along * np.sqrt(max(self.d - 1, 1)))
        base = self.length**2 + size**2
        return base - 2 * self.length * (unit + slack), base - 2 * self.length * (unit - slack)


def _vectors(batches):
    """Rows with sound vectors, as doubles: no null, no null or non-finite component, not zero."""
    for batch in batches:
        v = batch.column("v")
        keep, out = [], []
        for k in range(batch.num_rows):
            x = v[k].values if v[k].is_valid else None
            if x is not None and len(x) and not x.null_count:
                y = x.to_numpy(zero_copy_only=False).astype(np.float64)
                if np.isfinite(y).all() and y.any():
                    keep.append(k)
                    out.append(y.tobytes())
        yield pa.RecordBatch.from_arrays([batch.column("vec_id").take(pa.array(keep, pa.int64())), pa.array(out, pa.binary())], names=["vec_id", "v"])


def _blocks(batches):
    """Candidates of a partition in blocks of one row each."""
    ids: list[np.ndarray] = []
    held: list[bytes] = []
    for batch in batches:
        ids += [batch.column("vec_id").to_numpy()]
        held += batch.column("v").to_pylist()
        while len(held) >= BLOCK:
            every = np.concatenate(ids)
            yield _block(every[:BLOCK], held[:BLOCK])
            ids, held = [every[BLOCK:]], held[BLOCK:]
    if held:
        yield _block(np.concatenate(ids), held)


def _block(ids: np.ndarray, rows: list[bytes]) -> pa.RecordBatch:
    sizes = {len(r) for r in rows}
    out = [(n, [k for k, r in enumerate(rows) if len(r) == n]) for n in sorted(sizes)]
    return pa.RecordBatch.from_arrays(
        [pa.array([n // 8 for n, _ in out], pa.int32()), pa.array([ids[k].astype(np.int64).tobytes() for _, k in out], pa.binary()), pa.array([b"".join(rows[j] for j in k) for _, k in out], pa.binary())], names=["d", "ids", "rows"]
    )


def nearest(codes: Codes, ids: np.ndarray, x: np.ndarray, q_id: int, q: np.ndarray, centre: np.ndarray, turn: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """A query's k nearest in a block: ids and distances, after reranking what the ranges leave."""
    low, high = codes.ranges(q, centre, turn)
    own = ids == q_id
    high = np.where(own, np.inf, high)
    limit = np.partition(high, k - 1)[k - 1] if len(high) > k else np.inf
    at = np.flatnonzero((low <= limit * (1 + 1e-9) + 1e-9) & ~own)
    exact = np.sqrt(((x[at] - q) ** 2).sum(axis=1))
    best = np.lexsort((ids[at], exact))[:k]
    return ids[at[best]], exact[best]


def _search(shared, k: int):
    def run(batches):
        by_d, centres = shared.value
        for batch in batches:
            for d, ids, rows in zip(batch.column("d").to_pylist(), batch.column("ids"), batch.column("rows"), strict=True):
                if d not in by_d:
                    continue
                ids, x = np.frombuffer(ids.as_buffer(), np.int64), np.frombuffer(rows.as_buffer(), np.float64).reshape(-1, d)
                turn, (q_ids, queries) = rotation(d), by_d[d]
                codes = Codes(x, centres[d], turn)
                out = []
                for q_id, q in zip(q_ids, queries, strict=True):
                    got, far = nearest(codes, ids, x, q_id, q, centres[d], turn, k)
                    out.append((np.full(len(got), q_id), got, far))
                q, got, far = (np.concatenate(c) for c in zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(q), pa.array(got), pa.array(far)], names=["query_id", "vec_id", "score"])

    return run


def neighbours(vectors: DataFrame, queries, k: int = K) -> DataFrame:
    """vectors (vec_id, embedding) and a condition that picks the queries -> query_id, rank, vec_id, score.

    Every sound row but the query's own id is a candidate; score is the Euclidean distance in double precision,
    ties go to the smaller vec_id. Null vec_ids and vectors that are null, empty, zero, or hold null or non-finite
    components take no part; vectors of another length than the query's are no candidates. Repeated rows are
    candidates each time. Queries meet all blocks in turns of QUERIES, so that neither side is ever gathered whole.
    """
    spark = vectors.sparkSession
    rows = vectors.where("vec_id is not null").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v"))
    sound = table(rows.mapInArrow(_vectors, "vec_id long, v binary"), "vectors")
    blocks = table(sound.mapInArrow(_blocks, "d int, ids binary, rows binary"), "blocks")
    sample = likely(sound, SAMPLE, "vec_id").orderBy(F.pmod(F.xxhash64("vec_id"), F.lit(1 << 30)), "vec_id").limit(SAMPLE).select("v").toPandas()["v"]
    centres = {d: np.mean([np.frombuffer(v, np.float64) for v in sample if len(v) == 8 * d], axis=0) for d in {len(v) // 8 for v in sample}}
    asked = sound.where(queries)
    turns = max(1, -(-asked.count() // QUERIES))
    found = None
    for t in range(turns):
        some = asked.where(F.pmod(F.xxhash64("vec_id"), F.lit(turns)) == t).dropDuplicates(["vec_id", "v"]).orderBy("vec_id").toPandas()  # about QUERIES rows
        by_d = {}
        for d in {len(v) // 8 for v in some["v"]}:
            mine = some[some["v"].map(len) == 8 * d]
            by_d[d] = (mine["vec_id"].to_numpy(np.int64), np.stack([np.frombuffer(v, np.float64) for v in mine["v"]]))
            centres.setdefault(d, np.zeros(d))
        got = blocks.mapInArrow(_search(spark.sparkContext.broadcast((by_d, centres)), k), "query_id long, vec_id long, score double")
        found = got if found is None else found.unionByName(got)
    place = F.row_number().over(Window.partitionBy("query_id").orderBy("score", "vec_id"))
    return found.withColumn("rank", place).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
