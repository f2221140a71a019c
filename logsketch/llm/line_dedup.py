"""Near-duplicate lines by an exact set-similarity join over all lines of all documents.

A line is the set of its words. Words are ordered by rarity (counts over all lines, in a table of fixed size; any one
order gives the same result, a rarer front only fewer candidates). Two lines at the threshold must share a word
among the first few of both (prefix filter), at places from which the overlap can still be reached (positional
filter), and have sizes near each other (length filter). Candidates that also pass a parity test on 128 bits are
compared word by word. A line goes when an earlier line (by doc_id, then number) is similar enough.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkernel as K
from .common import lean, release, small_batches, sweep, table
from .sketch import FAN_IN, add_keys, marks, parted, sliced, summed

NUMERATOR = 80  # per cent of the union
CELLS = 1 << 18
HEAVY = 1 << 16  # sets of words that are known to every task at most: those of the most lines
SIZES = 64  # numbers of lines up to which sets are counted by it, to find from which on they are so few
FIRST = 4  # candidates kept for a line and word; lines that have more and stay unresolved meet all of theirs in the end
STEPS = 4096  # earlier lines of its word that a line meets at first; if more are left, it meets them in the end too
PART = 4096  # lines of a word's list that meet another part in one task in the end
SEEN = 1 << 22
HELD = 1 << 15  # lines of a task whose sets are told apart before they are passed on, about
SETS = 100_000  # lines whose sets meet in one task, about
FEW = 64  # lines that go from a text without Python, at most: each of the text's lines is looked for among them


def _line_sets(column: pa.Array, rank: np.ndarray | None) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """Per block: (row, line number, where each line's words begin, words ordered by rarity, their 64-bit hashes); lines without words are left out."""
    for first, data, offsets in K.blocks(column, 1 << 17):
        starts, _, h, _ = K.words(data, offsets)
        if not len(h):
            continue
        breaks = np.flatnonzero(data == 0x0A)
        cuts = np.sort(np.concatenate([breaks + 1, offsets[:-1]]))  # every line's first byte; words belong to the last of equal ones
        size = np.diff(np.searchsorted(starts, cuts), append=len(h))
        used = np.flatnonzero(size)
        line = np.repeat(np.arange(len(used)), size[used])
        row = np.searchsorted(offsets, cuts[used], side="right") - 1
        number = np.searchsorted(breaks, cuts[used]) - np.searchsorted(breaks, offsets[row])
        q = None if rank is None else rank[(h & np.uint64(len(rank) - 1)).astype(np.int64)] << np.uint64(38)
        for k in range(0, len(used), 1 << 16):
            some = (line >= k) & (line < k + (1 << 16)) if len(used) > 1 << 16 else slice(None)
            key = ((line[some] - k).astype(np.uint64) << np.uint64(48)) | (h[some] >> np.uint64(26))
            if q is not None:
                key |= q[some]
            order = np.argsort(key)
            key = key[order]
            new = np.ones(len(key), bool)
            new[1:] = key[1:] != key[:-1]
            key, hs = key[new], h[some][order][new]
            at = np.searchsorted(key, np.arange(min(len(used) - k, 1 << 16) + 1, dtype=np.uint64) << np.uint64(48)) if min(len(used) - k, 1 << 16) < 1 << 16 else np.append(np.searchsorted(key, np.arange(1 << 16, dtype=np.uint64) << np.uint64(48)), len(key))
            yield row[k : k + (1 << 16)] + first, number[k : k + (1 << 16)], at, key & np.uint64((1 << 48) - 1), hs


def _digests(at: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    return np.add.reduceat(h, at[:-1]).view(np.int64), np.add.reduceat(K.mix(h ^ np.uint64(0x9FB21C651E98DF25)), at[:-1]).view(np.int64)


def _lines(batches):
    """Of many lines at a time, the sets of words they have, packed in columns, and the lines that repeat an earlier one of
    them; at the end of a task, how often its words' cells occurred, in slices."""
    counts = np.zeros(CELLS, np.uint32)
    held, size = [], 0  # words are counted many at a time, as each time passes over all counters
    lines, n = [], 0
    for batch in batches:
        ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
        for row, number, at, _, h in _line_sets(batch.column("text"), None):
            held.append(h)
            size += len(h)
            if size > CELLS:
                add_keys(counts, np.concatenate(held))
                held, size = [], 0
            lines.append((*_digests(at, h), ids[row].astype(np.int64), np.ones(len(row), np.int64), number.astype(np.int32)))
            n += len(row)
            if n >= HELD:
                yield from _told_apart(lines)
                lines, n = [], 0
    if lines:
        yield from _told_apart(lines)
    if held:
        add_keys(counts, np.concatenate(held))
    found = sliced(counts)
    yield _rows(len(found), slice=pa.array([k for k, _ in found], pa.int32()), part=pa.array([TaskContext.get().partitionId() // FAN_IN] * len(found), pa.int32()), counts=pa.array([x for _, x in found], pa.binary()))


_PASSED = {"doc_id": pa.int64(), "line": pa.int32(), "n": pa.int64(), "sets": pa.binary(), "slice": pa.int32(), "part": pa.int32(), "counts": pa.binary()}


def _rows(size: int, /, **columns: pa.Array) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([columns.get(k, pa.nulls(size, kind)) for k, kind in _PASSED.items()], names=list(_PASSED))


_SETS = (np.int64, np.int64, np.int64, np.int64, np.int32)  # two digests, the first line's document, how many lines, the first line's number


def _grouped(columns) -> tuple[tuple[np.ndarray, ...], np.ndarray, np.ndarray]:
    """Sets, in the order of their first digest, each with its first line and the number of its lines; document and number of all other lines."""
    one, two, doc, n, line = columns
    order = np.argsort(one)
    new = np.ones(len(one), bool)
    new[1:] = one[order[1:]] != one[order[:-1]]
    several = ~new  # only what shares its first digest has to be put in order
    several[:-1] |= ~new[1:]
    some = order[several]
    order[several] = some[np.lexsort((line[some], doc[some], two[some], one[some]))]
    one, two, doc, n, line = (x[order] for x in columns)
    new[1:] |= two[1:] != two[:-1]
    begin = np.flatnonzero(new)
    first = np.repeat(begin, np.diff(begin, append=len(one)))
    other = (doc != doc[first]) | (line != line[first])  # not so where rows repeat a doc_id
    return (one[begin], two[begin], doc[begin], np.add.reduceat(n, begin), line[begin]), doc[other], line[other]


def _told_apart(lines) -> Iterator[pa.RecordBatch]:
    sets, doc, line = _grouped([np.concatenate(x) for x in zip(*lines, strict=True)])
    yield _rows(len(doc), doc_id=pa.array(doc), line=pa.array(line))
    yield _rows(1, n=pa.array([int(sets[3].sum())]), sets=pa.array([b"".join(x.tobytes() for x in sets)], pa.binary()))


def _dealt(buckets: int):
    """Packed sets -> the same by bucket of their first digest."""

    def run(batches):
        for batch in batches:
            for blob in batch.column("sets"):
                columns = _unpacked(blob.as_buffer(), _SETS)
                bucket = (((columns[0].view(np.uint64) >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)).astype(np.int32)
                at = np.flatnonzero(np.diff(bucket, prepend=-1))  # sets are in order, so a bucket is one run, or two if it holds 0
                parts = [b"".join(c[a:b].tobytes() for c in columns) for a, b in zip(at, np.append(at[1:], len(bucket)), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(bucket[at]), pa.array(parts, pa.binary())], names=["bucket", "sets"])

    return run


def _repeats(rows: pd.DataFrame) -> pd.DataFrame:
    """In one bucket: the lines that repeat an earlier one (n is 0), and of each set that several lines have the first line and their number."""
    (one, two, first, n, number), doc, line = _grouped([np.concatenate(x) for x in zip(*(_unpacked(x, _SETS) for x in rows["sets"]), strict=True)])
    several = n > 1
    none = np.zeros(len(doc), np.int64)
    both = {"doc_id": (doc, first), "line": (line, number), "d1": (none, one), "d2": (none, two), "n": (none, n)}
    return pd.DataFrame({k: np.concatenate([x, y[several]]) for k, (x, y) in both.items()})


def _place(doc: np.ndarray, line: np.ndarray) -> np.ndarray:
    return K.mix(doc.astype(np.int64).view(np.uint64) * np.uint64(0xD6E8FEB86659FD93) + line.astype(np.uint64))


def _need(n: np.ndarray, m: np.ndarray, numerator: int) -> np.ndarray:
    """The least overlap of sets of n and m words at the threshold."""
    return -((-numerator * (n + m)) // (100 + numerator))


def _postings(rank, heavy, buckets: int, numerator: int):
    """One row for a bucket and block of lines: the words at the front of each line, packed in columns."""
    hot_digest, hot_other, hot_doc, hot_line = heavy.value

    def run(batches):
        pending, size = [], 0
        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            for row, number, at, key, h in _line_sets(batch.column("text"), rank.value):
                n = np.diff(at)
                one, two = _digests(at, h)
                doc = ids[row]
                keep = 100 * n // numerator > n  # smaller sets match equal ones only, which are found by digest
                if len(hot_digest):
                    near = np.minimum(np.searchsorted(hot_digest, one), len(hot_digest) - 1)
                    keep &= (hot_digest[near] != one) | (hot_other[near] != two) | ((hot_doc[near] == doc) & (hot_line[near] == number))
                # 128 bits: the first six pick a bit, the seventh picks the half.
                half = (h >> np.uint64(51)) & np.uint64(1)
                bit = np.uint64(1) << (h >> np.uint64(58))
                parity = [np.bitwise_xor.reduceat(bit * x, at[:-1]) for x in (half ^ np.uint64(1), half)]
                front = np.where(keep, n - -((-numerator * n) // 100) + 1, 0)
                of = np.repeat(np.arange(len(n)), front)
                place = np.arange(len(of)) - np.repeat(np.cumsum(front) - front, front)
                word = K.mix(key[at[of] + place])
                pending.append((word, doc[of], number[of].astype(np.int32), n[of].astype(np.int32), place.astype(np.int32), parity[0][of], parity[1][of], one[of]))
                size += len(of)
                if size > 400_000:
                    yield from _packed(pending, buckets)
                    pending, size = [], 0
        if size:
            yield from _packed(pending, buckets)

    return run


_KINDS = (np.uint32, np.int64, np.int32, np.int32, np.int32, np.uint64, np.uint64, np.uint32)


def _packed(pending, buckets: int):
    columns = [np.concatenate(x) for x in zip(*pending, strict=True)]
    bucket = (columns[0] % np.uint64(buckets)).astype(np.int32)
    order = np.argsort(bucket, kind="stable")
    columns, bucket = [c[order] for c in columns], bucket[order]
    columns[0] = columns[0] >> np.uint64(32)  # two words of a bucket that fall together only share their candidates
    columns[7] = columns[7].view(np.uint64) >> np.uint64(32)
    at = np.flatnonzero(np.diff(bucket, prepend=-1))
    ends = np.append(at[1:], len(bucket))
    blobs = [[c[a:b].astype(kind, copy=False).tobytes() for a, b in zip(at, ends, strict=True)] for c, kind in zip(columns, _KINDS, strict=True)]
    yield pa.RecordBatch.from_arrays([pa.array(bucket[at])] + [pa.array(b, pa.binary()) for b in blobs], names=["bucket", *(f"c{k}" for k in range(len(_KINDS)))])


def _ready(own: tuple[np.ndarray, ...], numerator: int) -> tuple[np.ndarray, ...]:
    """What the filters compare of each posting of a list: how much of the overlap is within reach and how much is due, in the same unit, and the rest."""
    kind = np.int32 if not len(own[3]) or own[3].max() < 1 << 22 else np.int64
    n = own[3].astype(kind)
    return (100 + numerator) * (n - own[4].astype(kind)), numerator * n, n, *own[5:]


def _similar(of: tuple[np.ndarray, ...], x: np.ndarray, to: tuple[np.ndarray, ...], y: np.ndarray, numerator: int) -> np.ndarray:
    """Where the pairs of postings (x of one list, y of another, both ready) are that pass the length, positional and parity filters."""
    # The least overlap is within reach from both places; sets whose sizes are too far apart fail this as well.
    at = np.flatnonzero(np.minimum(of[0][x], to[0][y]) >= of[1][x] + to[1][y])
    i, j = x[at], y[at]
    n, m = of[2][i], to[2][j]
    differ = np.bitwise_count(of[3][i] ^ to[3][j]) + np.bitwise_count(of[4][i] ^ to[4][j])  # 128 at most
    return at[(differ <= n + m - 2 * _need(n, m, numerator)) & (of[5][i] != to[5][j])]


def _candidates(numerator: int):
    """In one bucket, by kind of row: PAIR, the first candidates (later line, earlier line) of each line and word; OPEN, a
    line that may have more; LIST, a part of the list of a word in which such a line stands."""

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        bucket = int(rows["bucket"].iloc[0])
        begins = np.argsort([np.frombuffer(x, np.int64, 1)[0] for x in rows["c1"]], kind="stable")  # blobs that are in order follow each other
        own = tuple(np.concatenate([np.frombuffer(rows[f"c{k}"].iloc[b], kind) for b in begins]) for k, kind in enumerate(_KINDS))
        order = np.sort((own[0].astype(np.uint64) << np.uint64(32)) | np.arange(len(own[0]), dtype=np.uint64)) & np.uint64((1 << 32) - 1)
        own = tuple(x[order.astype(np.int64)] for x in own)
        word, doc, line = own[:3]
        if ((word[1:] == word[:-1]) & ((doc[1:] < doc[:-1]) | ((doc[1:] == doc[:-1]) & (line[1:] < line[:-1])))).any():
            order = np.lexsort((line, doc, word))
            own = tuple(x[order] for x in own)
            word, doc, line = own[:3]
        ready = _ready(own, numerator)
        begin = np.flatnonzero(np.diff(word.astype(np.int64), prepend=-1))
        sizes = np.diff(np.append(begin, len(word)))
        start = np.repeat(begin, sizes)
        got = np.zeros(len(word), np.int32)
        out = []
        # Step k compares each line with the k-th line of its word's list, from the earliest on.
        x, step = np.flatnonzero(np.arange(len(word)) > start), 0
        start = start[x]
        more = np.zeros(len(word), bool)
        while len(x):
            y = start + step
            at = _similar(ready, x, ready, y, numerator)
            out.append((x[at], y[at]))
            got[x[at]] += 1
            step += 1
            left = start + step < x
            done = at[(got[x[at]] >= FIRST) & left[at]] if step < STEPS else np.flatnonzero(left)
            more[x[done]] = True
            left[done] = False
            x, start = x[left], start[left]
        x, y = (np.concatenate(k) for k in zip(*out, strict=True)) if out else np.zeros((2, 0), np.int64)
        pairs = np.stack([doc[x], line[x].astype(np.int64), doc[y], line[y].astype(np.int64)])
        open_ = np.flatnonzero(more)
        lists = []
        for k in np.unique(np.searchsorted(begin, open_, side="right") - 1).tolist():
            for p, a in enumerate(range(begin[k], begin[k] + sizes[k], PART)):
                b = min(a + PART, begin[k] + sizes[k])
                lists.append(((bucket << 32) + int(word[a]), p, b"".join(c[a:b].tobytes() for c in own)))
        n, m, q = pairs.shape[1], len(open_), len(lists)
        return pd.DataFrame(
            {
                "kind": np.repeat(np.array([PAIR, OPEN, LIST], np.int32), [n, m, q]),
                "xd": np.concatenate([pairs[0], doc[open_], np.array([w for w, _, _ in lists], np.int64)]),
                "xl": np.concatenate([pairs[1], line[open_], np.array([p for _, p, _ in lists], np.int64)]).astype(np.int32),
                "yd": np.concatenate([pairs[2], np.zeros(m + q, np.int64)]),
                "yl": np.concatenate([pairs[3], np.zeros(m + q, np.int64)]).astype(np.int32),
                "list": [None] * (n + m) + [x for _, _, x in lists],
            }
        )

    return run


PAIR, OPEN, LIST = 0, 1, 2


def _unpacked(blob: bytes, kinds=_KINDS) -> tuple[np.ndarray, ...]:
    n, at, out = len(memoryview(blob)) // sum(np.dtype(k).itemsize for k in kinds), 0, []
    for kind in kinds:
        out.append(np.frombuffer(blob, kind, n, at))
        at += n * np.dtype(kind).itemsize
    return tuple(out)


def _remaining(numerator: int, open_):
    """Two parts of one word's list -> all candidates of the lines that are still open, the later line first."""

    def run(batches):
        for batch in batches:
            for p, q, one, two in zip(batch.column("p").to_pylist(), batch.column("q").to_pylist(), batch.column("one"), batch.column("two"), strict=True):
                of, to = _unpacked(one.as_py()), _unpacked(two.as_py())
                ready, against = _ready(of, numerator), _ready(to, numerator)
                out = [np.zeros((4, 0), np.int64)]
                for x in np.flatnonzero(open_.value[(_place(of[1], of[2]) & np.uint64(SEEN - 1)).astype(np.int64)]).tolist():
                    y = np.arange(x if p == q else len(to[0]))
                    y = y[_similar(ready, np.full(len(y), x), against, y, numerator)]
                    out.append(np.stack([np.full(len(y), of[1][x]), np.full(len(y), of[2][x], np.int64), to[1][y], to[2][y].astype(np.int64)]))
                found = np.concatenate(out, axis=1)
                yield pa.RecordBatch.from_arrays([pa.array(found[0]), pa.array(found[1].astype(np.int32)), pa.array(found[2]), pa.array(found[3].astype(np.int32))], names=["xd", "xl", "yd", "yl"])

    return run


def _words_of(seen_docs, seen_lines):
    """The word sets of the lines that a candidate pair names (others may slip in and are joined away)."""

    def run(batches):
        docs, lines = seen_docs.value, seen_lines.value
        for batch in batches:
            ids = batch.column("doc_id").to_numpy(zero_copy_only=False)
            some = np.flatnonzero(docs[(K.mix(ids.astype(np.int64).view(np.uint64)) & np.uint64(SEEN - 1)).astype(np.int64)])
            if not len(some):
                continue
            batch = batch.take(pa.array(some))
            ids = ids[some]
            for row, number, at, _, h in _line_sets(batch.column("text"), None):
                keep = np.flatnonzero(lines[(_place(ids[row], number) & np.uint64(SEEN - 1)).astype(np.int64)])
                yield pa.RecordBatch.from_arrays([pa.array(ids[row][keep]), pa.array(number[keep].astype(np.int32)), _forty_bits(at, h, keep)], names=["doc_id", "line", "words"])

    return run


def _forty_bits(at: np.ndarray, h: np.ndarray, keep: np.ndarray) -> pa.Array:
    """Forty bits of each word of the lines in keep (65,536 at most), sorted, in a cell for each line."""
    n = np.diff(at)[keep]
    of = np.repeat(np.arange(len(keep)), n)
    key = (of.astype(np.uint64) << np.uint64(40)) | (h[np.arange(len(of)) + (at[keep] - np.cumsum(n) + n)[of]] >> np.uint64(24))
    key.sort()
    new = np.ones(len(key), bool)
    new[1:] = key[1:] != key[:-1]
    key = key[new]
    ends = 5 * np.searchsorted(key, np.arange(len(keep) + 1, dtype=np.uint64) << np.uint64(40))
    packed = key.view(np.uint8).reshape(-1, 8)[:, :5].tobytes()
    return pa.Array.from_buffers(pa.large_binary(), len(keep), [None, pa.py_buffer(ends.astype(np.int64).tobytes()), pa.py_buffer(packed)]).cast(pa.binary())


def _words(cells: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Where the words of each cell begin, and forty bits of each word."""
    cells = cells.cast(pa.large_binary())
    _, ends, data = cells.buffers()
    at = np.frombuffer(ends, np.int64)[cells.offset : cells.offset + len(cells) + 1]
    packed = np.frombuffer(data, np.uint8)[at[0] : at[-1]].reshape(-1, 5)
    out = np.zeros((len(packed), 8), np.uint8)
    out[:, :5] = packed
    return (at - at[0]) // 5, out.view(np.uint64).ravel()


AT_ONCE = 1 << 20  # words of pairs that are compared in one go, about


def _verify(numerator: int):
    def run(batches):
        for batch in batches:
            (ax, x), (ay, y) = _words(batch.column("xw")), _words(batch.column("yw"))
            n, m = np.diff(ax), np.diff(ay)
            upto, both = np.cumsum(n + m), np.zeros(batch.num_rows, np.int64)
            a = 0
            while a < batch.num_rows:
                b = max(a + 1, int(np.searchsorted(upto, (upto[a - 1] if a else 0) + AT_ONCE, side="right")))
                b = min(b, a + (1 << 24))
                of = np.arange(b - a, dtype=np.uint64) << np.uint64(40)
                key = np.concatenate([np.repeat(of, n[a:b]) | x[ax[a] : ax[b]], np.repeat(of, m[a:b]) | y[ay[a] : ay[b]]])
                key.sort()
                both[a:b] = np.bincount((key[1:][key[1:] == key[:-1]] >> np.uint64(40)).astype(np.int64), minlength=b - a)
                a = b
            yield pa.RecordBatch.from_arrays([batch.column("xd"), batch.column("xl")], names=["doc_id", "line"]).filter(pa.array(100 * both >= numerator * (n + m - both)))

    return run


def _doc_keys(batch: pa.RecordBatch) -> Iterator[np.ndarray]:
    for c in ("xd", "yd"):
        yield K.mix(batch.column(c).to_numpy().view(np.uint64))


def _line_keys(batch: pa.RecordBatch) -> Iterator[np.ndarray]:
    for c in "xy":
        yield _place(batch.column(f"{c}d").to_numpy(), batch.column(f"{c}l").to_numpy())


def _open_keys(batch: pa.RecordBatch) -> Iterator[np.ndarray]:
    yield _place(batch.column("xd").to_numpy(), batch.column("xl").to_numpy())


def _heavy(groups: DataFrame, total: int) -> tuple[np.ndarray, ...]:
    """Digests, document and line of the first of each set of words that many lines have, by digest; at most HEAVY of them."""
    by = dict(groups.groupBy(F.least("n", F.lit(SIZES)).alias("n")).count().collect())  # SIZES rows at most
    above, least = 0, SIZES
    while least > 1 and above + by.get(least, 0) <= HEAVY:
        above, least = above + by.get(least, 0), least - 1
    if least == SIZES:
        least = max(SIZES, total // HEAVY)  # fewer than HEAVY sets have more lines
    hot = groups.where(F.col("n") > least).select("d1", "d2", "doc_id", "line").toPandas().sort_values(["d1", "d2"])
    return tuple(hot[c].to_numpy(np.int64) for c in hot)


def repeated_lines(docs: DataFrame, numerator: int = NUMERATOR) -> DataFrame:
    """docs (doc_id, text) -> (doc_id, line): the lines, counted from 0, that repeat an earlier one.

    Earlier: smaller doc_id, then smaller number. Similar: 100 * shared words >= numerator * all words of both, words
    being runs outside space and \\t-\\r with A-Z folded, each counted once. Lines without words never count. Rows
    with a null doc_id take no part; rows that repeat a doc_id number their lines alike and count as one document.
    """
    spark: SparkSession = docs.sparkSession
    docs = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    with small_batches(spark):
        passed = table(docs.mapInArrow(lean(_lines), "doc_id long, line int, n long, sets binary, slice int, part int, counts binary"), "lines")
    counts = summed(passed.where("slice is not null"), CELLS)
    rank = spark.sparkContext.broadcast(np.minimum((np.log2(counts.astype(np.float64) + 1) * 30).astype(np.uint64), np.uint64(1023)))
    total = passed.agg(F.sum("n")).first()[0] or 0
    dealt = passed.where("sets is not null").select("sets").mapInArrow(lean(_dealt(max(16, total // SETS))), "bucket int, sets binary")
    with small_batches(spark):
        sets = table(dealt.groupBy("bucket").applyInPandas(_repeats, "doc_id long, line int, d1 long, d2 long, n long"), "sets")
    equal = table(passed.where("doc_id is not null").select("doc_id", "line").unionByName(sets.where("n = 0").select("doc_id", "line")), "repeats")
    heavy = spark.sparkContext.broadcast(_heavy(sets.where("n > 0"), total))
    release(passed, sets)

    buckets = max(16, int(total / 40_000))
    packed = docs.mapInArrow(lean(_postings(rank, heavy, buckets, numerator)), "bucket int, " + ", ".join(f"c{k} binary" for k in range(len(_KINDS))))
    with small_batches(spark):
        found = table(packed.groupBy("bucket").applyInPandas(_candidates(numerator), "kind int, xd long, xl int, yd long, yl int, list binary"), "candidates")
    sweep(spark)
    for b in (rank, heavy):
        b.destroy()
    line_of, pair = ["xd", "xl"], ["xd", "xl", "yd", "yl"]

    def confirmed(pairs: DataFrame) -> DataFrame:
        seen_docs, seen_lines = (spark.sparkContext.broadcast(marks(pairs.select(*columns), SEEN, keys)) for columns, keys in ((("xd", "yd"), _doc_keys), (pair, _line_keys)))
        with small_batches(spark):
            words = table(docs.mapInArrow(lean(_words_of(seen_docs, seen_lines)), "doc_id long, line int, words binary"), "words")
        for b in (seen_docs, seen_lines):
            b.destroy()
        once = words.dropDuplicates(["doc_id", "line"])
        both = pairs.select(*pair).join(once.select(F.col("doc_id").alias("xd"), F.col("line").alias("xl"), F.col("words").alias("xw")), line_of)
        both = both.join(once.select(F.col("doc_id").alias("yd"), F.col("line").alias("yl"), F.col("words").alias("yw")), ["yd", "yl"])
        out = table(both.select("xd", "xl", "xw", "yw").mapInArrow(lean(_verify(numerator)), "doc_id long, line int").distinct(), "similar")
        release(words)
        sweep(spark)
        return out

    settled = equal.select(F.col("doc_id").alias("xd"), F.col("line").alias("xl"))
    pairs = table(found.where(F.col("kind") == PAIR).select(*pair).distinct().join(settled, line_of, "left_anti"), "pairs")
    similar = confirmed(pairs)
    unresolved = found.where(F.col("kind") == OPEN).select("xd", "xl").distinct().join(settled, line_of, "left_anti").join(similar.select(F.col("doc_id").alias("xd"), F.col("line").alias("xl")), line_of, "left_anti")
    unresolved = table(unresolved, "open")
    if unresolved.limit(1).count():
        open_ = spark.sparkContext.broadcast(marks(unresolved, SEEN, _open_keys))
        lists = found.where(F.col("kind") == LIST)
        one = lists.select(F.col("xd").alias("word"), F.col("xl").alias("p"), F.col("list").alias("one"))
        two = lists.select(F.col("xd").alias("word"), F.col("xl").alias("q"), F.col("list").alias("two"))
        rest = one.join(two, "word").where("q <= p").select("p", "q", "one", "two").mapInArrow(lean(_remaining(numerator, open_)), "xd long, xl int, yd long, yl int")
        rest = table(rest.distinct().join(unresolved, line_of, "left_semi").join(pairs, pair, "left_anti"), "rest")
        similar = similar.unionByName(confirmed(rest))
    return table(similar.unionByName(equal).distinct(), "removed")


@F.pandas_udf(T.StringType())
def _without(text: pd.Series, gone: pd.Series) -> pd.Series:
    out = []
    for t, g in zip(text, gone, strict=True):
        if t is not None and g is not None:
            drop = set(g.tolist())
            t = "\n".join(x for k, x in enumerate(t.split("\n")) if k not in drop)
        out.append(t)
    return pd.Series(out, dtype=object)


def without_lines(docs: DataFrame, removed: DataFrame) -> DataFrame:
    """docs with `removed` lines cut from text; adds n_lines, n_removed, in place of columns of these names. Lines stay apart by \\n; null text stays null."""
    columns = [c for c in docs.columns if c not in ("n_lines", "n_removed")]
    own = docs.select(F.struct(*(F.col(f"`{c}`") for c in columns)).alias("_row"), F.col("doc_id").alias("_id"))
    # Most rows need not meet the lines that go: only those that may lose one are shuffled.
    whole, some = parted(own, F.xxhash64(F.col("_id").cast("long")), removed.select(F.xxhash64(F.col("doc_id").cast("long"))))
    per_doc = removed.groupBy(F.col("doc_id").alias("_doc")).agg(F.collect_set("line").alias("_gone"))
    out = some.join(per_doc, F.col("_id") == F.col("_doc"), "left")
    # Only texts that lose many lines go to Python, once: a filter on the result would else run it a second time, in workers of its own.
    many = F.size("_gone") > FEW
    cut = _without.asNondeterministic()(F.when(many, F.col("_row.text")), F.when(many, F.col("_gone")))
    few = F.array_join(F.filter(F.split("_row.text", "\n", -1), lambda _, k: ~F.array_contains("_gone", k)), "\n")
    out = out.select("_row", "_gone", F.when(F.col("_gone").isNull() | many, cut).otherwise(few).alias("_cut"))
    out = out.unionByName(whole.select("_row", F.lit(None).cast(out.schema["_gone"].dataType).alias("_gone"), F.lit(None).cast("string").alias("_cut")))
    text = F.col("_row.text")
    n_lines = F.when(text.isNull(), 0).otherwise(F.octet_length(text) - F.octet_length(F.replace(text, F.lit("\n"), F.lit(""))) + 1)
    kept = [(F.when(F.col("_gone").isNull(), text).otherwise(F.col("_cut")) if c == "text" else F.col(f"_row.`{c}`")).alias(c) for c in columns]
    return out.select(*kept, n_lines.cast("int").alias("n_lines"), F.when(F.col("_gone").isNull(), 0).otherwise(F.size("_gone")).alias("n_removed"))
