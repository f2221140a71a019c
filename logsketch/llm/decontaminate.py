"""Benchmark passages in documents, re-parameterised ones included.

Texts become templates: numbers, names and units give way to typed placeholders. Windows of a few template words of
every benchmark item are looked up for every document by hash. Windows that line up are joined to a stretch, and
of the stretch counts the longest part in which what fills the placeholders is consistent: one value of the item always
stands for one value of the document, and two for two.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import bounded_bytes, lean, small_batches, table

WINDOW = 8
LITERALS = 4  # words of a window that are no placeholders
ENOUGH = 13  # template words of an item that a document must share in one stretch, or the whole item if it is shorter
BROADCAST_BYTES = 64 << 20  # of benchmark text; beyond, windows meet by a shuffled join

# Units that turn into a placeholder after a number.
UNITS = (
    "mm cm m km inch inches foot feet ft yard yards mile miles mg g kg gram grams kilogram kilograms ton tons tonne tonnes lb lbs pound pounds ounce ounces oz "
    "ml cl l litre litres liter liters gallon gallons ms s sec second seconds min minute minutes h hr hour hours day days week weeks month months year years "
    "percent dollar dollars usd euro euros eur cent cents kmh mph kb mb gb tb hz khz mhz ghz w kw kwh v a j kj degrees degree c f k"
).split()

_WORD = np.ones(256, bool)
_WORD[: 0x30] = False
_WORD[0x3A:0x41] = _WORD[0x5B:0x5F] = _WORD[0x60] = _WORD[0x7B:0x80] = False
_DIGIT = np.zeros(256, bool)
_DIGIT[0x30:0x3A] = True
_UPPER = np.zeros(256, bool)
_UPPER[0x41:0x5B] = True
_POINT = np.zeros(256, bool)
_POINT[[0x2E, 0x2C]] = True
_STOP = np.zeros(256, bool)
_STOP[[0x2E, 0x21, 0x3F, 0x3A, 0x0A]] = True
NUMBER, NAME, UNIT = (np.uint64(k) for k in (1, 2, 3))


def _hash_words(words) -> np.ndarray:
    text = pa.array([" ".join(words)])
    (_, data, offsets), *_ = K.blocks(text)
    return np.sort(K.words(data, offsets)[2])


_UNITS = _hash_words(UNITS)


@dataclass
class Template:
    """Words of one text: what stands in the template (a hash, or a placeholder's number) and the hash of what was there."""

    shape: np.ndarray
    value: np.ndarray


def templates(column: pa.Array) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """Per block: first row, where each row's words begin, shapes, values. Null and wordless rows have none.

    A word is a run of letters or of digits (with points or commas inside); letters are folded A-Z, other bytes from
    0x80 on count as letters. A capitalised word is a name unless a sentence begins there; neighbouring names are one.
    """
    for first, data, offsets in K.blocks(column):
        n = len(data)
        inside, digit = _WORD[data], _DIGIT[data]
        if n > 2:
            joint = np.flatnonzero(_POINT[data[1:-1]] & digit[:-2] & digit[2:]) + 1
            edge = np.zeros(n + 1, bool)
            edge[offsets] = True
            joint = joint[~edge[joint] & ~edge[joint + 1]]
            inside[joint] = digit[joint] = True
        numbers, letters = K.runs(inside & digit, offsets), K.runs(inside & ~digit, offsets)
        starts, ends = np.concatenate([numbers[0], letters[0]]), np.concatenate([numbers[1], letters[1]])
        kind = np.repeat(np.array([1, 0], np.uint8), [len(numbers[0]), len(letters[0])])
        order = np.argsort(starts, kind="stable")
        starts, ends, kind = starts[order], ends[order], kind[order]
        value = K.hashes(data, starts, ends)
        at = np.searchsorted(starts, offsets)
        shape = value.copy()
        if len(starts):
            row_first = np.zeros(len(starts), bool)
            row_first[at[:-1][at[:-1] < at[1:]]] = True
            # A stop since the last word's end makes a sentence's first word.
            stops = np.concatenate([[0], np.cumsum(_STOP[data])])
            begins = row_first.copy()
            begins[1:] |= stops[starts[1:]] > stops[ends[:-1]]
            lead = data[starts]
            high = (lead == 0xC3) & (ends - starts > 1)
            second = data[np.minimum(starts + 1, n - 1)]
            capital = _UPPER[lead] | (high & (second >= 0x80) & (second <= 0x9E))
            name = capital & ~begins & (kind == 0)
            number = kind == 1
            follows = np.zeros(len(starts), bool)
            follows[1:] = number[:-1] & ~row_first[1:]
            unit = follows & (kind == 0)
            unit[unit] = np.isin(value[unit], _UNITS)
            shape[name], shape[number], shape[unit] = NAME, NUMBER, UNIT
            drop = np.zeros(len(starts), bool)
            drop[1:] = (shape[1:] == NAME) & (shape[:-1] == NAME) & ~row_first[1:]
            if drop.any():
                head = np.flatnonzero(~drop)
                value = np.add.reduceat(value * np.uint64(3), head)
                shape = shape[head]
                at = np.searchsorted(head, at)
        yield first, at, shape, value


def _windows(shape: np.ndarray) -> np.ndarray:
    return K.shingles(K.mix(shape), WINDOW)


def _literal(shape: np.ndarray) -> np.ndarray:
    """Windows with enough words that are no placeholders."""
    plain = np.concatenate([[0], np.cumsum(shape > UNIT)])
    return plain[WINDOW:] - plain[:-WINDOW] >= LITERALS


class Items:
    """The benchmark's templates and the windows in them."""

    def __init__(self, rows: list[tuple[int, str | None]]):
        self.ids, self.templates = [], []
        for first, at, shape, value in templates(pa.array([t for _, t in rows], pa.string())):
            for k, (a, b) in enumerate(zip(at[:-1], at[1:], strict=True)):
                if b > a:
                    self.ids.append(rows[first + k][0])
                    self.templates.append(Template(shape[a:b], value[a:b]))
        hashes, items, places = [], [], []
        self.short: dict[int, list[int]] = defaultdict(list)  # items under a window, by their length
        for k, t in enumerate(self.templates):
            if len(t.shape) < WINDOW:
                self.short[len(t.shape)].append(k)
                continue
            some = np.flatnonzero(_literal(t.shape))
            hashes.append(_windows(t.shape)[some]), items.append(np.full(len(some), k)), places.append(some)
        self.hash, self.item, self.place = (np.concatenate(x) if x else np.zeros(0, kind) for x, kind in ((hashes, np.uint64), (items, np.int64), (places, np.int64)))
        order = np.argsort(self.hash, kind="stable")
        self.hash, self.item, self.place = self.hash[order], self.item[order], self.place[order]
        self.maybe = np.zeros(1 << 20, bool)
        self.maybe[(self.hash & np.uint64((1 << 20) - 1)).astype(np.int64)] = True

    def found(self, shape: np.ndarray, value: np.ndarray, hits: np.ndarray) -> dict[int, int]:
        """Item number -> template words shared in its longest consistent stretch, if they are enough. hits: windows to look up."""
        out: dict[int, int] = {}
        diagonals: dict[tuple[int, int], list[int]] = defaultdict(list)
        for p in hits:
            h = K.shingles(K.mix(shape[p : p + WINDOW]), WINDOW)[0]
            for j in range(int(np.searchsorted(self.hash, h)), int(np.searchsorted(self.hash, h, side="right"))):
                diagonals[int(self.item[j]), int(p - self.place[j])].append(int(self.place[j]))
        for (k, shift), places in diagonals.items():
            t = self.templates[k]
            enough = min(ENOUGH, len(t.shape))
            mark = np.zeros(len(t.shape) + 1, bool)
            for p in places:
                mark[p : p + WINDOW] = True
            edges = np.flatnonzero(np.diff(np.concatenate([[False], mark, [False]]).astype(np.int8)))
            for a, b in zip(edges[::2], edges[1::2], strict=True):
                # Words next to the windows that agree belong to the stretch too.
                while a > 0 and a - 1 + shift >= 0 and shape[a - 1 + shift] == t.shape[a - 1]:
                    a -= 1
                while b < len(t.shape) and b + shift < len(shape) and shape[b + shift] == t.shape[b]:
                    b += 1
                if b - a >= enough:
                    n = longest(t.shape[a:b], t.value[a:b], value[a + shift : b + shift], np.array([p - a for p in places if a <= p < b]))
                    if n >= enough:
                        out[k] = max(out.get(k, 0), n)
        return out

    def found_short(self, shape: np.ndarray, value: np.ndarray) -> dict[int, int]:
        """Items shorter than a window: their whole template must occur."""
        out = {}
        for n, items in self.short.items():
            if len(shape) >= n:
                mine = K.shingles(K.mix(shape), n)
                for k in items:
                    t = self.templates[k]
                    if (t.shape > UNIT).sum() >= min(LITERALS, n):
                        for p in np.flatnonzero(mine == K.shingles(K.mix(t.shape), n)[0]):
                            if consistent(t.shape, t.value, value[p : p + n]):
                                out[k] = n
                                break
        return out


def consistent(shape: np.ndarray, ours: np.ndarray, theirs: np.ndarray) -> bool:
    """Whether the placeholders' values map one to one, kind by kind."""
    for kind in (NUMBER, NAME, UNIT):
        at = shape == kind
        if at.any():
            pairs = set(zip(ours[at].tolist(), theirs[at].tolist(), strict=True))
            if len(pairs) != len({a for a, _ in pairs}) or len(pairs) != len({b for _, b in pairs}):
                return False
    return True


def longest(shape: np.ndarray, ours: np.ndarray, theirs: np.ndarray, windows: np.ndarray) -> int:
    """The length of the longest run of words in which the placeholders' values map one to one and one of the windows lies."""
    windows = np.sort(windows)
    forth: dict[tuple[int, int], list[int]] = {}  # value -> its partner in the run and how often
    back: dict[tuple[int, int], list[int]] = {}
    most = a = 0

    def close(b: int) -> None:
        nonlocal most
        k = int(np.searchsorted(windows, a))
        if b - a > most and k < len(windows) and windows[k] + WINDOW <= b:
            most = b - a

    kinds, ours, theirs = shape.tolist(), ours.tolist(), theirs.tolist()
    for b, kind in enumerate(kinds):
        if kind > UNIT:
            continue
        x, y = (kind, ours[b]), (kind, theirs[b])
        if forth.get(x, [theirs[b]])[0] != theirs[b] or back.get(y, [ours[b]])[0] != ours[b]:
            close(b)
            while forth.get(x, [theirs[b]])[0] != theirs[b] or back.get(y, [ours[b]])[0] != ours[b]:
                if kinds[a] <= UNIT:
                    for of, key in ((forth, (kinds[a], ours[a])), (back, (kinds[a], theirs[a]))):
                        of[key][1] -= 1
                        if not of[key][1]:
                            del of[key]
                a += 1
        forth.setdefault(x, [theirs[b], 0])[1] += 1
        back.setdefault(y, [ours[b], 0])[1] += 1
    close(len(kinds))
    return most


def _lookup(shared):
    def run(batches):
        items = shared.value
        for batch in batches:
            doc, item, words = [], [], []
            ids = batch.column("doc_id")
            for first, at, shape, value in templates(batch.column("text")):
                w = _windows(shape)
                hits = np.flatnonzero(items.maybe[(w & np.uint64((1 << 20) - 1)).astype(np.int64)])
                if len(hits) and len(items.hash):
                    near = np.minimum(np.searchsorted(items.hash, w[hits]), len(items.hash) - 1)
                    hits = hits[items.hash[near] == w[hits]]
                rows = np.searchsorted(at, hits, side="right") - 1
                hits = hits[hits + WINDOW <= at[rows + 1]] if len(hits) else hits
                rows = np.searchsorted(at, hits, side="right") - 1
                for k in range(len(at) - 1) if items.short else np.unique(rows):
                    a, b = at[k], at[k + 1]
                    got = items.found(shape[a:b], value[a:b], hits[rows == k] - a)
                    if items.short:
                        got |= items.found_short(shape[a:b], value[a:b])
                    for i, n in got.items():
                        doc.append(ids[first + int(k)].as_py()), item.append(items.ids[i]), words.append(n)
            yield pa.RecordBatch.from_arrays([pa.array(doc, pa.int64()), pa.array(item, pa.int64()), pa.array(words, pa.int32())], names=["doc_id", "item_id", "shared_words"])

    return run


def leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs (doc_id, text), benchmark (item_id, text) -> (doc_id, item_id, shared_words) for every leaked item.

    Null and empty texts match nothing; repeated rows match alike and come once; items of equal text all match. A
    benchmark over BROADCAST_BYTES is taken in parts of that size, each against all documents.
    """
    spark = docs.sparkSession
    docs = docs.where("doc_id is not null").select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    items = benchmark.where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text"))
    parts = 1
    if not bounded_bytes(items, BROADCAST_BYTES // 8):  # a file's bytes may grow some times when decoded
        parts = max(1, -(-int(items.agg(F.sum(F.octet_length("text"))).first()[0] or 0) // BROADCAST_BYTES))
    out = None
    for k in range(parts):
        rows = [(r[0], r[1]) for r in items.where(F.pmod(F.xxhash64("item_id"), F.lit(parts)) == k).orderBy("item_id").collect()]  # at most about BROADCAST_BYTES
        got = docs.mapInArrow(lean(_lookup(spark.sparkContext.broadcast(Items(rows)))), "doc_id long, item_id long, shared_words int")
        out = got if out is None else out.unionByName(got)
    return out.groupBy("doc_id", "item_id").agg(F.max("shared_words").alias("shared_words"))


def contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """Per leaking document: doc_id, items (sorted), shared_words (most in one item)."""
    return leaks(docs, benchmark).groupBy("doc_id").agg(F.array_sort(F.collect_set("item_id")).alias("items"), F.max("shared_words").alias("shared_words"))


def decontaminate(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """docs without the leaking documents; columns stay. Rows with a null doc_id stay."""
    with small_batches(docs.sparkSession):
        bad = table(leaks(docs, benchmark).select(F.col("doc_id").alias("_bad")).distinct(), "leaking")
    return docs.join(bad, docs["doc_id"] == bad["_bad"], "left_anti")
