"""Documents as token pieces, packed into as few sequences as can be found.

Every document's ids are cut only where it is longer than a sequence. Packing is bin completion: the largest piece left
opens a sequence, the fillings around it that no other filling dominates are enumerated, the one that wastes least goes
first, and the others are tried as well, as long as the waste so far could still save a sequence over the best solution
known (at first, best-fit decreasing) and that is above the lower bound. Pieces are dealt at random to groups of bounded size, so that
all cost is local; a group loses less than one sequence.
"""

from __future__ import annotations

import json
import zlib
from itertools import islice

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import keep, lean, small_batches, table

CAPACITY, END = 4096, 1
GROUP = 8192  # pieces that are packed together, on average
NODES, TRIES = 4000, 4  # fillings looked at in one group at most: so many, and so many for each piece; the incumbent stands after that
KNOWN = 600_000  # words whose ids a worker keeps; others are encoded each time
TOPS = (48, CAPACITY)  # ways of a first descent: from how many of the longest lengths the first of three pieces may come
TABLE = 1 << 21  # places in the table of these words
CALL = 1 << 12  # words for one call of the tokenizer, which holds some hundred bytes for each of their ids until it returns


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


# The pattern by which the tokenizer cuts text, on which the finer cut below rests.
CLASSES = "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"
_LETTER, _FIGURE, _OTHER, _HIGH = 1, 2, 3, 4
_kind = np.full(256, _OTHER, np.uint8)
_kind[K.SPACE] = 0
_kind[0x30:0x3A] = _FIGURE
_kind[0x41:0x5B] = _kind[0x61:0x7B] = _LETTER
_kind[0x80:] = _HIGH
_kind[0x1C:0x20] = 0  # white space to the tokenizer


class Ids:
    """A worker's memory of words and their ids, in arrays: an open table of hashes, and the ids of all words in a row.

    Words end at white space, so a word's ids do not depend on its neighbours. Where the tokenizer folds case and cuts by
    CLASSES, words end at ASCII letters' ends as well, at digits, and at letters that no apostrophe precedes.
    """

    of: dict[str, Ids] = keep(__name__, {})

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            config = json.load(f)
        cut = ((config.get("pre_tokenizer") or {}).get("pretokenizers") or [{}])[0].get("pattern", {}).get("Regex")
        folds = any(n.get("type") == "Lowercase" for n in (config.get("normalizer") or {}).get("normalizers", []))
        self.fine = folds and cut == CLASSES and config["model"].get("end_of_word_suffix") == "</w>"
        self.special = [t["content"].encode() for t in config.get("added_tokens", [])]
        vocabulary = self.model.get_vocab(with_added_tokens=True)
        self.last = np.zeros(max(vocabulary.values()) + 1, bool)  # whether an id ends a word
        self.last[[v for k, v in vocabulary.items() if k.endswith("</w>")]] = True
        self.keys, self.slot = np.zeros(TABLE, np.uint64), np.zeros(TABLE, np.int32)
        self.begin, self.ids = np.zeros(KNOWN + 1, np.int64), np.zeros(1 << 20, np.uint32)
        self.n = 0

    def _find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each hash (not zero) its place in the table, or the free place where it would go; and whether it is there."""
        at = (h & np.uint64(TABLE - 1)).astype(np.int64)
        there = self.keys[at]
        todo = np.flatnonzero((there != h) & (there != 0))
        while len(todo):
            at[todo] = (at[todo] + 1) & (TABLE - 1)
            there = self.keys[at[todo]]
            todo = todo[(there != h[todo]) & (there != 0)]
        return at, self.keys[at] == h

    def _encode(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all words in a row, and how many each has."""
        n = np.zeros(len(words), np.int64)
        plain = np.array([self.fine and w.isalpha() and w.isascii() for w in words], bool)
        together = np.flatnonzero(plain)
        parts: list[np.ndarray] = [np.zeros(0, np.uint32)] * len(words)
        flat = np.zeros(0, np.uint32)
        if len(together):
            # Words of letters go together: each is one word to the tokenizer too, and its last id says so.
            calls = (b" ".join(words[k] for k in together[a : a + CALL]).decode() for a in range(0, len(together), CALL))
            flat = np.concatenate([np.array(self.model.encode(text, add_special_tokens=False).ids, np.uint32) for text in calls])
            ends = np.flatnonzero(self.last[flat]) + 1
            n[together] = np.diff(ends, prepend=0)
        if len(together) == len(words):
            return flat, n
        begins = np.cumsum(n) - n
        others = np.flatnonzero(~plain)
        for a in range(0, len(others), CALL):
            some = others[a : a + CALL]
            for k, e in zip(some, self.model.encode_batch_fast([words[k].decode() for k in some], add_special_tokens=False), strict=True):
                parts[k] = np.array(e.ids, np.uint32)
                n[k] = len(parts[k])
        total = np.cumsum(n) - n
        out = np.zeros(int(n.sum()), np.uint32)
        if len(flat):
            out[np.repeat(total[together] - begins[together], n[together]) + np.arange(len(flat))] = flat
        for k in others:
            out[total[k] : total[k] + n[k]] = parts[k]
        return out, n

    def _words(self, data: np.ndarray, offsets: np.ndarray, raw: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        if not self.fine or any(s in raw for s in self.special):
            starts, ends, h, first = K.words(data, offsets, K.EXACT)
            return starts, ends, h ^ np.uint64(0x9E3779B97F4A7C15), first  # apart from the finer words, which are folded
        kind = _kind[data]
        inside = kind > 0
        starts, ends = K.runs(inside, offsets)
        if len(data) > 1:
            a, b = kind[:-1], kind[1:]
            cut = (a == _LETTER) & ((b == _OTHER) | (b == _FIGURE)) | (a == _FIGURE) & ((b == _LETTER) | (b == _OTHER) | (b == _FIGURE)) | (a == _OTHER) & ((b == _FIGURE) | (b == _LETTER) & (data[:-1] != 0x27))
            more = np.flatnonzero(cut) + 1
            edge = np.zeros(len(data) + 1, bool)
            edge[more] = True
            edge[offsets] = False
            more = np.flatnonzero(edge)
            if len(more):
                starts, ends = np.sort(np.concatenate([starts, more])), np.sort(np.concatenate([ends, more]))
        return starts, ends, K.hashes(data, starts, ends), np.searchsorted(starts, offsets)

    def rows(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all rows of a block, and where each row's begin (one more than rows)."""
        raw = data.tobytes()
        starts, ends, h, first = self._words(data, offsets, raw)
        h[h == 0] = 1
        at, known = self._find(h)
        source, n = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
        k = self.slot[at[known]]
        source[known] = self.begin[k]
        n[known] = self.begin[k + 1] - self.begin[k]
        store = self.ids
        missing = np.flatnonzero(~known)
        if len(missing):
            uniq, where, inverse = np.unique(h[missing], return_index=True, return_inverse=True)
            where = missing[where]
            flat, size = self._encode([raw[a:b] for a, b in zip(starts[where].tolist(), ends[where].tolist(), strict=True)])
            begins = np.cumsum(size) - size
            keep = min(len(uniq), KNOWN - self.n)
            base = int(self.begin[self.n])
            if keep:
                used = int(size[:keep].sum())
                while base + used > len(self.ids):
                    self.ids = np.concatenate([self.ids, np.zeros_like(self.ids)])
                self.ids[base : base + used] = flat[:used]
                self.begin[self.n + 1 : self.n + keep + 1] = base + begins[:keep] + size[:keep]
                self._keep(uniq[:keep], np.arange(self.n, self.n + keep, dtype=np.int32))
                self.n += keep
            # What is not kept is read from behind the store.
            store = np.concatenate([self.ids, flat])
            source[missing], n[missing] = len(self.ids) + begins[inverse], size[inverse]
        total = np.concatenate([[0], np.cumsum(n)])
        out = store[np.repeat(source - total[:-1], n) + np.arange(total[-1])]
        return out, total[first]

    def _keep(self, h: np.ndarray, slots: np.ndarray) -> None:
        while len(h):
            at, _ = self._find(h)
            self.keys[at] = h  # of several that want one place the last gets it
            mine = self.keys[at] == h
            self.slot[at[mine]] = slots[mine]
            h, slots = h[~mine], slots[~mine]


def _pieces(path: str, capacity: int, end: int):
    def run(batches):
        if path not in Ids.of:
            Ids.of[path] = Ids(path)
        worker = Ids.of[path]
        for batch in batches:
            ids = batch.column("doc_id")
            rows: list[tuple] = []
            at = []
            for first, data, offsets in K.blocks(batch.column("text")):
                every, at_row = worker.rows(data, offsets)
                for k, (i, j) in enumerate(zip(at_row[:-1].tolist(), at_row[1:].tolist(), strict=True)):
                    tokens = np.append(every[i:j], np.uint32(end)).astype("<u4")
                    for p, a in enumerate(range(0, len(tokens), capacity)):
                        piece = tokens[a : a + capacity]
                        at.append(first + k)
                        rows.append((p, a, len(piece), zlib.crc32(piece.tobytes())))
            columns = zip(*rows, strict=True) if rows else [[]] * 4
            kinds = (pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([ids.take(pa.array(at, pa.int64())), *(pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True))], names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return run


def token_pieces(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """docs (doc_id, text) -> doc_id, piece, start, length, ids_crc32: each row's ids with `end` after them, cut every `capacity`."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return docs.mapInArrow(lean(_pieces(path or tokenizer_path(), capacity, end)), "doc_id long, piece int, start long, length long, ids_crc32 long")


def least(lengths: np.ndarray, capacity: int) -> int:
    """A lower bound on sequences: all ids over the capacity, and pieces of which no two fit together with what must lie beside them."""
    n = -(-int(lengths.sum()) // capacity) if len(lengths) else 0
    for k in {0, *np.unique(lengths[lengths * 2 <= capacity]).tolist()[:: max(1, len(lengths) // 64)]}:
        big = lengths > capacity - k
        mid = (lengths * 2 > capacity) & ~big
        low = (lengths >= k) & (lengths * 2 <= capacity)
        room = int(mid.sum()) * capacity - int(lengths[mid].sum())
        n = max(n, int(big.sum() + mid.sum()) + max(0, -(-(int(lengths[low].sum()) - room) // capacity)))
    return n


def best_fit(lengths: np.ndarray, capacity: int) -> list[list[int]]:
    """Best-fit decreasing: each piece into the fullest sequence that still takes it."""
    open_: list[list[int]] = [[] for _ in range(capacity + 1)]  # sequences by the room they have
    some = np.zeros(capacity + 1, bool)
    out: list[list[int]] = []
    for k in np.argsort(-lengths, kind="stable").tolist():
        n = int(lengths[k])
        room = n + int(np.argmax(some[n:])) if some[n:].any() else -1
        if room < 0:
            out.append([k])
            b, room = len(out) - 1, capacity
        else:
            b = open_[room].pop()
            some[room] = bool(open_[room])
            out[b].append(k)
        open_[room - n].append(b)
        some[room - n] = True
    return out


def _ones(bits: int) -> int:
    return (1 << bits) - 1


def _dominated(filling: tuple[int, ...], count: np.ndarray, free: int, waste: int) -> bool:
    """Whether a piece that is left over could take the place of smaller ones: of none, of one, or of several together."""
    one, many = 0, 0  # sums of single pieces and of two or more, as bits
    for n in filling:
        many |= (one | many) << n
        one |= 1 << n
    for n in set(filling):
        if count[n] == filling.count(n):
            free &= ~(1 << n)

    def up(bits: int, by: int) -> int:
        """The bits and those up to `by` above them."""
        done = 0
        while done < by:
            step = min(done + 1, by - done)
            bits, done = bits | bits << step, done + step
        return bits

    return bool(free & up(many, waste) or waste and free & up((one | 1) << 1, waste - 1))


def _fillings(count: np.ndarray, room: int, spare: int, tries: list[int]):
    """The fillings of any number of pieces that are not dominated, least waste first, larger pieces first, with at most `spare` waste.

    Each filling looked at takes one of tries[0].
    """
    have = np.flatnonzero(count[: room + 1]).tolist()
    free = 0
    for n in have:
        free |= 1 << n
    reach, mask = [1], _ones(room + 1)  # the sums that the smallest lengths give, as bits
    for n in have:
        bits, c, step = reach[-1], min(int(count[n]), room // n), 1
        while c:
            k = min(step, c)
            bits |= bits << k * n & mask
            c, step = c - k, 2 * step
        reach.append(bits)

    def exact(i: int, s: int):
        if not s:
            yield ()
            return
        for j in range(i - 1, -1, -1):
            if not reach[j + 1] >> s & 1:
                return
            n = have[j]
            for c in range(min(int(count[n]), s // n), 0, -1):
                if reach[j] >> s - c * n & 1:
                    for rest in exact(j, s - c * n):
                        yield (n,) * c + rest

    sums = reach[-1]
    while sums:
        s = sums.bit_length() - 1
        if room - s > spare:
            return
        for filling in exact(len(have), s):
            if tries[0] <= 0:
                return
            tries[0] -= 1
            if not _dominated(filling, count, free, room - s):
                yield filling
        sums ^= 1 << s


def _bits(lengths) -> int:
    out = 0
    for n in lengths:
        out |= 1 << n
    return out


def _quick(count: np.ndarray, room: int, top: int) -> tuple[int, ...]:
    """The best filling by at most three pieces, and the fewest of these; the first of three is one of the `top` longest, so that short ones stay for later."""
    have = np.flatnonzero(count[: room + 1]).tolist()
    if not have:
        return ()
    mask = _ones(room + 1)
    one = _bits(have)
    if have[-1] == room:
        return (room,)
    two = {n: ((one if count[n] > 1 else one & ~(1 << n)) << n) & mask for n in have}  # sums of pairs, by one of the two
    pairs = 0
    for bits in two.values():
        pairs |= bits
    best, found = have[-1], (have[-1],)
    if pairs.bit_length() - 1 > best:
        best = pairs.bit_length() - 1
        n = next(n for n in reversed(have) if two[n] >> best & 1)
        found = (n, best - n)
    if best < room:
        three = 0
        for n in have[-top:]:
            three |= pairs << n
        sums = three & mask & ~_ones(best + 1)
        while sums:
            s = sums.bit_length() - 1
            for x in reversed(have[-top:]):
                if x <= s and pairs >> s - x & 1:
                    for y in reversed(have):
                        z = s - x - y
                        if y <= x and 0 < z <= y and one >> z & 1 and count[x] >= 1 + (x == y) + (x == z) and count[y] >= 1 + (y == x) + (y == z) and count[z] >= 1 + (z == x) + (z == y):
                            return (x, y, z)
            sums ^= 1 << s
    return found


def _greedy(lengths: np.ndarray, capacity: int, top: int) -> list[tuple[int, ...]]:
    """One quick filling after the other, without a way back."""
    count = np.bincount(lengths, minlength=capacity + 1)
    out = []
    for large in range(capacity, 0, -1):
        while count[large]:
            count[large] -= 1
            out.append((large, *_quick(count, capacity - large, top)))
            np.subtract.at(count, list(out[-1][1:]), 1)
    return out


def _options(count: np.ndarray, room: int, spare: int, tries: list[int], top: int):
    """The quick filling, then all others that are not dominated."""
    first = _quick(count, room, top)
    yield first
    first = tuple(sorted(first))
    yield from (f for f in _fillings(count, room, spare, tries) if tuple(sorted(f)) != first)


def complete(lengths: np.ndarray, capacity: int = CAPACITY) -> list[list[int]]:
    """Sequences as lists of places in `lengths` (1 to capacity each)."""
    if not len(lengths):
        return []
    best = best_fit(lengths, capacity)
    bound = least(lengths, capacity)
    if len(best) > bound:
        total = int(lengths.sum())
        count = np.bincount(lengths, minlength=capacity + 1)
        most, tries = len(best), [NODES + TRIES * len(lengths)]
        incumbent: list[tuple[int, ...]] | None = None
        top, fewest = TOPS[0], len(lengths) + 1
        for way in TOPS:
            if fewest > bound:
                found = _greedy(lengths, capacity, way)
                if len(found) < fewest:
                    top, fewest = way, len(found)
                if len(found) < most:
                    incumbent, most = found, len(found)
        done: list[tuple[int, ...]] = []
        taken = [0]  # fillings tried so far for each open place; they are enumerated anew on the way back, not kept
        waste = 0
        while taken and most > bound and tries[0] > 0:
            left = np.flatnonzero(count)
            chosen = None
            spare = (most - 1) * capacity - total - waste
            if not len(left):
                if len(done) < most:
                    incumbent, most = list(done), len(done)
            elif spare >= 0 and len(done) + 1 < most:
                large = int(left[-1])
                count[large] -= 1
                chosen = next(islice(_options(count, capacity - large, spare, tries, top), taken[-1], None), None)
                count[large] += 1
                tries[0] -= 1
            if chosen is not None:
                chosen = (large, *chosen)
                taken[-1] += 1
                taken.append(0)
                done.append(chosen)
                np.subtract.at(count, list(chosen), 1)
                waste += capacity - sum(chosen)
                continue
            taken.pop()
            if done:
                chosen = done.pop()
                np.add.at(count, list(chosen), 1)
                waste -= capacity - sum(chosen)
        if incumbent is not None:
            by: dict[int, list[int]] = {}
            for k, n in enumerate(lengths.tolist()):
                by.setdefault(n, []).append(k)
            best = [[by[n].pop() for n in sequence] for sequence in incumbent]
    return best


def _deal(capacity: int):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        # Any order of rows gives the same sequences.
        rows = rows.sort_values(["length", "doc_id", "piece", "ids_crc32"], ascending=[False, True, True, True]).reset_index(drop=True)
        lengths = rows["length"].to_numpy()
        sequence, offset = np.zeros(len(rows), np.int64), np.zeros(len(rows), np.int64)
        for k, places in enumerate(complete(lengths, capacity)):
            n = lengths[places]
            sequence[places], offset[places] = k, np.cumsum(n) - n
        return rows.assign(sequence_id=rows["part"].to_numpy().astype(np.int64) * (1 << 32) + sequence, offset=offset)[["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]]

    return run


def pack(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """docs (doc_id, text) -> doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null and empty texts are one id, the end. Repeated rows are packed as often as they are given; a null doc_id is
    kept. No rows: no rows. Other columns are not read. Which pieces are packed together also depends on how the input
    is split into tasks, so that rows repeated any number of times still spread over all groups.
    """
    with small_batches(docs.sparkSession):
        pieces = table(token_pieces(docs, path, capacity, end), "pieces")
    parts = max(1, round(pieces.count() / GROUP))
    part = F.pmod(F.xxhash64("doc_id", "piece", "ids_crc32", F.monotonically_increasing_id()), F.lit(parts)).cast("int")
    return pieces.withColumn("part", part).groupBy("part").applyInPandas(_deal(capacity), "doc_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
