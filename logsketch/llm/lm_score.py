"""Cross-entropy difference: two matched n-gram models, one of a target, one of everything, over one vocabulary.

The vocabulary is every word of all rows, and one unknown word. Words and word pairs are counted exactly. Rows are put
together to chunks of some megabytes; a chunk's distinct words and pairs go, sorted and with their counts, to partitions
by key, which add the chunks up and send each the totals of its own keys in the same order. What one task holds is a
chunk or a share of the keys; the number of both grows with the input, and nothing is broadcast. A row's score is the
mean over its words of the background's loss less the target's: the higher, the more it reads like the target.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import lean, small_batches, sweep, table, trim

VOCABULARY = (1 << 16) - 1
PAIR_WEIGHT = 0.5  # of the word pair against the single word
FLUSH = 400_000
CHUNK = 2 << 20  # bytes of text whose words and pairs are counted together
FILE = 4  # chunks of one file, as a reader decodes all of a file's chunks at once
SHARE = 6 << 20  # bytes of text for each partition of the keys
WORD, PAIR = 0, 1
COLUMNS = (4, 2)  # of counts, by kind
TOTALS = -1  # in place of a chunk, in the row of a partition's own sums
BEGIN = np.uint64(0x5851F42D4C957F2D)  # stands before a row's first word
_CHUNKS = "chunk long, size long, rows binary"
_REQUESTS = "part int, kind int, chunk long, keys binary, width int, counts binary"
_ANSWERS = "part int, kind int, chunk long, width int, counts binary, distinct long, background long, aim long"


def _word_counts(batches):
    """Words and their counts, summed over blocks as long as memory stays small."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    size = 0

    def flush():
        words, inverse = np.unique(np.concatenate([w for w, _ in held]), return_inverse=True)
        return words, np.bincount(inverse, weights=np.concatenate([c for _, c in held])).astype(np.int64)

    for batch in batches:
        for _, data, offsets in K.blocks(batch.column("text")):
            held.append(np.unique(K.words(data, offsets)[2], return_counts=True))
            size += len(held[-1][0])
            if size > 2 * FLUSH:
                held = [flush()]
                size = len(held[0][0])
                if size > FLUSH:
                    yield pa.RecordBatch.from_arrays([pa.array(held[0][0].view(np.int64)), pa.array(held[0][1])], names=["word", "n"])
                    held, size = [], 0
    if held:
        words, counts = flush()
        yield pa.RecordBatch.from_arrays([pa.array(words.view(np.int64)), pa.array(counts)], names=["word", "n"])


def vocabulary(docs: DataFrame, size: int = VOCABULARY) -> np.ndarray:
    """The most frequent words' hashes, sorted; ties to the smaller hash."""
    counts = docs.select("text").mapInArrow(lean(_word_counts), "word long, n long").groupBy("word").agg(F.sum("n").alias("n"))
    top = counts.orderBy(F.desc("n"), "word").limit(size).collect()  # `size` rows, whatever the input
    return np.sort(np.array([r[0] for r in top], np.int64).view(np.uint64))


def _chunks(batches):
    """Rows of some megabytes of text together, as Arrow streams."""
    held: list[pa.RecordBatch] = []
    size, n, base = 0, 0, TaskContext.get().partitionId() << 32

    def out():
        sink = pa.BufferOutputStream()
        with pa.ipc.new_stream(sink, held[0].schema) as writer:
            for x in held:
                writer.write_batch(x)
        return pa.RecordBatch.from_arrays([pa.array([base + n]), pa.array([size], pa.int64()), pa.array([sink.getvalue().to_pybytes()], pa.binary())], names=["chunk", "size", "rows"])

    for batch in batches:
        for first, data, offsets in K.blocks(batch.column("text")):
            held.append(batch.slice(first, len(offsets) - 1))
            size += len(data)
            if size >= CHUNK:
                yield out()
                held, size, n = [], 0, n + 1
    if held:
        yield out()


def _texts(rows: bytes) -> list[pa.RecordBatch]:
    return list(pa.ipc.open_stream(rows))


def _column(batches: list[pa.RecordBatch], name: str) -> np.ndarray:
    return np.concatenate([b.column(name).to_numpy(zero_copy_only=False) for b in batches])


class Grams:
    """A chunk's words: the distinct words and pairs in the order of their keys, and the place of each word among them."""

    def __init__(self, batches: list[pa.RecordBatch]):
        hashes, sizes = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for batch in batches:
            for _, data, offsets in K.blocks(batch.column("text")):
                _, _, h, first = K.words(data, offsets)
                hashes.append(h), sizes.append(np.diff(first))
        h, self.sizes = np.concatenate(hashes), np.concatenate(sizes)
        begins = np.cumsum(self.sizes) - self.sizes
        begins = begins[self.sizes > 0]
        self.words, self.word = np.unique(np.append(h, BEGIN), return_inverse=True)
        begin, self.word = self.word[-1], self.word[:-1]
        self.before = np.empty_like(self.word)
        self.before[1:] = self.word[:-1]
        self.before[begins] = begin
        # Pairs by their places in the chunk first: these are exact and small.
        pairs, self.pair = np.unique(self.before * len(self.words) + self.word, return_inverse=True)
        keys = K.mix(K.mix(self.words[pairs // len(self.words)]) * np.uint64(3) + self.words[pairs % len(self.words)])
        order = np.argsort(keys)
        self.pairs = keys[order]
        place = np.empty_like(order)
        place[order] = np.arange(len(order))
        self.pair = place[self.pair]

    def counts(self, roles: list[np.ndarray]) -> list[tuple[int, np.ndarray, np.ndarray]]:
        """(kind, keys, counts by column), for each role of rows: words as such and as the first of a pair; pairs."""
        words, pairs = [], []
        for role in roles:
            own = np.repeat(role, self.sizes)
            words += [np.bincount(x[own], minlength=len(self.words)) for x in (self.word, self.before)]
            pairs.append(np.bincount(self.pair[own], minlength=len(self.pairs)))
        return [(WORD, self.words, np.stack(words)), (PAIR, self.pairs, np.stack(pairs))]


def _packed_keys(keys: np.ndarray) -> bytes:
    """Sorted keys as differences, byte by byte of all, so that the bytes that are zero lie together."""
    return np.diff(keys, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T.tobytes()


def _unpacked_keys(keys: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(keys, np.uint8).reshape(8, -1).T.copy().view(np.uint64).ravel(), dtype=np.uint64)


def _packed(counts: np.ndarray) -> tuple[int, bytes]:
    """Counts in the least width that holds them, compressed, behind their size."""
    most = int(counts.max(initial=0))
    width = next(w for w in (1, 2, 4, 8) if most < 1 << 8 * w)
    raw = counts.astype(f"<u{width}").tobytes()
    return width, len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def _unpacked(width: int, counts: bytes, columns: int) -> np.ndarray:
    raw = pa.decompress(counts[8:], int.from_bytes(counts[:8], "little"), codec="zstd", asbytes=True)
    return np.frombuffer(raw, f"<u{width}").reshape(columns, -1)


def _requests(parts: int):
    def run(batches):
        for batch in batches:
            for chunk, rows in zip(batch.column("chunk").to_pylist(), batch.column("rows"), strict=True):
                texts, out = _texts(rows.as_py()), []
                for kind, keys, counts in Grams(texts).counts([_column(texts, "seen"), _column(texts, "aim")]):
                    part = ((keys >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)
                    edges = np.searchsorted(part, np.arange(parts + 1))
                    for p in np.unique(part).tolist():
                        at = slice(edges[p], edges[p + 1])
                        out.append((p, kind, chunk, _packed_keys(keys[at]), *_packed(counts[:, at])))
                kinds = (pa.int32(), pa.int32(), pa.int64(), pa.binary(), pa.int32(), pa.binary())
                columns = zip(*out, strict=True) if out else [[]] * len(kinds)
                yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, kinds, strict=True)], names=["part", "kind", "chunk", "keys", "width", "counts"])

    return run


def _answer(rows: pa.Table) -> pa.Table:
    """Adds up the counts of one share of the keys; each chunk gets the totals of its keys."""
    part, kind = rows.column("part")[0].as_py(), rows.column("kind")[0].as_py()
    columns = COLUMNS[kind]
    keys = [_unpacked_keys(x.as_py()) for x in rows.column("keys")]
    at = np.concatenate([[0], np.cumsum([len(k) for k in keys])])
    uniq, inverse = np.unique(np.concatenate(keys), return_inverse=True)
    del keys
    total = np.zeros((columns, len(uniq)), np.uint64)
    for k, (width, counts) in enumerate(zip(rows.column("width").to_pylist(), rows.column("counts"), strict=True)):
        total[:, inverse[at[k] : at[k + 1]]] += _unpacked(width, counts.as_py(), columns)  # keys of one request differ
    out: list[tuple] = [(chunk, *_packed(total[:, inverse[at[k] : at[k + 1]]]), 0, 0, 0) for k, chunk in enumerate(rows.column("chunk").to_pylist())]
    if kind == WORD:
        out.append((TOTALS, 1, b"", int((total[0] > 0).sum()), int(total[0].sum()), int(total[2].sum())))
    chunk, width, counts, *sums = zip(*out, strict=True)
    n = len(out)
    del total, inverse
    trim()
    return pa.table(
        [pa.array([part] * n, pa.int32()), pa.array([kind] * n, pa.int32()), pa.array(chunk, pa.int64()), pa.array(width, pa.int32()), pa.array(counts, pa.binary()), *(pa.array(x, pa.int64()) for x in sums)],
        names=["part", "kind", "chunk", "width", "counts", "distinct", "background", "aim"],
    )


def _loss(pair: np.ndarray, first: np.ndarray, word: np.ndarray, words: int, vocabulary: int) -> np.ndarray:
    """Each word's loss by its pair's count, the count of the word before as the first of a pair, and its own."""
    weight = np.where(first > 0, PAIR_WEIGHT, 0)
    return -np.log(weight * pair / np.maximum(first, 1) + (1 - weight) * (word + 1.0) / (words + vocabulary))


def _score(distinct: int, sums: tuple[int, int]):
    vocabulary = distinct + 1  # and the unknown word

    def run(chunk: pa.Table, answers: pa.Table) -> pa.Table:
        batches = [b for x in chunk.column("rows") for b in _texts(x.as_py())]
        grams = Grams(batches)
        totals: dict[int, list] = {WORD: [], PAIR: []}
        rows = zip(*(answers.column(c).to_pylist() for c in ("kind", "part", "width", "counts")), strict=True)
        for kind, _, width, counts in sorted(rows, key=lambda r: r[:2]):
            totals[kind].append(_unpacked(width, counts, COLUMNS[kind]).astype(np.float64))
        n = grams.sizes
        row, many = np.repeat(np.arange(len(n)), n), np.maximum(n, 1)
        losses = [np.zeros(len(n)), np.zeros(len(n))]
        if len(row):
            words, pairs = np.concatenate(totals[WORD], axis=1), np.concatenate(totals[PAIR], axis=1)
            for k in (0, 1):
                loss = _loss(pairs[k][grams.pair], words[2 * k + 1][grams.before], words[2 * k][grams.word], sums[k], vocabulary)
                losses[k] = np.bincount(row, weights=loss, minlength=len(n)) / many
        out = pa.table([pa.chunked_array([b.column("doc_id") for b in batches], pa.int64()), pa.array(n.astype(np.int64)), pa.array(losses[1]), pa.array(losses[0]), pa.array(losses[0] - losses[1])], names=["doc_id", "n_words", "loss_target", "loss_background", "difference"])
        return out.filter(pa.array(_column(batches, "seen")))

    return run


def score(docs: DataFrame, target: DataFrame | str) -> DataFrame:
    """docs (doc_id, text) -> doc_id, n_words, loss_target, loss_background, difference.

    target: rows (doc_id, text), or the name of a boolean column of docs that is true for rows of the target, which
    saves counting them twice. The background is all of docs. Losses are means over a row's words in natural
    logarithms; rows without words or text score 0. Repeated rows count and are scored each time. An empty target leaves
    a uniform target model. Words of the target that docs lack only add to its sum. Words and pairs are told apart by
    64-bit hashes.
    """

    def some(df: DataFrame, seen: bool, aim) -> DataFrame:
        return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.lit(seen).alias("seen"), aim.alias("aim"))

    if isinstance(target, str):
        rows = some(docs, True, F.coalesce(F.col(target), F.lit(False)))
    else:
        rows = some(docs, True, F.lit(False)).unionByName(some(target, False, F.lit(True)))
    chunks = table(rows.mapInArrow(lean(_chunks), _CHUNKS), "chunks", FILE)
    parts = max(1, round((chunks.agg(F.sum("size")).first()[0] or 0) / SHARE))
    with small_batches(docs.sparkSession):
        answers = table(chunks.mapInArrow(lean(_requests(parts)), _REQUESTS).groupBy("kind", "part").applyInArrow(_answer, _ANSWERS), "answers")
    for _ in range(2):  # the requests' shuffle files go before the next shuffle; Spark's cleaner takes a moment
        sweep(docs.sparkSession)
        time.sleep(1)
    sums = [x or 0 for x in answers.where(F.col("chunk") == TOTALS).agg(F.sum("distinct"), F.sum("background"), F.sum("aim")).first()]
    answers = answers.where(F.col("chunk") != TOTALS).select("chunk", "kind", "part", "width", "counts")
    return chunks.groupBy("chunk").cogroup(answers.groupBy("chunk")).applyInArrow(_score(sums[0], (sums[1], sums[2])), "doc_id long, n_words long, loss_target double, loss_background double, difference double")
