"""A generalised additive model with pairwise interactions over measures of a text.

Every measure is cut into bins of about equal rows. In each round, one shallow tree for each measure in turn is fitted
to what is left over and added, damped, to the measure's lookup table; afterwards the pairs of measures that explain
most of the rest get two-way tables in the same manner. A score is a sum of looked-up values.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import lean, likely, table

SAMPLE = 60_000  # labelled rows that the model is fitted on at most, chosen by a hash of their id
BINS, PAIR_BINS, PAIRS = 64, 12, 12
ROUNDS, PAIR_ROUNDS, RATE, RIDGE = 150, 80, 0.15, 2.0
MEASURES = (
    "log_bytes", "log_words", "word_length", "long_words", "short_words", "words_per_line", "upper", "digits", "spaces", "high_bytes", "points", "commas", "exclamations", "bars",
    "marks", "other_symbols", "capitalised", "all_capitals", "distinct_words", "repeats_next", "distinct_pairs", "top_word", "points_per_word", "log_lines",
)


def _class(*codes: int | range) -> np.ndarray:
    out = np.zeros(256, bool)
    for c in codes:
        out[list(c) if isinstance(c, range) else c] = True
    return out


_CLASSES = {
    "upper": _class(range(0x41, 0x5B)), "digits": _class(range(0x30, 0x3A)), "spaces": K.SPACE, "high_bytes": _class(range(0x80, 256)), "points": _class(0x2E, 0x3F), "commas": _class(0x2C, 0x3B, 0x3A),
    "exclamations": _class(0x21), "bars": _class(0x7C), "marks": _class(0x23, 0x24, 0x25, 0x26, 0x2A), "other_symbols": _class(0x22, 0x27, range(0x28, 0x2A), 0x2B, 0x2D, 0x2F, range(0x3C, 0x3F), 0x40, range(0x5B, 0x61), 0x7B, 0x7D, 0x7E),
}


def measure(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """The measures of each row of a block, in the order of MEASURES."""
    rows = len(offsets) - 1
    per = lambda flags: np.diff(np.concatenate([[0], np.cumsum(flags)])[offsets])
    starts, ends, h, first = K.words(data, offsets)
    n, size = np.diff(first), np.diff(offsets)
    row = np.repeat(np.arange(rows), n)
    length = ends - starts
    words, nbytes = np.maximum(n, 1), np.maximum(size, 1)
    count = lambda flags: np.bincount(row[flags], minlength=rows)
    lines = per(data == 0x0A) + 1
    capital = _CLASSES["upper"]
    lead = capital[data[starts]] if len(starts) else np.zeros(0, bool)
    caps = np.concatenate([[0], np.cumsum(capital[data])])
    lower = np.concatenate([[0], np.cumsum(_class(range(0x61, 0x7B))[data])])
    shout = (caps[ends] - caps[starts] > 1) & (lower[ends] == lower[starts])
    order = np.lexsort((h, row))
    hs, rs = h[order], row[order]
    new = np.ones(len(hs), bool)
    new[1:] = (hs[1:] != hs[:-1]) | (rs[1:] != rs[:-1])
    distinct = np.bincount(rs[new], minlength=rows)
    begins = np.flatnonzero(new)
    top = np.zeros(rows)
    np.maximum.at(top, rs[begins], np.diff(np.append(begins, len(hs))))
    again = np.zeros(len(h), bool)
    again[1:] = (h[1:] == h[:-1]) & (row[1:] == row[:-1])
    pair = K.mix(h[:-1] * np.uint64(3) + h[1:]) if len(h) > 1 else np.zeros(0, np.uint64)
    inside = row[1:] == row[:-1] if len(h) > 1 else np.zeros(0, bool)
    pair, pair_row = pair[inside], row[1:][inside] if len(h) > 1 else row
    order = np.lexsort((pair, pair_row))
    ps, pr = pair[order], pair_row[order]
    new = np.ones(len(ps), bool)
    new[1:] = (ps[1:] != ps[:-1]) | (pr[1:] != pr[:-1])
    share = {name: per(flags[data]) / nbytes for name, flags in _CLASSES.items()}
    values = {
        "log_bytes": np.log1p(size), "log_words": np.log1p(n), "word_length": np.bincount(row, weights=length, minlength=rows) / words, "long_words": count(length > 12) / words, "short_words": count(length < 3) / words,
        "words_per_line": n / lines, "capitalised": count(lead) / words, "all_capitals": count(shout) / words, "distinct_words": distinct / words, "repeats_next": count(again) / words,
        "distinct_pairs": np.bincount(pr[new], minlength=rows) / np.maximum(n - 1, 1), "top_word": top / words, "points_per_word": per(_CLASSES["points"][data]) / words, "log_lines": np.log(lines),
    } | share
    return np.stack([values[m] for m in MEASURES], axis=1)


def _measures(batches):
    for batch in batches:
        parts = [measure(data, offsets) for _, data, offsets in K.blocks(batch.column("text"))]
        x = np.concatenate(parts) if parts else np.zeros((0, len(MEASURES)))
        flat = pa.array(x.astype(np.float32).ravel())
        yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * len(MEASURES)), flat)], names=["doc_id", "measures"])


def measures(docs: DataFrame) -> DataFrame:
    """docs (doc_id, text) -> doc_id, measures (array of float, in the order of MEASURES). Null text is empty."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(lean(_measures), "doc_id long, measures array<float>")


@dataclass
class Model:
    """Bin edges and lookup tables."""

    base: float = 0.0
    edges: list[np.ndarray] = field(default_factory=list)
    tables: list[np.ndarray] = field(default_factory=list)
    coarse: list[np.ndarray] = field(default_factory=list)
    pairs: list[tuple[int, int, np.ndarray]] = field(default_factory=list)

    def score(self, x: np.ndarray) -> np.ndarray:
        out = np.full(len(x), self.base)
        for k, (e, t) in enumerate(zip(self.edges, self.tables, strict=True)):
            out += t[np.searchsorted(e, x[:, k], side="right")]
        bins: dict[int, np.ndarray] = {}
        for i, j, t in self.pairs:
            for k in (i, j):
                if k not in bins:
                    bins[k] = np.searchsorted(self.coarse[k], x[:, k], side="right")
            out += t[bins[i], bins[j]]
        return 1 / (1 + np.exp(-np.clip(out, -30, 30)))


def _edges(v: np.ndarray, bins: int) -> np.ndarray:
    return np.unique(np.quantile(v, np.linspace(0, 1, bins + 1)[1:-1], method="lower"))


def _split(g: np.ndarray, h: np.ndarray) -> tuple[float, int]:
    """The best cut of a row of bins: its gain and the first bin on the right."""
    a, b = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
    if not len(a):
        return 0.0, 0
    gain = a**2 / (b + RIDGE) + (g.sum() - a) ** 2 / (h.sum() - b + RIDGE) - g.sum() ** 2 / (h.sum() + RIDGE)
    k = int(np.argmax(gain))
    return float(gain[k]), k + 1


def _tree(g: np.ndarray, h: np.ndarray) -> np.ndarray:
    """Values of a tree of depth two over the bins."""
    out = np.zeros(len(g))
    _, cut = _split(g, h)
    for a, b in ((0, cut), (cut, len(g))):
        if b > a:
            gain, inner = _split(g[a:b], h[a:b])
            for c, d in ((a, a + inner), (a + inner, b)) if gain > 0 else ((a, b),):
                if d > c:
                    out[c:d] = g[c:d].sum() / (h[c:d].sum() + RIDGE)
    return out


def _quarters(g: np.ndarray, h: np.ndarray) -> tuple[float, np.ndarray]:
    """The best cut of a two-way table into four leaves, and their values."""
    ga, ha = (np.pad(np.cumsum(np.cumsum(x, axis=0), axis=1), ((1, 0), (1, 0))) for x in (g, h))
    total_g, total_h = ga[-1, -1], ha[-1, -1]
    parts = [(ga[1:-1, 1:-1], ha[1:-1, 1:-1])]
    top, left = (ga[1:-1, -1:], ha[1:-1, -1:]), (ga[-1:, 1:-1], ha[-1:, 1:-1])
    parts.append((top[0] - parts[0][0], top[1] - parts[0][1]))
    parts.append((left[0] - parts[0][0], left[1] - parts[0][1]))
    parts.append((total_g - top[0] - left[0] + parts[0][0], total_h - top[1] - left[1] + parts[0][1]))
    gain = sum(a**2 / (b + RIDGE) for a, b in parts) - total_g**2 / (total_h + RIDGE)
    if not gain.size:
        return 0.0, np.zeros_like(g)
    i, j = np.unravel_index(int(np.argmax(gain)), gain.shape)
    out = np.zeros_like(g)
    for (a, b), where in zip(parts, ((slice(0, i + 1), slice(0, j + 1)), (slice(0, i + 1), slice(j + 1, None)), (slice(i + 1, None), slice(0, j + 1)), (slice(i + 1, None), slice(j + 1, None))), strict=True):
        out[where] = a[i, j] / (b[i, j] + RIDGE)
    return float(gain[i, j]), out


def fit(x: np.ndarray, y: np.ndarray) -> Model:
    """x: rows of measures, y: 0 or 1. No rows, or labels of one kind, leave a constant."""
    model = Model()
    if not len(y) or y.min() == y.max():
        share = (y.sum() + 1) / (len(y) + 2)
        model.base = float(np.log(share / (1 - share)))
        return model
    share = y.mean()
    model.base = float(np.log(share / (1 - share)))
    k = x.shape[1]
    model.edges, model.coarse = [_edges(x[:, j], BINS) for j in range(k)], [_edges(x[:, j], PAIR_BINS) for j in range(k)]
    bins = [np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(model.edges)]
    model.tables = [np.zeros(len(e) + 1) for e in model.edges]
    f = np.full(len(y), model.base)

    def rest() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-f))
        return y - p, p * (1 - p)

    for _ in range(ROUNDS):
        for j in range(k):
            r, w = rest()
            step = RATE * _tree(np.bincount(bins[j], r, len(model.tables[j])), np.bincount(bins[j], w, len(model.tables[j])))
            model.tables[j] += step
            f += step[bins[j]]
    coarse = [np.searchsorted(e, x[:, j], side="right") for j, e in enumerate(model.coarse)]
    sizes = [len(e) + 1 for e in model.coarse]

    def grid(i: int, j: int, v: np.ndarray) -> np.ndarray:
        return np.bincount(coarse[i] * sizes[j] + coarse[j], v, sizes[i] * sizes[j]).reshape(sizes[i], sizes[j])

    r, w = rest()
    gains = sorted(((_quarters(grid(i, j, r), grid(i, j, w))[0], i, j) for i in range(k) for j in range(i + 1, k)), reverse=True)[:PAIRS]
    model.pairs = [(i, j, np.zeros((sizes[i], sizes[j]))) for g, i, j in gains if g > 0]
    for _ in range(PAIR_ROUNDS):
        for i, j, t in model.pairs:
            r, w = rest()
            step = RATE * _quarters(grid(i, j, r), grid(i, j, w))[1]
            t += step
            f += step[coarse[i], coarse[j]]
    return model


def _scores(shared):
    def run(batches):
        for batch in batches:
            x = batch.column("measures").flatten().to_numpy(zero_copy_only=False).reshape(-1, len(MEASURES))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(shared.value.score(x.astype(np.float64)))], names=["doc_id", "score"])

    return run


def classify(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE) -> DataFrame:
    """docs (doc_id, text), labels (doc_id, `label` 0 or 1) -> doc_id, held_out, score, predicted.

    Fitted on at most `sample` labelled rows whose crc32(doc_id as text) mod 3 is not 1; the others are held out. Only
    measures of the text enter. Null text counts as empty; a null doc_id is scored and not held out; repeated rows
    are scored each time; labels that are null or for no document are not used; no labels give a score of one half.
    """
    known = table(measures(docs), "measures")
    fold = F.crc32(F.col("doc_id").cast("string")) % 3
    marks = labels.where(F.col(label).isin(0, 1) & F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), F.col(label).cast("int").alias("_y"))
    labelled = table(known.where(fold != 1).join(marks, "doc_id").select("doc_id", "measures", "_y"), "labelled")
    rows = likely(labelled, sample, "doc_id").orderBy(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 30)), "doc_id", "_y").limit(sample).select("measures", "_y").toPandas()
    x = np.stack(rows["measures"].to_numpy()).astype(np.float64) if len(rows) else np.zeros((0, len(MEASURES)))
    model = docs.sparkSession.sparkContext.broadcast(fit(x, rows["_y"].to_numpy(np.float64)))
    out = known.mapInArrow(lean(_scores(model)), "doc_id long, score double")
    return out.select("doc_id", F.coalesce(fold == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
