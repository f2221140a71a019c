"""Main text of web pages by a recurrent block labeller.

A page is the sequence of its text blocks. Each block is a vector: hashed tags, classes and ids of its path, hashed
words, and a few measures. A bidirectional LSTM reads the whole sequence both ways and labels every block, so that a
decision rests on the document around it. It is fitted on a bounded sample of the pages themselves, labelled by what
their own mark-up declares, with further blocks of declared kinds put in, so that rare kinds are known as well.
"""

from __future__ import annotations

import html
import re
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .common import likely

SAMPLE, SAMPLE_BYTES = 240, 1 << 18  # pages that the labeller is fitted on at most, none longer than that
PATH, WORD, MORE, HIDDEN = 32, 12, 6, 16
EPOCHS, GROUP, RATE = 14, 24, 0.01
ROWS = 128  # pages that are labelled together

# Elements that start a block, elements without an end, elements whose text is no text.
BLOCKS = frozenset(
    "address article aside blockquote body button center dd details dialog div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hr html label legend li main menu nav ol optgroup option p pre section select summary table tbody td tfoot th thead title tr ul".split()
)
EMPTY = frozenset("area base br col embed hr img input link meta param source track wbr".split())
# Words of tags, classes and ids that mark what is not the article.
ASIDE = (
    "nav menu navbar breadcrumb breadcrumbs header masthead footer aside sidebar side widget notice alert cookie consent banner ad ads advert advertisement sponsor sponsored promo form newsletter subscribe "
    "signup login search comment comments reply replies disqus share sharing social related recommended popup modal overlay pagination pager tags copyright toolbar head title button select option label"
).split()
_ASIDE = frozenset(ASIDE)
_RAW = re.compile(r"<!--.*?(?:-->|$)|<(script|style|noscript|template|svg|iframe|object|textarea)\b.*?(?:</\1\s*>|$)|<!\[CDATA\[.*?\]\]>|<[!?][^>]*>", re.S | re.I)
# Quotes count only behind an equals sign; a tag that the page's end cuts off is no text.
_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)((?:[^>=]++|=\s*+(?:\"[^\"]*+\"|'[^']*+'|))*+)(?:>|\Z)")
# Elements that are seen between words; all else that is taken out leaves its neighbours together.
_SEEN = ("svg", "iframe", "object", "textarea")
_NAMES = re.compile(r"""\b(?:class|id|role)\s*=\s*(?:"([^"]*)"|'([^']*)'|([^\s"'>]+))""", re.I)
_SPLIT = re.compile(r"[^a-z0-9]+")
_rng = np.random.default_rng(17)
_path_table = _rng.choice([-1.0, 1.0], size=(2048, PATH)).astype(np.float32)
_word_table = _rng.normal(size=(4096, WORD)).astype(np.float32)


def blocks(page: str | None) -> list[tuple[tuple[str, ...], str, int]]:
    """Text blocks in page order: path (tags with words of class, id and role), text, characters inside links.

    Unclosed and stray tags are taken as browsers take them: a paragraph ends where another block begins, an end
    tag without its start is passed over. Character references are decoded, white space becomes one space.
    """
    out: list[tuple[tuple[str, ...], str, int]] = []
    path: list[tuple[str, tuple[str, ...]]] = []
    held: list[str] = []
    link = linked = 0

    def close() -> None:
        nonlocal linked
        text = " ".join(html.unescape("".join(held)).split())
        if text:
            out.append((tuple(x for _, names in path for x in names), text, linked))
        held.clear()
        linked = 0

    source = _RAW.sub(lambda m: " " if (m[1] or "").lower() in _SEEN else "", page or "")
    at = 0
    for m in _TAG.finditer(source):
        if m.start() > at:
            held.append(source[at : m.start()])
            linked += (m.start() - at) if link else 0
        at = m.end()
        end, tag = m[1], m[2].lower()
        if tag == "a":
            link = 0 if end else 1
        elif tag == "br":
            held.append(" ")
        elif tag in BLOCKS:
            close()
            link = 0
            if end:
                if any(t == tag for t, _ in path):
                    while path.pop()[0] != tag:
                        pass
            else:
                if path and path[-1][0] == "p":
                    path.pop()
                if tag in ("li", "dt", "dd", "tr", "td", "th", "option") and path and path[-1][0] == tag:
                    path.pop()
                if tag not in EMPTY:
                    names = [tag]
                    if "=" in m[3]:
                        for a, b, c in _NAMES.findall(m[3]):
                            names += [x for x in _SPLIT.split((a or b or c).lower()) if x]
                    path.append((tag, tuple(names)))
    held.append(source[at:])
    close()
    return out


def declared(path: tuple[str, ...]) -> bool:
    """Whether the mark-up itself says that a block belongs to the article."""
    inside = "article" in path or "main" in path
    after = path[max((k for k, x in enumerate(path) if x in ("article", "main")), default=-1) + 1 :] if inside else path
    return not _ASIDE.intersection(after) and not (inside and _ASIDE.intersection(path[: len(path) - len(after)]) - {"header"})


_paths: dict[tuple[str, ...], np.ndarray] = {}


def _path_vector(path: tuple[str, ...]) -> np.ndarray:
    if path not in _paths:
        if len(_paths) > 50_000:
            _paths.clear()
        v = np.zeros(PATH, np.float32)
        for depth, x in enumerate(path):
            v += _path_table[zlib.crc32(x.encode()) % 2048] * (1.0 if depth else 0.5)
        _paths[path] = v / np.sqrt(max(1, len(path)))
    return _paths[path]


def vectors(found: list[tuple[tuple[str, ...], str, int]]) -> np.ndarray:
    """One row for each block."""
    out = np.zeros((len(found), PATH + WORD + MORE), np.float32)
    if not found:
        return out
    texts = pa.array([t for _, t, _ in found])
    for first, data, offsets in K.blocks(texts):
        _, _, h, at = K.words(data, offsets)
        n = np.diff(at)
        row = np.repeat(np.arange(len(n)), n)
        cell = (h & np.uint64(4095)).astype(np.int64)
        for j in range(WORD):
            out[first : first + len(n), PATH + j] = np.bincount(row, weights=_word_table[cell, j], minlength=len(n)) / np.maximum(n, 1)
        out[first : first + len(n), PATH + WORD] = np.log1p(n) / 4
    chars = np.array([len(t) for _, t, _ in found], np.float32)
    out[:, :PATH] = [_path_vector(p) for p, _, _ in found]
    out[:, PATH + WORD + 1] = np.log1p(chars) / 6
    out[:, PATH + WORD + 2] = np.minimum(1, np.array([k for _, _, k in found]) / np.maximum(chars, 1))
    out[:, PATH + WORD + 3] = [t[-1] in ".!?" for _, t, _ in found]
    out[:, PATH + WORD + 4] = np.arange(len(found)) / len(found)
    out[:, PATH + WORD + 5] = 1
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


class Labeller:
    """Bidirectional LSTM with one output for each block."""

    def __init__(self, seed: int = 3):
        r = np.random.default_rng(seed)
        d = PATH + WORD + MORE
        self.p = {}
        for side in "fb":
            self.p[f"x{side}"] = (r.normal(size=(d, 4 * HIDDEN)) / np.sqrt(d)).astype(np.float32)
            self.p[f"h{side}"] = (r.normal(size=(HIDDEN, 4 * HIDDEN)) / np.sqrt(HIDDEN)).astype(np.float32)
            self.p[f"c{side}"] = np.concatenate([np.zeros(HIDDEN), np.ones(HIDDEN), np.zeros(2 * HIDDEN)]).astype(np.float32)
        self.p["o"] = (r.normal(size=2 * HIDDEN) / np.sqrt(2 * HIDDEN)).astype(np.float32)
        self.p["s"] = (r.normal(size=d) * 0.01).astype(np.float32)

    @staticmethod
    def _pad(pages: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        n = np.array([len(p) for p in pages])
        x = np.zeros((len(pages), n.max(), PATH + WORD + MORE), np.float32)
        for k, p in enumerate(pages):
            x[k, : len(p)] = p
        return x, n

    def _run(self, x: np.ndarray, n: np.ndarray, side: str, keep: bool = False):
        """Hidden states of one direction; the backward one reads every page from its own end."""
        b, t, _ = x.shape
        w, u, c0 = self.p[f"x{side}"], self.p[f"h{side}"], self.p[f"c{side}"]
        drive = x.reshape(b * t, -1) @ w
        drive = drive.reshape(b, t, -1) + c0
        h, c = np.zeros((b, HIDDEN), np.float32), np.zeros((b, HIDDEN), np.float32)
        out = np.zeros((b, t, HIDDEN), np.float32)
        trail = []
        for k in range(t) if side == "f" else range(t - 1, -1, -1):
            live = (k < n)[:, None]
            z = drive[:, k] + h @ u
            i, f, o = _sigmoid(z[:, :HIDDEN]), _sigmoid(z[:, HIDDEN : 2 * HIDDEN]), _sigmoid(z[:, 2 * HIDDEN : 3 * HIDDEN])
            g = np.tanh(z[:, 3 * HIDDEN :])
            before = (h, c)
            c = np.where(live, f * c + i * g, 0)
            s = np.tanh(c)
            h = np.where(live, o * s, 0)
            out[:, k] = h
            if keep:
                trail.append((k, live, i, f, o, g, s, *before))
        return out, trail

    def label(self, pages: list[np.ndarray]) -> list[np.ndarray]:
        """Probabilities for each block of each page."""
        out: list[np.ndarray] = [np.zeros(0)] * len(pages)
        order = sorted((k for k, p in enumerate(pages) if len(p)), key=lambda k: len(pages[k]))
        for a in range(0, len(order), ROWS):
            some = order[a : a + ROWS]
            x, n = self._pad([pages[k] for k in some])
            both = np.concatenate([self._run(x, n, "f")[0], self._run(x, n, "b")[0]], axis=2)
            y = _sigmoid(both @ self.p["o"] + x @ self.p["s"])
            for row, k in enumerate(some):
                out[k] = y[row, : n[row]]
        return out

    def _step(self, pages: list[np.ndarray], truth: list[np.ndarray]) -> dict[str, np.ndarray]:
        x, n = self._pad(pages)
        b, t, d = x.shape
        y = np.zeros((b, t), np.float32)
        for k, v in enumerate(truth):
            y[k, : len(v)] = v
        live = np.arange(t)[None, :] < n[:, None]
        runs = {side: self._run(x, n, side, keep=True) for side in "fb"}
        both = np.concatenate([runs["f"][0], runs["b"][0]], axis=2)
        e = np.where(live, _sigmoid(both @ self.p["o"] + x @ self.p["s"]) - y, 0) / live.sum()
        grad = {"o": np.einsum("bt,bth->h", e, both), "s": np.einsum("bt,btd->d", e, x)}
        for m, side in enumerate("fb"):
            back = e[:, :, None] * self.p["o"][m * HIDDEN : (m + 1) * HIDDEN]
            u = self.p[f"h{side}"]
            gz = np.zeros((b, t, 4 * HIDDEN), np.float32)
            gu = np.zeros_like(u)
            dh, dc = np.zeros((b, HIDDEN), np.float32), np.zeros((b, HIDDEN), np.float32)
            for k, alive, i, f, o, g, s, h0, c0 in reversed(runs[side][1]):
                dh = np.where(alive, dh + back[:, k], 0)
                dc = np.where(alive, dc + dh * o * (1 - s**2), 0)
                z = np.concatenate([dc * g * i * (1 - i), dc * c0 * f * (1 - f), dh * s * o * (1 - o), dc * i * (1 - g**2)], axis=1)
                gz[:, k] = z
                gu += h0.T @ z
                dh, dc = z @ u.T, dc * f
            grad[f"h{side}"] = gu
            grad[f"x{side}"] = x.reshape(b * t, d).T @ gz.reshape(b * t, -1)
            grad[f"c{side}"] = gz.sum(axis=(0, 1))
        return grad

    def fit(self, pages: list[np.ndarray], truth: list[np.ndarray], seed: int = 4) -> Labeller:
        """Adam over groups of pages of like length."""
        r = np.random.default_rng(seed)
        use = sorted((k for k, p in enumerate(pages) if len(p)), key=lambda k: len(pages[k]))
        groups = [use[a : a + GROUP] for a in range(0, len(use), GROUP)]
        first, second, step = ({k: np.zeros_like(v) for k, v in self.p.items()} for _ in range(3))
        step = 0
        for epoch in range(EPOCHS):
            for g in r.permutation(len(groups)):
                grad = self._step([pages[k] for k in groups[g]], [truth[k] for k in groups[g]])
                step += 1
                rate = RATE * (1 - epoch / EPOCHS) + 0.001
                for k, v in grad.items():
                    first[k] = 0.9 * first[k] + 0.1 * v
                    second[k] = 0.99 * second[k] + 0.01 * v**2
                    self.p[k] = (self.p[k] - rate * (first[k] / (1 - 0.9**step)) / (np.sqrt(second[k] / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        return self


def training(pages: list[str], seed: int = 6) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Every page as it is, and once more with blocks of declared kinds put in at random places."""
    r = np.random.default_rng(seed)
    x, y = [], []
    for page in pages:
        found = blocks(page)
        if not found:
            continue
        x.append(vectors(found))
        y.append(np.array([declared(p) for p, _, _ in found], np.float32))
        mixed = list(found)
        for _ in range(int(r.integers(4, 12))):
            at = int(r.integers(len(mixed) + 1))
            beside = mixed[min(at, len(mixed) - 1)][0]
            base = beside[: int(r.integers(0, len(beside) + 1))]
            _, text, _ = found[int(r.integers(len(found)))]
            tail = ("p",) if r.random() < 0.5 else ("ul", "li") if r.random() < 0.3 else ()
            if r.random() < 0.7:
                word = ASIDE[int(r.integers(len(ASIDE)))]
                path = (*base, *(("div", word), ("section", word), (word,), ("aside", word), ("ul", word))[int(r.integers(5))], *tail)
            else:
                path = (*("html", "body"), *(("article",), ("main",), ("main", "article"), ("article", "div", "content"), ("div", "content"), ("article", "section"))[int(r.integers(6))], *(("p",), ("h2",), ("blockquote", "p"), ("ul", "li"), ("pre",), ("div",))[int(r.integers(6))])
            mixed.insert(at, (path, text, len(text) if "li" in tail else 0))
        x.append(vectors(mixed))
        y.append(np.array([declared(p) for p, _, _ in mixed], np.float32))
    return x, y


def _extract(shared, columns: list[str]):
    def run(batches):
        labeller = shared.value
        for batch in batches:
            text: list[str] = []
            rows = batch.column("_html").to_pylist()
            for a in range(0, len(rows), ROWS * 4):
                found = [blocks(page) for page in rows[a : a + ROWS * 4]]
                marks = labeller.label([vectors(f) for f in found])
                text += ["\n".join(t for (_, t, _), m in zip(f, p, strict=True) if m >= 0.5) for f, p in zip(found, marks, strict=True)]
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in columns), pa.array(text, pa.string()), pa.array([len(t) for t in text], pa.int64())], names=[*columns, "text", "n_chars"])

    return run


def extract(pages: DataFrame, column: str = "html", key: str = "page_id", sample: int = SAMPLE) -> DataFrame:
    """pages without `column`, with text and n_chars (code points) added; columns of those names are replaced.

    Null, empty and textless pages give an empty text. Rows that repeat are extracted each time; null keys are kept.
    No pages, no rows. The labeller is fitted on at most `sample` pages of at most SAMPLE_BYTES each, chosen by a hash of `key`; longer pages are extracted all the same.
    """
    spark = pages.sparkSession
    columns = [c for c in pages.columns if c not in (column, "text", "n_chars", "_html")]
    some = likely(pages.where(F.octet_length(column) <= SAMPLE_BYTES), sample, key).orderBy(F.pmod(F.xxhash64(key), F.lit(1 << 30)), column).select(column).limit(sample)
    rows: pd.DataFrame = some.toPandas()
    labeller = Labeller().fit(*training(rows[column].tolist())) if len(rows) else Labeller()
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pages.schema if f.name in columns) + ", text string, n_chars long"
    narrow = pages.select(*columns, F.col(column).cast("string").alias("_html"))
    return narrow.mapInArrow(_extract(spark.sparkContext.broadcast(labeller), columns), schema)
