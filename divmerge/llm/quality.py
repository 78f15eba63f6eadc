"""Quality rules: statistics of whole texts, and boosted trees over them as flat node arrays with monotonic constraints.

The statistics come from numpy over all words of a batch. The trees are grown here, on histograms, with the logistic
loss: each split of a constrained feature must move its two values the right way, and children inherit the bounds of
their parent's middle, so the score is monotonic in that feature over the whole model. Scoring walks all rows down one
level at a time through arrays (feature, threshold, left, right, value).

The model is fitted on at most ``MAX_LABELLED`` labelled rows (those least by a seeded hash of their id); that is the
only bound. Statistics and verdicts cover every row and every whole text.

Defined results: null and empty texts have no words and fail the base rule; labels that are null are left out; with no
labels of both kinds every text scores 1 and the base rule decides alone; extra columns do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .textnum import SPACE, Chunk, chunks, covered, prefix_hash, span_hash, trim, windows, words

MAX_LABELLED = 8000
REPEAT_WINDOW = 8
#: A text is rejected where the model gives good quality less than this.
LEAST_SCORE = 0.35
BASE = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
FEATURES = ("log_words", "mean_word", "symbol_rate", "dup_line_rate", "repeat_rate", "upper_rate", "digit_rate", "mark_rate", "bar_rate", "shout_rate", "distinct_rate", "line_words", "short_rate")
#: More of these may only lower the score; fixed choice.
MONOTONE = {"symbol_rate": -1, "dup_line_rate": -1, "repeat_rate": -1, "bar_rate": -1, "shout_rate": -1}


def _class(chars: bytes) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars)] = True
    return out


_SYMBOL = _class(b"#*$%&|<>")
_UPPER, _DIGIT, _MARK = _class(bytes(range(65, 91))), _class(bytes(range(48, 58))), _class(b".,;:!?")
_BAR, _SHOUT = _class(b"|"), _class(b"!")


def _per_row(mask: np.ndarray, offs: np.ndarray) -> np.ndarray:
    total = np.zeros(len(mask) + 1, np.int64)
    np.cumsum(mask, out=total[1:])
    return np.diff(total[offs])


def statistics(c: Chunk) -> tuple[np.ndarray, np.ndarray]:
    """(rows, 5) of BASE and (rows, 13) of FEATURES."""
    prefix = prefix_hash(c.data)
    w = words(c, prefix=prefix)
    n_words, doc, n = w.count, w.doc, c.n
    head = (c.data & 0xC0) != 0x80  # first bytes of code points
    char_at = np.zeros(len(c.data) + 1, np.int64)
    np.cumsum(head & ~SPACE[c.data], out=char_at[1:])
    word_chars = np.diff(char_at[c.offs])
    rows = lambda table: _per_row(table[c.data], c.offs)
    symbols = rows(_SYMBOL)

    # Lines with a word, equal to an earlier line of the row.
    cut = np.flatnonzero(c.data == 0x0A)
    begin = np.unique(np.concatenate([c.offs[:-1], cut + 1]))
    begin = begin[begin < len(c.data)]
    begin = begin[c.data[begin] != 0x0A]
    ends = np.union1d(cut, c.offs[1:])
    until = ends[np.searchsorted(ends, begin, "right")] if len(begin) else begin
    full = (np.searchsorted(w.start, until) - np.searchsorted(w.start, begin)) > 0
    begin, until = begin[full], until[full]
    line_doc = np.searchsorted(c.offs, begin, "right") - 1
    lh = span_hash(prefix, begin, until)
    order = np.lexsort((lh, line_doc))
    again = (lh[order][1:] == lh[order][:-1]) & (line_doc[order][1:] == line_doc[order][:-1])
    dup_lines = np.bincount(line_doc[order][1:][again], minlength=n)
    lines = np.bincount(line_doc, minlength=n)

    # Words inside windows that the row holds twice or more.
    h, fits = windows(w, REPEAT_WINDOW)
    at = np.flatnonzero(fits)
    order = np.lexsort((h[at], doc[at]))
    hs, ds = h[at][order], doc[at][order]
    same = np.zeros(len(hs) + 1, bool)
    same[1:-1] = (hs[1:] == hs[:-1]) & (ds[1:] == ds[:-1]) if len(hs) else False
    twice = at[order[same[1:] | same[:-1]]]
    repeat = np.bincount(doc[covered(len(doc), twice, REPEAT_WINDOW)], minlength=n)

    order = np.lexsort((w.hash, doc))
    ws, wd = w.hash[order], doc[order]
    new = np.ones(len(ws), bool)
    new[1:] = (ws[1:] != ws[:-1]) | (wd[1:] != wd[:-1])
    distinct = np.bincount(wd[new], minlength=n)
    short = np.bincount(doc[(w.end - w.start) <= 3], minlength=n)

    base = np.stack([n_words, word_chars, symbols, dup_lines, repeat], 1)
    nw, nc, nl = np.maximum(n_words, 1), np.maximum(word_chars, 1), np.maximum(lines, 1)
    feats = np.stack([
        np.log1p(n_words), word_chars / nw, symbols / nc, dup_lines / nl, repeat / nw, rows(_UPPER) / nc, rows(_DIGIT) / nc,
        rows(_MARK) / nw, rows(_BAR) / nw, rows(_SHOUT) / nw, distinct / np.sqrt(nw), n_words / nl, short / nw,
    ], 1)
    return base, feats


@dataclass
class Trees:
    """All trees in one set of arrays; ``roots`` are their first nodes. A leaf points to itself."""

    roots: np.ndarray
    feature: np.ndarray
    threshold: np.ndarray
    left: np.ndarray
    right: np.ndarray
    value: np.ndarray
    base: float
    depth: int

    def score(self, x: np.ndarray) -> np.ndarray:
        """Probability of good quality for each row."""
        total = np.full(len(x), self.base)
        row = np.arange(len(x))
        for root in self.roots:
            at = np.full(len(x), root)
            for _ in range(self.depth):
                go = x[row, self.feature[at]] <= self.threshold[at]
                at = np.where(go, self.left[at], self.right[at])
            total += self.value[at]
        return 1.0 / (1.0 + np.exp(-total))


def fit_trees(x: np.ndarray, y: np.ndarray, monotone: np.ndarray, n_trees: int = 60, depth: int = 4, rate: float = 0.15, bins: int = 64, l2: float = 1.0, least_rows: int = 10) -> Trees:
    """Boost ``n_trees`` trees of at most ``depth`` levels on the logistic loss."""
    n, f = x.shape
    edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1], method="lower")) if n else np.zeros(0) for j in range(f)]
    code = np.stack([np.searchsorted(edges[j], x[:, j], "left") for j in range(f)], 1)  # bin b: x <= edges[b]
    share = np.clip(y.mean() if n else 1.0, 1e-3, 1 - 1e-3)
    base = float(np.log(share / (1 - share)))
    nodes: dict[str, list] = {k: [] for k in ("feature", "threshold", "left", "right", "value")}
    roots, raw = [], np.full(n, base)

    def node(value: float) -> int:
        i = len(nodes["value"])
        for k, v in (("feature", 0), ("threshold", np.inf), ("left", i), ("right", i), ("value", value)):
            nodes[k].append(v)
        return i

    def grow(rows: np.ndarray, g: np.ndarray, h: np.ndarray, level: int, low: float, high: float) -> int:
        value = float(np.clip(-g[rows].sum() / (h[rows].sum() + l2), low, high))
        me = node(value * rate)
        if level == depth or len(rows) < 2 * least_rows:
            raw[rows] += value * rate
            return me
        best = (1e-6, -1, 0, 0.0)
        gs, hs = g[rows].sum(), h[rows].sum()
        for j in range(f):
            k = len(edges[j]) + 1
            if k < 2:
                continue
            cj = code[rows, j]
            gl, hl, nl = (np.cumsum(np.bincount(cj, weights=a, minlength=k))[:-1] for a in (g[rows], h[rows], np.ones(len(rows))))
            vl, vr = np.clip(-gl / (hl + l2), low, high), np.clip(-(gs - gl) / (hs - hl + l2), low, high)
            gain = -(gl * vl + (hl + l2) * vl**2 / 2 + (gs - gl) * vr + (hs - hl + l2) * vr**2 / 2) + (gs * value + (hs + l2) * value**2 / 2)
            ok = (nl >= least_rows) & (len(rows) - nl >= least_rows) & ((vr - vl) * monotone[j] >= 0)
            gain = np.where(ok, gain, -np.inf)
            b = int(np.argmax(gain))
            if gain[b] > best[0]:
                best = (float(gain[b]), j, b, float(vl[b] + vr[b]) / 2)
        _, j, b, mid = best
        if j < 0:
            raw[rows] += value * rate
            return me
        go = code[rows, j] <= b
        bounds = [(low, high), (low, high)]
        if monotone[j] > 0:
            bounds = [(low, mid), (mid, high)]
        elif monotone[j] < 0:
            bounds = [(mid, high), (low, mid)]
        left = grow(rows[go], g, h, level + 1, *bounds[0])
        right = grow(rows[~go], g, h, level + 1, *bounds[1])
        nodes["feature"][me], nodes["threshold"][me], nodes["left"][me], nodes["right"][me] = j, float(edges[j][b]), left, right
        return me

    for _ in range(n_trees if n and 0 < y.sum() < n else 0):
        p = 1 / (1 + np.exp(-raw))
        roots.append(grow(np.arange(n), p - y, p * (1 - p), 0, -np.inf, np.inf))
    if not roots:
        node(0.0)
        base = 50.0
    types = {"feature": np.int64, "threshold": float, "left": np.int64, "right": np.int64, "value": float}
    return Trees(np.array(roots, np.int64), *(np.array(nodes[k], t) for k, t in types.items()), base, depth)


def bounded_sample(rows: DataFrame, key: str, limit: int, seed: int = 11) -> DataFrame:
    """At most ``limit`` rows, those least by a seeded hash of ``key``.

    A first cut by the hash leaves about the limit over all tasks together, so no task sends a limit of its own.
    """
    n = rows.count()
    h = F.xxhash64(F.lit(seed), F.col(key))
    if n > 2 * limit:
        share = (1.2 * limit + 200) / n
        rows = rows.where(h < F.lit(int(-(1 << 63) + share * (1 << 64))))
    return rows.orderBy(h, key).limit(limit)


def sample_labels(labels: DataFrame, label: str, limit: int, keep=None) -> DataFrame:
    """At most ``limit`` labelled ids, those least by a seeded hash: (doc_id, label)."""
    rows = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull())
    if keep is not None:
        rows = rows.where(keep)
    rows = rows.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(label).cast("int").alias("label"))
    return bounded_sample(rows, "doc_id", limit)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for c in chunks(b.column("text")):
            _, x = statistics(c)
            yield pa.RecordBatch.from_arrays([b.column("label").slice(c.lo, c.n), pa.array(list(x), pa.list_(pa.float64()))], names=["label", "x"])


def train(docs: DataFrame, labels: DataFrame, label: str = "quality", max_labelled: int = MAX_LABELLED) -> Trees:
    """Fit the trees on the statistics of at most ``max_labelled`` labelled texts."""
    ship(docs.sparkSession)
    chosen = sample_labels(labels, label, max_labelled)  # bounded by its limit, so it may be sent to all
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(chosen), "doc_id").select("label", "text")
    got = rows.mapInArrow(_features, "label int, x array<double>").toPandas()
    x = np.array(got["x"].tolist(), float).reshape(len(got), len(FEATURES))
    y = got["label"].to_numpy(float)
    order = np.lexsort((*x.T, y))  # whatever order the rows came in
    return fit_trees(x[order], y[order], np.array([MONOTONE.get(k, 0) for k in FEATURES]))


def base_failed(base: np.ndarray) -> np.ndarray:
    """Fewer than 20 words, or more than 30 % of them in repeated windows."""
    return (base[:, 0] < 20) | (100 * base[:, 4] > 30 * base[:, 0])


def _judge(model: Trees, least: float):
    schema = pa.schema([("doc_id", pa.int64()), *((k, pa.int64()) for k in BASE), ("base_failed", pa.bool_()), ("kept", pa.bool_()), ("score", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in chunks(b.column("text")):
                base, x = statistics(c)
                failed, score = base_failed(base), model.score(x)
                yield pa.RecordBatch.from_arrays([
                    b.column("doc_id").slice(c.lo, c.n), *(pa.array(base[:, k].astype(np.int64)) for k in range(len(BASE))),
                    pa.array(failed), pa.array(~failed & (score >= least)), pa.array(score),
                ], schema=schema)

    return run


def judge(docs: DataFrame, model: Trees, least: float = LEAST_SCORE) -> DataFrame:
    """(doc_id, base statistics, base_failed, kept, score) of every text."""
    ship(docs.sparkSession)
    schema = "doc_id long, " + ", ".join(f"{k} long" for k in BASE) + ", base_failed boolean, kept boolean, score double"
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_judge(model, least), schema)


def keep(docs: DataFrame, model: Trees, least: float = LEAST_SCORE) -> DataFrame:
    """The rows of ``docs`` that :func:`judge` keeps, with all their columns."""
    ship(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in chunks(b.column("text")):
                base, x = statistics(c)
                good = ~base_failed(base) & (model.score(x) >= least)
                yield b.slice(c.lo, c.n).filter(pa.array(good))
        trim()

    return docs.mapInArrow(run, docs.schema)
