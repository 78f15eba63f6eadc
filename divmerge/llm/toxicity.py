"""Toxicity by a factorization machine over hashed terms.

A term is a run of letters, digits and non-ASCII bytes in lower case, or the first ``STEMS`` bytes of a longer one; a text is the set of its terms, hashed into
``BUCKETS``. The score is w0 + sum w_i + the pairwise part, half of sum_f ((sum v_if)^2 - sum v_if^2): a pair of terms
(an insult beside the mention of a group) can raise it though neither term does, which additive weights cannot express.

The machine is fitted here on at most ``MAX_LABELLED`` labelled rows (those least by a seeded hash of the id); buckets in
fewer than ``LEAST_DF`` of these texts carry nothing; of the others those are kept whose information on the label is more
than chance gives the best of so many, ``MAX_TERMS`` at most.
A fifth of the sample is held back to turn raw scores into probabilities and to put the best threshold at ``THRESHOLD``.

Defined results: null and empty texts have no terms and get the score of the bias; null labels train nothing; without labels of both
kinds every score is 0; a term counts once in a text, however often it stands there; extra columns do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .quality import sample_labels
from .textnum import Chunk, chunks, prefix_hash, span_hash, words

BUCKETS = 1 << 20
FACTORS = 8
STEMS = (5, 7)
MAX_LABELLED, LEAST_DF, MAX_TERMS = 20_000, 3, 8192
THRESHOLD = 0.3

_SEPARATOR = np.ones(256, bool)
_SEPARATOR[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = False
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


def terms(c: Chunk) -> tuple[np.ndarray, np.ndarray]:
    """(row, bucket) of each term of a chunk, with repeats."""
    data = _LOWER[c.data]
    if len(data):  # capitals of the Latin-1 block, in UTF-8
        two = np.flatnonzero(data[:-1] == 0xC3) + 1
        capital = two[(data[two] >= 0x80) & (data[two] <= 0x9E) & (data[two] != 0x97)]
        data[capital] += 0x20
    prefix = prefix_hash(data)
    w = words(Chunk(c.lo, c.hi, data, c.offs), prefix=prefix, separators=_SEPARATOR)
    doc, found = [w.doc], [w.hash]
    for size in STEMS:
        long = np.flatnonzero(w.end - w.start > size)
        doc.append(w.doc[long])
        found.append(span_hash(prefix, w.start[long], w.start[long] + size) * np.uint64(2 * size + 1))
    return np.concatenate(doc), (np.concatenate(found) >> np.uint64(44)).astype(np.int64)


@dataclass
class FactorizationMachine:
    """``row[bucket]`` is the row of a bucket in ``w`` and ``v``, or -1. Scores are ``sigmoid(scale * raw + shift)``."""

    row: np.ndarray
    bias: float
    w: np.ndarray
    v: np.ndarray
    scale: float = 1.0
    shift: float = 0.0
    empty: bool = False

    def raw(self, doc: np.ndarray, term: np.ndarray, n: int) -> np.ndarray:
        """Raw scores of n texts from their distinct (text, term row) entries, ordered by text."""
        out = np.full(n, self.bias)
        if len(doc):
            at = np.flatnonzero(np.diff(doc, prepend=-1))
            v = self.v[term]
            s, q = np.add.reduceat(v, at, 0), np.add.reduceat(v * v, at, 0)
            out[doc[at]] += np.add.reduceat(self.w[term], at) + 0.5 * (s * s - q).sum(1)
        return out

    def score(self, c: Chunk) -> np.ndarray:
        if self.empty:
            return np.zeros(c.n)
        doc, bucket = terms(c)
        term = self.row[bucket]
        on = term >= 0
        key = np.unique(doc[on] * len(self.w) + term[on])
        raw = self.raw(key // len(self.w), key % len(self.w), c.n)
        return 1.0 / (1.0 + np.exp(-np.clip(self.scale * raw + self.shift, -60, 60)))


def _information(y: np.ndarray, doc: np.ndarray, term: np.ndarray, k: int) -> np.ndarray:
    """G statistic of each term against the label."""
    n, pos = len(y), y.sum()
    a = np.bincount(term, weights=y[doc], minlength=k)
    df = np.bincount(term, minlength=k).astype(float)
    g = np.zeros(k)
    for seen, total, share in ((a, df, pos), (df - a, df, n - pos), (pos - a, n - df, pos), (n - pos - df + a, n - df, n - pos)):
        expect = total * share / n
        g += np.where(seen > 0, seen * np.log(np.maximum(seen, 1e-9) / np.maximum(expect, 1e-9)), 0)
    return g


def fit(y: np.ndarray, doc: np.ndarray, term: np.ndarray, k: int, factors: int = FACTORS, epochs: int = 15, rate: float = 0.1, l2: float = 1e-4, batch: int = 256, seed: int = 5) -> tuple[float, np.ndarray, np.ndarray]:
    """Adagrad on the logistic loss; entries (doc, term) are distinct and ordered by doc."""
    rng = np.random.default_rng(seed)
    share = float(np.clip(y.mean(), 1e-3, 1 - 1e-3))
    bias, w, v = float(np.log(share / (1 - share))), np.zeros(k), rng.normal(0, 0.01, (k, factors))
    gb, gw, gv = 1e-8, np.full(k, 1e-8), np.full((k, factors), 1e-8)
    begin = np.searchsorted(doc, np.arange(len(y) + 1))
    for _ in range(epochs):
        order = rng.permutation(len(y))
        for lo in range(0, len(y), batch):
            pick = order[lo : lo + batch]
            size = begin[pick + 1] - begin[pick]
            d = np.repeat(np.arange(len(pick)), size)
            t = term[np.arange(size.sum()) + np.repeat(begin[pick] - (np.cumsum(size) - size), size)]
            vt = v[t]
            s = np.zeros((len(pick), factors))
            at = np.flatnonzero(np.diff(d, prepend=-1))
            raw = np.full(len(pick), bias)
            if len(at):
                s[d[at]] = np.add.reduceat(vt, at, 0)
                q = np.add.reduceat(vt * vt, at, 0)
                raw[d[at]] += np.add.reduceat(w[t], at) + 0.5 * (s[d[at]] ** 2 - q).sum(1)
            err = (1 / (1 + np.exp(-np.clip(raw, -30, 30))) - y[pick]) / len(pick)
            gb += err.sum() ** 2
            bias -= rate * err.sum() / np.sqrt(gb)
            if not len(t):
                continue
            o = np.argsort(t, kind="stable")
            a = np.flatnonzero(np.diff(t[o], prepend=-1))
            u = t[o][a]
            dw = np.add.reduceat(err[d[o]], a) + l2 * w[u]
            dv = np.add.reduceat(err[d[o]][:, None] * (s[d[o]] - vt[o]), a, 0) + l2 * v[u]
            gw[u] += dw**2
            gv[u] += dv**2
            w[u] -= rate * dw / np.sqrt(gw[u])
            v[u] -= 0.3 * rate * dv / np.sqrt(gv[u])
    return bias, w, v


def _calibrated(raw: np.ndarray, y: np.ndarray, threshold: float) -> tuple[float, float]:
    """Scale by a logistic fit; shift so that the cut with the best F1 (the middle of the widest such gap) scores ``threshold``."""
    order = np.argsort(-raw, kind="stable")
    r, hit = raw[order], y[order]
    tp = np.cumsum(hit)
    f1 = 2 * tp / (np.arange(1, len(r) + 1) + y.sum())
    i = int(np.argmax(f1))
    cut = (r[i] + r[i + 1]) / 2 if i + 1 < len(r) else r[i] - 1
    scale = 1.0
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(scale * (raw - cut), -30, 30)))
        grad, hess = ((p - y) * (raw - cut)).sum() + 0.1 * (scale - 1), (p * (1 - p) * (raw - cut) ** 2).sum() + 0.1
        scale = float(np.clip(scale - np.clip(grad / hess, -0.5, 0.5), 0.2, 5.0))
    return scale, float(np.log(threshold / (1 - threshold)) - scale * cut)


def _entries(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for c in chunks(b.column("text")):
            doc, bucket = terms(c)
            key = np.unique(doc * BUCKETS + bucket)
            at = np.searchsorted(key // BUCKETS, np.arange(c.n + 1))
            own = (key % BUCKETS).astype(np.int32)
            yield pa.RecordBatch.from_arrays([b.column("label").slice(c.lo, c.n), pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(own))], names=["label", "terms"])


def train(docs: DataFrame, labels: DataFrame, label: str = "toxic", keep=None, max_labelled: int = MAX_LABELLED, threshold: float = THRESHOLD) -> FactorizationMachine:
    """Fit on at most ``max_labelled`` of the labels for which the column ``keep`` holds."""
    ship(docs.sparkSession)
    chosen = sample_labels(labels, label, max_labelled, keep)  # bounded by its limit, so it may be sent to all
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(chosen), "doc_id").select("label", "text")
    got = rows.mapInArrow(_entries, "label int, terms array<int>").toArrow()
    y = got["label"].to_numpy().astype(float)
    lists = got["terms"].combine_chunks()
    size, bucket = np.diff(lists.offsets.to_numpy()), lists.flatten().to_numpy().astype(np.int64)
    doc = np.repeat(np.arange(len(y)), size)
    if len(y) < 20 or not 0 < y.sum() < len(y):
        return FactorizationMachine(np.full(BUCKETS, -1), 0.0, np.zeros(1), np.zeros((1, FACTORS)), empty=True)
    # an order of the texts that does not depend on the order they came in
    mark = np.bincount(doc, weights=bucket * 1.0, minlength=len(y)) + size
    rank = np.empty(len(y), np.int64)
    rank[np.lexsort((mark, y))] = np.arange(len(y))
    y = y[np.argsort(rank)]
    doc = rank[doc]
    held = np.arange(len(y)) % 5 == 0
    df = np.bincount(bucket, minlength=BUCKETS)
    kept = np.flatnonzero(df >= LEAST_DF)
    row = np.full(BUCKETS, -1)
    row[kept] = np.arange(len(kept))
    on = row[bucket] >= 0
    train_on = on & ~held[doc]
    g = _information(np.where(held, 0, y), doc[train_on], row[bucket[train_on]], len(kept)) if len(kept) else np.zeros(0)
    strong = np.argsort(-g, kind="stable")[:MAX_TERMS]
    best = np.sort(kept[strong[g[strong] >= np.log(max(2, len(kept)))]])  # what chance alone gives the best of so many terms
    row[:] = -1
    row[best] = np.arange(len(best))
    key = np.unique(doc[row[bucket] >= 0] * max(1, len(best)) + row[bucket[row[bucket] >= 0]])
    doc, term = key // max(1, len(best)), key % max(1, len(best))
    place = np.cumsum(~held) - 1
    own = ~held[doc]
    bias, w, v = fit(y[~held], place[doc[own]], term[own], max(1, len(best)))
    fm = FactorizationMachine(row, bias, w, v)
    fm.scale, fm.shift = _calibrated(fm.raw(doc, term, len(y))[held], y[held], threshold)
    return fm


def _score(model: FactorizationMachine, threshold: float):
    schema = pa.schema([("doc_id", pa.int64()), ("score", pa.float64()), ("predicted", pa.int32())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in chunks(b.column("text")):
                s = model.score(c)
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(c.lo, c.n), pa.array(s), pa.array((s >= threshold).astype(np.int32))], schema=schema)

    return run


def score(docs: DataFrame, model: FactorizationMachine, threshold: float = THRESHOLD) -> DataFrame:
    """``docs(doc_id, text)`` to (doc_id, score, predicted)."""
    ship(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_score(model, threshold), "doc_id long, score double, predicted int")
