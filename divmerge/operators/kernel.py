"""The skip-gram kernel: negative sampling on minibatches, in numpy.

A minibatch is a run of consecutive positions, of sentences in random order, with all their contexts. It sums the gradients of its pairs into the rows they
touch, each row's sum divided by the square root of the number of pairs in it: frequent words would otherwise take many
steps at once. The windows of a run overlap, so a word's context row is read once for all positions around it, and its
gradients are added up before they are added to its row. The pairs of a position share their negatives, which is a fifth of the
work of drawing them apart.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

BLOCK = 32


@dataclass(frozen=True)
class SkipGramConfig:
    dim: int = 32
    window: int = 10
    negatives: int = 5
    rate: float = 0.05
    least_rate: float = 0.001
    epochs: int = 5
    batch_pairs: int = 8192
    noise_power: float = 0.75
    subsample: float | None = None  # keep frequent words with probability sqrt(t / f), where set
    dynamic_window: bool = False
    seed: int = 1


class NoiseTable:
    """Draws word ids with probability proportional to count ** power: the search begins where a table of equal steps says."""

    def __init__(self, counts: np.ndarray, power: float = 0.75) -> None:
        w = np.asarray(counts, np.float64) ** power
        self.cum = np.cumsum(w / w.sum())
        self.cum[-1:] = 1.0
        self.steps = 1 << (2 * len(w)).bit_length()
        self.begin = np.searchsorted(self.cum, np.arange(self.steps) / self.steps, "right").astype(np.int32)

    def draw(self, rng: np.random.Generator, n: int) -> np.ndarray:
        u = rng.random(n)
        at = self.begin[(u * self.steps).astype(np.int64)].astype(np.int64)
        low = np.flatnonzero(self.cum[at] <= u)
        while len(low):
            at[low] += 1
            low = low[self.cum[at[low]] <= u[low]]
        return at


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))


def contexts_of(ids: np.ndarray, sent: np.ndarray, window: int, rng: np.random.Generator | None = None) -> np.ndarray:
    """(positions, 2 * reach) context ids within ``window`` positions of one sentence, -1 where there is none; with ``rng`` each word's window is shrunk at random."""
    n = len(ids)
    reach = rng.integers(1, window + 1, n) if rng is not None else None
    d_max = min(window, max(0, n - 1))
    out = np.full((n, 2 * d_max), -1, np.int32)
    for d in range(1, d_max + 1):
        left = np.flatnonzero(sent[:-d] == sent[d:])
        if not len(left):  # no sentence is longer
            return out[:, : 2 * (d - 1)]
        right = left + d
        l, r = (left, right) if reach is None else (left[reach[left] >= d], right[reach[right] >= d])
        out[l, 2 * d - 2] = ids[l + d]
        out[r, 2 * d - 1] = ids[r - d]
    return out


def windows_of(sent: np.ndarray, window: int, rng: np.random.Generator | None = None) -> np.ndarray:
    """(positions, 2 * reach + 1) 1 where the position ``j - reach`` further on is a context, else 0; ``contexts_of`` as a mask. ``reach`` is less than ``window`` where no sentence is longer."""
    n = len(sent)
    reach = rng.integers(1, window + 1, n) if rng is not None else None
    same = []
    for d in range(1, min(window, max(0, n - 1)) + 1):
        s = sent[:-d] == sent[d:]
        if not s.any():
            break
        same.append(s)
    w = len(same)
    out = np.zeros((n, 2 * w + 1), np.float32)
    for d, s in enumerate(same, 1):
        out[: n - d, w + d] = s if reach is None else s & (reach[: n - d] >= d)
        out[d:, w - d] = s if reach is None else s & (reach[d:] >= d)
    return out


def pairs_of(ids: np.ndarray, sent: np.ndarray, window: int, rng: np.random.Generator | None = None) -> tuple[np.ndarray, np.ndarray]:
    """(word, context) ids within ``window`` positions of one sentence."""
    c = contexts_of(ids, sent, window, rng)
    at, col = np.nonzero(c >= 0)
    return ids[at], c[at, col].astype(ids.dtype)


class _Matrix:
    """Vectors of words, with scratch to add to many rows at once."""

    def __init__(self, vectors: np.ndarray) -> None:
        self.vectors, self.rows = vectors, vectors.view(np.dtype((np.void, vectors.itemsize * vectors.shape[1])))[:, 0]
        self.pairs, self.last = np.zeros(len(vectors), np.float32), np.zeros(len(vectors), np.int32)

    def scatter(self, rows: np.ndarray, before: np.ndarray, grads: np.ndarray, weight: np.ndarray, rate: float) -> None:
        """Add to each row the sum of its gradients over the square root of the pairs in it (``weight`` pairs for each gradient). ``before`` is the rows as they are; both are overwritten.

        Most rows come once and are written back whole; what else belongs to a row that comes again is added to it number by number.
        """
        dim, at = self.vectors.shape[1], np.arange(len(rows), dtype=np.int32)
        np.add.at(self.pairs, rows, weight)
        self.last[rows] = at
        grads *= (np.float32(rate) / np.sqrt(np.maximum(self.pairs.take(rows), 1)))[:, None]
        self.pairs[rows] = 0
        before += grads
        np.put(self.rows, rows, before.view(self.rows.dtype)[:, 0])  # of equal rows the last stays
        again = np.flatnonzero(self.last.take(rows) != at)
        np.add.at(self.vectors.reshape(-1), (rows[again, None] * dim + np.arange(dim)).reshape(-1), grads.take(again, 0).reshape(-1))


def _shuffled(ids: np.ndarray, sent: np.ndarray, rng: np.random.Generator) -> tuple[np.ndarray, np.ndarray]:
    """The sentences in random order, each as it is."""
    begin = np.flatnonzero(np.diff(sent, prepend=-1))
    size = np.diff(begin, append=len(sent))
    order = rng.permutation(len(begin))
    begin, size = begin[order], size[order]
    at = np.arange(len(sent)) + np.repeat(begin - (np.cumsum(size) - size), size)
    return ids[at], sent[at]


class SkipGram:
    """One model: word and context matrices over a fixed vocabulary."""

    def __init__(self, counts: np.ndarray, cfg: SkipGramConfig, seed: int) -> None:
        self.cfg, self.counts = cfg, np.asarray(counts, np.float64)
        self.rng = np.random.default_rng(seed)
        v = len(counts)
        self.words = ((self.rng.random((v, cfg.dim), np.float32) - 0.5) / cfg.dim).astype(np.float32)
        self.contexts = np.zeros((v, cfg.dim), np.float32)
        self.noise = NoiseTable(counts, cfg.noise_power)
        self.seen = np.zeros(v, np.int64)
        self.pairs = 0

    def gradients(self, w: np.ndarray, c: np.ndarray, neg: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """Gradients (to climb) of the objective of positions, for words (b), contexts (b, m) and negatives (b, k), and its sum.

        ``c`` is -1 where a position has no context. A position's pairs share its negatives, each of which weighs as many as
        there are pairs: the word's vector is the same in all, so that is the sum over pairs with the same draws.
        """
        on = c >= 0
        many = on.sum(1).astype(np.float32)
        x, y, z = self.words[w], self.contexts[c], self.contexts[neg]
        pos, no = np.matmul(y, x[:, :, None])[:, :, 0], np.matmul(z, x[:, :, None])[:, :, 0]
        gp = (np.float32(1) - sigmoid(pos)) * on
        gn = -sigmoid(no) * many[:, None]
        gx = np.matmul(gp[:, None, :], y)[:, 0] + np.matmul(gn[:, None, :], z)[:, 0]
        value = float(-(np.logaddexp(0, -pos) * on).sum() - (np.logaddexp(0, no) * many[:, None]).sum())
        return gx, gp[:, :, None] * x[:, None, :], gn[:, :, None] * x[:, None, :], value

    def run_gradients(self, own: np.ndarray, near: np.ndarray, on: np.ndarray, neg: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, float]:
        """The same for a run of consecutive positions: gradients of words (b), of ``near`` (b + 2 * reach, the run with the positions about it) and of negatives (b, k).

        ``on[i, j]`` says that ``near[i + j]`` is a context of position i. A context's gradients come added up over the run.
        """
        gx, g, value = self._gradients(self.words.take(own, 0), self.contexts.take(np.concatenate([near, neg.reshape(-1)]), 0), on)
        return gx, g[: len(near)], g[len(near) :].reshape(*neg.shape, -1), value

    def _gradients(self, own: np.ndarray, other: np.ndarray, on: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """From vectors: those of the run, and of ``near`` and the negatives, one after the other; gradients in the same order.

        The dot products of ``BLOCK`` positions with all positions about them are one matrix product, whose band is read.
        """
        (b, wide), dim = on.shape, own.shape[1]
        pad = wide - 1
        block, many = max(BLOCK, pad), on.sum(1)
        n, near = -(-b // block), b + pad
        x, y = np.zeros((n * block, dim), np.float32), np.zeros((n * block + pad, dim), np.float32)
        x[:b], y[:near], z = own, other[:near], other[near:].reshape(b, -1, dim)
        runs, around = x.reshape(n, block, dim), np.lib.stride_tricks.as_strided(y, (n, block + pad, dim), (block * y.strides[0], *y.strides))
        dots = np.matmul(runs, around.transpose(0, 2, 1))
        band = np.lib.stride_tricks.as_strided(dots, (n, block, wide), (dots.strides[0], dots.strides[1] + dots.strides[2], dots.strides[2]))  # band[., i, j]: positions i and i + j
        pos, no = sigmoid(band.reshape(-1, wide)[:b]), sigmoid(-np.einsum("bkd,bd->bk", z, own))
        gp, gn = np.zeros((n * block, wide), np.float32), (no - 1) * many[:, None]
        np.multiply(1 - pos, on, out=gp[:b])
        dots.fill(0)
        band[:] = gp.reshape(n, block, wide)
        gx, part = np.matmul(dots, around).reshape(-1, dim)[:b], np.matmul(dots.transpose(0, 2, 1), runs)
        gx += np.einsum("bk,bkd->bd", gn, z)
        gy = np.zeros_like(y)
        gy[: n * block].reshape(n, block, dim)[:] = part[:, :block]
        gy[block : n * block].reshape(n - 1, block, dim)[:, :pad] += part[:-1, block:]
        gy[n * block :] += part[-1, block:]
        g = np.empty_like(other)
        g[:near] = gy[:near]
        np.einsum("bk,bd->bkd", gn, own, out=g[near:].reshape(z.shape))
        return gx, g, float((np.log(pos) * on).sum() + (np.log(no) * many[:, None]).sum())

    def train(self, ids: np.ndarray, sent: np.ndarray, progress: float) -> float:
        """One pass over sentences (ids with their sentence numbers); ``progress`` in [0, 1] sets the learning rate. The mean objective of a pair."""
        cfg = self.cfg
        self.seen += np.bincount(ids, minlength=len(self.seen))
        if cfg.subsample:
            f = self.counts[ids] / self.counts.sum()
            keep = self.rng.random(len(ids)) < np.sqrt(cfg.subsample / np.maximum(f, 1e-12))
            ids, sent = ids[keep], sent[keep]
        alone = np.diff(sent, prepend=-1, append=-1) != 0
        alone = alone[:-1] & alone[1:]
        ids, sent = _shuffled(ids[~alone], sent[~alone], self.rng)  # without words that have no context
        on = windows_of(sent, cfg.window, self.rng if cfg.dynamic_window else None)
        reach = on.shape[1] // 2
        if not reach:
            return 0.0
        padded = np.concatenate([np.zeros(reach, ids.dtype), ids, np.zeros(reach, ids.dtype)])
        rate = max(cfg.least_rate, cfg.rate * (1.0 - progress))
        words, contexts = _Matrix(self.words), _Matrix(self.contexts)
        value, step = 0.0, max(1, cfg.batch_pairs // (2 * reach))
        noise = self.noise.draw(self.rng, len(ids) * cfg.negatives).reshape(len(ids), -1)
        for lo in range(0, len(ids), step):
            own, near, here = ids[lo : lo + step], padded[lo : lo + step + 2 * reach], on[lo : lo + step]
            neg = noise[lo : lo + step]
            other = np.concatenate([near, neg.reshape(-1)])
            x, y = words.vectors.take(own, 0), contexts.vectors.take(other, 0)
            gx, gy, v = self._gradients(x, y, here)
            value += v
            many = here.sum(1)
            times = np.zeros(len(near), many.dtype)
            for j in range(2 * reach + 1):
                times[j : j + len(own)] += here[:, j]
            words.scatter(own, x, gx, many, rate)
            contexts.scatter(other, y, gy, np.concatenate([times, np.repeat(many, cfg.negatives)]), rate)
        pairs = int(on.sum())
        self.pairs += pairs
        return value / pairs
