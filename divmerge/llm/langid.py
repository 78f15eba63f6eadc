"""Language identification by interpolated Kneser-Ney character models in sorted hash arrays.

Words (white-space runs) are lower-cased and stripped to their letters; a word is scored between boundary marks, so the
evidence of a text is the sum over its words and a word is scored once for each batch. For each language the model of
order ``ORDER`` interpolates absolute discounting downwards: the highest order uses counts, lower orders use the
number of distinct letters seen before the n-gram, the lowest order is uniform over the alphabet. Each order is a
sorted array of 64-bit hashes with one row of log probabilities (and of log back-off weights, for contexts) for all languages.

Counts cover every training text: tasks count n-grams of their distinct words, Spark adds them up and writes all of them.
A language's model needs no other language's counts but the size of the common alphabet, so languages are taken in groups
of about ``MAX_NGRAMS`` n-grams: one group's table is on the driver and in a worker at a time, and each group passes over
the texts with a running winner. No n-gram and no language is left out; a language larger than that is a group of its own.

The language with the lowest cross-entropy for each letter wins. The score is its share under a softmax of the negative cross-entropies,
with a temperature fitted on all training texts so that scores are calibrated; texts under ``reject``
are flagged in ``rejected`` (the label stays, for users who want it).

Defined results: null texts and texts without a letter are ``und`` with score 0; rows without a label train nothing; with no labels at all every
text is ``und``; ties go to the language first in the alphabet; extra columns do not matter.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import discard, materialize, ship
from .textnum import WORD_CHUNK_BYTES, chunks, mix64, words

ORDER = 4
DISCOUNT = 0.75
MAX_NGRAMS = 3_000_000
MAX_CELLS = 4 * MAX_NGRAMS  # n-grams times languages of a group; the tables are dense
TEMPERATURES = np.geomspace(0.02, 2.0, 40)
EDGE = 0x20  # boundary mark, never a letter
_G = np.uint64(0x9E3779B97F4A7C15)

_letters: np.ndarray | None = None


def letter_table() -> np.ndarray:
    global _letters
    if _letters is None:
        _letters = np.array([chr(i).isalpha() for i in range(0x110000)])
    return _letters


def letters_of(found: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the letters of each word in lower case between boundary marks, all in one array, and each word's number of letters."""
    flat = np.frombuffer("\n".join(found).lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    cut = flat == 10
    word = np.cumsum(cut)
    keep = letter_table()[flat] & ~cut
    size = np.bincount(word[keep], minlength=len(found))
    # an edge, the letters, an edge
    out = np.full(len(found) * 2 + int(keep.sum()), EDGE, np.uint32)
    at = np.arange(int(keep.sum())) + 2 * word[keep] + 1
    out[at] = flat[keep]
    return out, size


def ngrams(points: np.ndarray, size: np.ndarray, order: int) -> tuple[np.ndarray, np.ndarray]:
    """For each predicted position (letters and the closing edge) the hash of its longest n-gram of each length 1..order.

    Returns (order, positions) of hashes, 0 where the word does not reach back so far, and the word of each position.
    """
    length = size + 2
    word = np.repeat(np.arange(len(size)), length)
    start = np.repeat(np.cumsum(length) - length, length)
    pos = np.arange(len(points)) - start
    at = np.flatnonzero(pos > 0)
    out = np.zeros((order, len(at)), np.uint64)
    h = np.zeros(len(at), np.uint64)
    p64 = points.astype(np.uint64)
    for n in range(1, order + 1):  # letters are added from the right
        ok = pos[at] >= n - 1
        back = at - (n - 1)
        h = mix64(h + (p64[np.maximum(back, 0)] + np.uint64(n << 32)) * _G)
        out[n - 1] = np.where(ok, h, 0)
    return out, word[at]


def _uniques(c, w) -> tuple[list[str], np.ndarray]:
    u, first, inverse = np.unique(w.hash, return_index=True, return_inverse=True)
    data = c.data.tobytes()
    return [data[a:b].decode("utf-8", "replace") for a, b in zip(w.start[first].tolist(), w.end[first].tolist())], inverse


def _count(order: int):
    schema = pa.schema([("lang", pa.string()), ("n", pa.int32()), ("gram", pa.string()), ("k", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # for each length: hashes, n-grams, and counts (languages x n-grams)
        none = [(np.zeros(0, np.uint64), np.zeros((0, n), np.uint32), np.zeros((0, 0))) for n in range(1, order + 1)]
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = list(none)
        known: list[str] = []

        def add(n: int, h: np.ndarray, grams: np.ndarray, k: np.ndarray) -> None:
            h0, g0, k0 = held[n - 1]
            k0 = np.pad(k0, ((0, len(known) - k0.shape[0]), (0, 0))) if k0.size else np.zeros((len(known), len(h0)))
            u, first, inverse = np.unique(np.concatenate([h0, h]), return_index=True, return_inverse=True)
            both = np.concatenate([k0, k], 1)
            held[n - 1] = u, np.concatenate([g0, grams])[first], np.stack([np.bincount(inverse, weights=row, minlength=len(u)) for row in both])

        def told() -> Iterator[pa.RecordBatch]:
            for n, (_, g, k) in enumerate(held, 1):
                text = np.ascontiguousarray(g).tobytes().decode("utf-32-le", "surrogatepass")
                grams = np.array([text[i : i + n] for i in range(0, len(text), n)], object)
                for name, row in zip(known, k):
                    on = np.flatnonzero(row > 0)
                    for lo in range(0, len(on), 50_000):
                        part = on[lo : lo + 50_000]
                        yield pa.RecordBatch.from_arrays([pa.array([name] * len(part)), pa.array([n] * len(part), pa.int32()), pa.array(grams[part], pa.string()), pa.array(row[part].astype(np.int64))], schema=schema)

        for b in batches:
            langs = b.column("lang").to_pylist()
            for c in chunks(b.column("text"), WORD_CHUNK_BYTES):
                w = words(c)
                found, inverse = _uniques(c, w)
                if not found:
                    continue
                points, size = letters_of(found)
                known += sorted(set(langs[c.lo : c.hi]) - set(known))
                of = np.array([known.index(x) for x in langs[c.lo : c.hi]])
                weight = np.bincount(of[w.doc] * len(found) + inverse, minlength=len(known) * len(found)).reshape(len(known), -1)
                length = size + 2
                pos = np.arange(len(points)) - np.repeat(np.cumsum(length) - length, length)
                at = np.flatnonzero(pos > 0)
                hashes, word = ngrams(points, size, order)
                for n in range(1, order + 1):
                    on = np.flatnonzero((hashes[n - 1] != 0) & (size[word] > 0))
                    u, first, back = np.unique(hashes[n - 1][on], return_index=True, return_inverse=True)
                    begin = at[on[first]] - (n - 1)
                    k = np.stack([np.bincount(back, weights=row[word[on]], minlength=len(u)) for row in weight])
                    add(n, u, points[begin[:, None] + np.arange(n)], k)
                if sum(k.size for _, _, k in held) > MAX_CELLS:  # sums of a part of the texts; Spark adds them up
                    yield from told()
                    held[:], known = none, []
        yield from told()

    return run


@dataclass
class LanguageModels:
    """Sorted hashes of each order, and a column of log values for each language."""

    languages: list[str]
    hashes: list[np.ndarray]
    logp: list[np.ndarray]
    backoff: list[np.ndarray]  # of contexts, under the same hashes
    floor: np.ndarray
    temperature: float = 1.0
    reject: float = 0.5

    def position_scores(self, found: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(positions, languages) of log probabilities of each letter and closing edge, the word of each position, and the letters of each word."""
        points, size = letters_of(found)
        order = len(self.hashes)
        h, word = ngrams(points, size, order)
        total = np.zeros((h.shape[1], len(self.languages)), np.float32)
        todo = np.arange(h.shape[1])
        # context of a position = n-grams that end at the position before it
        prev = np.full(h.shape[1], -1)
        same = word[1:] == word[:-1]
        prev[1:][same] = np.arange(h.shape[1] - 1)[same]
        edge = np.array([EDGE], np.uint64)
        h_edge = mix64((edge + np.uint64(1 << 32)) * _G)[0]
        for n in range(order, 0, -1):
            if not len(todo):
                break
            x = h[n - 1][todo]
            at = np.searchsorted(self.hashes[n - 1], x)
            at = np.minimum(at, max(0, len(self.hashes[n - 1]) - 1))
            hit = (x != 0) & (self.hashes[n - 1][at] == x) if len(self.hashes[n - 1]) else np.zeros(len(x), bool)
            total[todo[hit]] += self.logp[n - 1][at[hit]]
            miss = todo[~hit]
            reach = h[n - 1][miss] != 0
            if n > 1 and reach.any():  # weight of the context that is left, where it is known
                m = miss[reach]
                c = np.where(prev[m] >= 0, h[n - 2][np.maximum(prev[m], 0)], h_edge if n == 2 else np.uint64(0))
                if len(self.hashes[n - 2]):
                    at = np.minimum(np.searchsorted(self.hashes[n - 2], c), len(self.hashes[n - 2]) - 1)
                    known = (self.hashes[n - 2][at] == c) & (c != 0)
                    total[m[known]] += self.backoff[n - 2][at[known]]
            todo = miss
        total[todo] += self.floor
        return total, word, size

    def word_scores(self, found: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(words, languages) of log probabilities, and the letters of each word."""
        total, word, size = self.position_scores(found)
        out = np.zeros((len(found), len(self.languages)))
        for j in range(len(self.languages)):
            out[:, j] = np.bincount(word, weights=total[:, j], minlength=len(found))
        out[size == 0] = 0
        return out, size

    def text_scores(self, c) -> tuple[np.ndarray, np.ndarray]:
        """(rows, languages) of mean log probability a letter, and the letters of each row."""
        w = words(c)
        found, inverse = _uniques(c, w)
        if not found:
            return np.zeros((c.n, len(self.languages))), np.zeros(c.n)
        s, size = self.word_scores(found)
        letters = np.bincount(w.doc, weights=size[inverse], minlength=c.n)
        out = np.stack([np.bincount(w.doc, weights=s[inverse, j], minlength=c.n) for j in range(len(self.languages))], 1)
        return out / np.maximum(letters, 1)[:, None], letters

    def decide(self, mean: np.ndarray, letters: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Winner (-1: undetermined) and its score."""
        if not self.languages:
            return np.full(len(letters), -1), np.zeros(len(letters))
        return _share(mean, letters, self.temperature)


def kneser_ney(langs: np.ndarray, n: np.ndarray, gram: np.ndarray, k: np.ndarray, languages: list[str], order: int, discount: float, alphabet: int = 0) -> LanguageModels:
    """Build the arrays from counts (one entry for each language, length and n-gram); ``alphabet`` is the number of letters where other languages have more."""
    L = len(languages)
    col = {x: i for i, x in enumerate(languages)}
    tables: list[dict[str, int]] = []
    counts: list[np.ndarray] = []
    for m in range(1, order + 1):
        on = n == m
        names = sorted(set(gram[on]))
        row = {g: i for i, g in enumerate(names)}
        t = np.zeros((len(names), L))
        np.add.at(t, ([row[g] for g in gram[on]], [col[x] for x in langs[on]]), k[on])
        tables.append(row)
        counts.append(t)
    edge = chr(EDGE)
    alphabet = max(1, len(tables[0]), alphabet)
    logp: list[np.ndarray] = []
    backoff: list[np.ndarray] = []
    lower = np.full((1, L), 1.0 / alphabet)
    for m in range(1, order + 1):
        row, raw = tables[m - 1], counts[m - 1]
        # below the top: distinct letters before it; an n-gram at a word's start has no letter before it and keeps its count
        use = raw.copy()
        if m < order:
            more = np.zeros_like(raw)
            if tables[m]:
                np.add.at(more, [row[g[1:]] for g in tables[m]], counts[m] > 0)
            heads = np.array([g[0] == edge for g in row], bool)
            use = np.where(heads[:, None] & (m > 1), raw, more) if len(row) else raw
        names = list(row)
        ctx_of: dict[str, int] = {}
        ctx = np.array([ctx_of.setdefault(g[:-1], len(ctx_of)) for g in names], np.int64)
        total, kinds = np.zeros((len(ctx_of), L)), np.zeros((len(ctx_of), L))
        np.add.at(total, ctx, use)
        np.add.at(kinds, ctx, use > 0)
        seen = total > 0
        weight = np.where(seen, discount * kinds / np.maximum(total, 1e-300), 1.0)
        below = lower if m == 1 else np.exp(logp[m - 2])[[tables[m - 2][g[1:]] for g in names]]
        p = np.where(seen[ctx], np.maximum(use - discount, 0) / np.maximum(total[ctx], 1e-300), 0) + weight[ctx] * below
        logp.append(np.log(np.maximum(p, 1e-12)))
        if m > 1:  # back-off weights sit with the contexts, which are n-grams one shorter
            held = np.zeros((len(tables[m - 2]), L))
            for g, i in ctx_of.items():
                if g in tables[m - 2]:
                    held[tables[m - 2][g]] = np.log(weight[i])
            backoff.append(held)
        else:
            unseen = weight[0] / alphabet if len(weight) else np.full(L, 1.0 / alphabet)
    backoff.append(np.zeros((len(tables[-1]), L)))
    hashes = []
    for m in range(1, order + 1):
        names = list(tables[m - 1])
        points = np.frombuffer("".join(names).encode("utf-32-le", "surrogatepass"), np.uint32).reshape(len(names), m).astype(np.uint64)
        h = np.zeros(len(names), np.uint64)
        for j in range(m):
            h = mix64(h + (points[:, m - 1 - j] + np.uint64((j + 1) << 32)) * _G)
        o = np.argsort(h)
        hashes.append(h[o])
        logp[m - 1], backoff[m - 1] = logp[m - 1][o].astype(np.float32), backoff[m - 1][o].astype(np.float32)
    return LanguageModels(languages, hashes, logp, backoff, np.log(np.maximum(unseen, 1e-12)).astype(np.float32))


@dataclass
class LanguageGroups:
    """Models of more n-grams than are held at once: the written counts, from which each group's arrays are built in turn."""

    counts: DataFrame
    groups: list[list[str]]
    order: int
    discount: float
    alphabet: int
    temperature: float = 1.0
    reject: float = 0.5

    @property
    def languages(self) -> list[str]:
        return [x for g in self.groups for x in g]

    def parts(self) -> Iterator[LanguageModels]:
        for g in self.groups:
            got = self.counts.where((F.col("lang") >= g[0]) & (F.col("lang") <= g[-1])).toPandas()  # groups are runs of the alphabet
            yield kneser_ney(got["lang"].to_numpy(), got["n"].to_numpy(), got["gram"].to_numpy(), got["k"].to_numpy(), g, self.order, self.discount, self.alphabet)


def _groups(sizes: dict[str, int], max_ngrams: int) -> list[list[str]]:
    """Languages in order, in groups of bounded tables; a language is never split."""
    out: list[list[str]] = []
    total = 0
    for x in sorted(sizes, key=lambda x: x.encode("utf-8", "surrogatepass")):
        many = total + sizes[x]
        if not out or many > max_ngrams or many * (len(out[-1]) + 1) > MAX_CELLS:
            out.append([])
            many = sizes[x]
        out[-1].append(x)
        total = many
    return out


def train(docs: DataFrame, order: int = ORDER, discount: float = DISCOUNT, max_ngrams: int = MAX_NGRAMS, calibration_rows: int | None = None) -> LanguageModels | LanguageGroups:
    """Models from all of ``docs(doc_id, text, lang)``; rows without text or language are left out. ``max_ngrams`` bounds what is held at once, not what is counted. Scores are calibrated on all rows, or not at all with ``calibration_rows=0``."""
    ship(docs.sparkSession)
    rows = docs.where("text is not null and lang is not null").select(F.col("lang").cast("string").alias("lang"), "text")
    counted = rows.mapInArrow(_count(order), "lang string, n int, gram string, k long").groupBy("lang", "n", "gram").agg(F.sum("k").alias("k"))
    counted = materialize(counted, "ngrams")
    groups = _groups({r["lang"]: r["count"] for r in counted.groupBy("lang").count().collect()}, max_ngrams)
    if not groups:
        z = np.zeros(0, np.uint64)
        return LanguageModels([], [z] * order, [np.zeros((0, 0))] * order, [np.zeros((0, 0))] * order, np.zeros(0))
    alphabet = counted.where("n = 1").agg(F.countDistinct("gram")).first()[0]
    many = LanguageGroups(counted, groups, order, discount, alphabet)
    one = next(many.parts()) if len(groups) == 1 else None
    if calibration_rows is None:
        scored = _scored(one or many, rows)
        _calibrate(one or many, scored)
        discard(scored)
    elif calibration_rows:
        raise ValueError("calibration takes all rows or none")
    if one is not None:
        discard(counted)
    return one or many


def _share(mean: np.ndarray, letters: np.ndarray, temperature: float) -> tuple[np.ndarray, np.ndarray]:
    z = np.exp((mean - mean.max(1, keepdims=True)) / temperature)
    return np.where(letters > 0, mean.argmax(1), -1), np.where(letters > 0, z.max(1) / z.sum(1), 0.0)


def _means(part: LanguageModels, kept: list[str], last: bool):
    """Appends a group's mean log probabilities to those of each row; the last group's pass leaves out the text."""
    names = [*kept, "mean", "letters"] if last else [*kept, "text", "mean", "letters"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in chunks(b.column("text"), WORD_CHUNK_BYTES):
                mean, letters = part.text_scores(c)
                old = b.column("mean").slice(c.lo, c.n)
                mean = np.concatenate([old.flatten().to_numpy().reshape(c.n, -1) if len(old.flatten()) else np.zeros((c.n, 0)), mean], 1)
                lists = pa.ListArray.from_arrays(pa.array((np.arange(c.n + 1) * mean.shape[1]).astype(np.int32)), pa.array(mean.reshape(-1)))
                text = [] if last else [b.column("text").slice(c.lo, c.n)]
                yield pa.RecordBatch.from_arrays([*(b.column(x).slice(c.lo, c.n) for x in kept), *text, lists, pa.array(letters.astype(np.float64))], names=names)

    return run


def _scored(model: LanguageModels | LanguageGroups, rows: DataFrame) -> DataFrame:
    """``rows(text, ...)`` without the text, with the mean log probabilities by language and the number of letters: each text scored once, into a written table."""
    kept = [c for c in rows.columns if c != "text"]
    now = rows.select(*kept, "text", F.array().cast("array<double>").alias("mean"), F.lit(0.0).alias("letters"))
    parts = len(model.groups) if isinstance(model, LanguageGroups) else 1
    for i, part in enumerate(model.parts() if isinstance(model, LanguageGroups) else [model]):
        last = i == parts - 1
        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in now.schema if not (last and f.name == "text"))
        then = materialize(now.mapInArrow(_means(part, kept, last), schema), "scores")
        discard(now)
        now = then
    return now


def _calibrate(model: LanguageModels | LanguageGroups, scored: DataFrame) -> None:
    """Temperature of least log loss over all ``scored(lang, mean, letters)``; rejection at the score that all but one in a thousand right answers reach.

    Sums by temperature and the lowest thousandth come back.
    """
    names, many = {x: i for i, x in enumerate(model.languages)}, len(model.languages)
    now = scored.select("lang", "mean", "letters")

    def known(b: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        truth = np.array([names.get(x, -2) for x in b.column("lang").to_pylist()], np.int64)  # a language without a letter has no model
        mean, letters = b.column("mean").flatten().to_numpy().reshape(b.num_rows, many), b.column("letters").to_numpy()
        on = (letters > 0) & (truth >= 0)
        return mean[on], letters[on], truth[on]

    def losses(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(len(TEMPERATURES)), 0
        for b in batches:
            mean, _, truth = known(b)
            for i, t in enumerate(TEMPERATURES):
                z = (mean - mean.max(1, keepdims=True)) / t
                total[i] += (np.log(np.exp(z).sum(1)) - z[np.arange(len(z)), truth]).sum()
            n += len(mean)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total))), pa.array(total), pa.array(np.full(len(total), n))], names=["i", "loss", "n"])

    got = now.mapInArrow(losses, "i long, loss double, n long").groupBy("i").agg(F.sum("loss").alias("loss"), F.sum("n").alias("n")).collect()
    if got and got[0]["n"]:
        model.temperature = temperature = float(TEMPERATURES[min((r["loss"], r["i"]) for r in got)[1]])

        def rights(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                mean, letters, truth = known(b)
                if len(mean):
                    win, score = _share(mean, letters, temperature)
                    yield pa.RecordBatch.from_arrays([pa.array(score[win == truth])], names=["score"])

        right = now.mapInArrow(rights, "score double")
        n = right.count()
        at = 0.001 * max(0, n - 1)
        low = [r["score"] for r in right.orderBy("score").limit(int(at) + 2).collect()]
        if n:
            model.reject = float(min(0.5, np.interp(at, np.arange(len(low)), low)))


def _predict(model: LanguageModels):
    schema = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64()), ("cross_entropy", pa.float64()), ("rejected", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = np.array([*model.languages, "und"], object)
        for b in batches:
            for c in chunks(b.column("text"), WORD_CHUNK_BYTES):
                mean, letters = model.text_scores(c) if model.languages else (np.zeros((c.n, 0)), np.zeros(c.n))
                win, score = model.decide(mean, letters)
                ce = -mean.max(1) / np.log(2) if model.languages else np.zeros(c.n)
                yield pa.RecordBatch.from_arrays([
                    b.column("doc_id").slice(c.lo, c.n), pa.array(names[win], pa.string()), pa.array(score), pa.array(ce, mask=win < 0), pa.array((win < 0) | (score < model.reject)),
                ], schema=schema)

    return run


def _pass(part: LanguageModels, temperature: float):
    """Adds a group to the running winner of each row: ``top`` is its mean log probability, ``mass`` the sum of exp((mean - top) / temperature)."""
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string()), ("win", pa.string()), ("top", pa.float64()), ("mass", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = np.array(part.languages, object)
        for b in batches:
            for c in chunks(b.column("text"), WORD_CHUNK_BYTES):
                old = [b.column(x).slice(c.lo, c.n) for x in ("win", "top", "mass")]
                win, top, mass = old[0].to_numpy(zero_copy_only=False), old[1].to_numpy(zero_copy_only=False), old[2].to_numpy(zero_copy_only=False)
                mean, letters = part.text_scores(c)
                best = mean.max(1)
                more = best > top  # a tie stays with the language first in the alphabet
                high = np.maximum(best, top)
                mass = mass * np.exp((top - high) / temperature) + np.exp((mean - high[:, None]) / temperature).sum(1)
                win = np.where(letters > 0, np.where(more, names[mean.argmax(1)], win), None)
                yield pa.RecordBatch.from_arrays([b.column("doc_id").slice(c.lo, c.n), b.column("text").slice(c.lo, c.n), pa.array(win, pa.string()), pa.array(high), pa.array(mass)], schema=schema)

    return run


def _predict_groups(docs: DataFrame, model: LanguageGroups) -> DataFrame:
    lowest = F.lit(-1e300)
    now = docs.select("doc_id", "text", F.lit(None).cast("string").alias("win"), lowest.alias("top"), F.lit(0.0).alias("mass"))
    for part in model.parts():
        then = materialize(now.mapInArrow(_pass(part, model.temperature), "doc_id long, text string, win string, top double, mass double"), "languages")
        discard(now)
        now = then
    score = F.when(F.col("win").isNull(), 0.0).otherwise(1 / F.col("mass"))
    entropy = F.when(F.col("win").isNotNull(), -F.col("top") / float(np.log(2)))
    return now.select("doc_id", F.coalesce("win", F.lit("und")).alias("lang_pred"), score.alias("score"), entropy.alias("cross_entropy"), (F.col("win").isNull() | (score < model.reject)).alias("rejected"))


def predict(docs: DataFrame, model: LanguageModels | LanguageGroups) -> DataFrame:
    """``docs(doc_id, text)`` to (doc_id, lang_pred, score, cross_entropy in bits a letter, rejected)."""
    spark = docs.sparkSession
    ship(spark)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if isinstance(model, LanguageGroups):
        return _predict_groups(docs, model)
    return docs.mapInArrow(_predict(model), "doc_id long, lang_pred string, score double, cross_entropy double, rejected boolean")


def _decided(languages: list[str], temperature: float, reject: float):
    """Winners of scored rows."""
    schema = pa.schema([("doc_id", pa.int64()), ("lang_pred", pa.string()), ("score", pa.float64()), ("cross_entropy", pa.float64()), ("rejected", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = np.array([*languages, "und"], object)
        for b in batches:
            if not b.num_rows:
                continue
            mean = b.column("mean").flatten().to_numpy().reshape(b.num_rows, len(languages))
            win, score = _share(mean, b.column("letters").to_numpy(), temperature)
            ce = pa.array(-mean.max(1) / np.log(2), mask=win < 0)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(names[win], pa.string()), pa.array(score), ce, pa.array((win < 0) | (score < reject))], schema=schema)

    return run


def train_and_predict(docs: DataFrame, training: Column, order: int = ORDER, discount: float = DISCOUNT, max_ngrams: int = MAX_NGRAMS) -> DataFrame:
    """``predict(docs, train(docs.where(training)))``, with each text scored once: the training rows' scores calibrate, and all rows are decided from the same table."""
    model = train(docs.where(training), order, discount, max_ngrams, calibration_rows=0)
    if not model.languages:
        return predict(docs, model)
    usable = training & F.col("text").isNotNull() & F.col("lang").isNotNull()
    scored = _scored(model, docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.when(usable, F.col("lang").cast("string")).alias("lang"), "text"))
    _calibrate(model, scored.where("lang is not null"))
    return scored.select("doc_id", "mean", "letters").mapInArrow(_decided(model.languages, model.temperature, model.reject), "doc_id long, lang_pred string, score double, cross_entropy double, rejected boolean")
