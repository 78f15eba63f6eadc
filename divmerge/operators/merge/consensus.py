"""Consensus by alternating orthogonal alignment over the union vocabulary, with missing words estimated on the way.

Each round: for every model the orthogonal map of its present rows onto the consensus Y; a missing row's estimate maps to
the old Y row exactly, so it is never made: the new row is (sum of present aligned rows + absent * old row) / n.

The vectors are grouped by word once and never written again; where they come grouped, the first Y is drawn as it is read. A row's Y follows from its first value and the rotations so
far, so a round is one narrow pass: it brings Y up to date, adds up what the displacement needs, and adds up n
cross-covariances of d x d, whose decompositions are made where the sums meet, in tasks. n rotations come to the
driver and go out with the next pass; when those of several rounds pass ``HISTORY_BYTES``, the table is written once with its Y.
``missing='present_only'`` averages present rows alone: the same fixed points, reached sooner where many rows are missing.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...functions.draws import gaussian
from ...session import discard, materialize, ship
from .basic import by_word, merge_concat, principal
from .linalg import lists_of, procrustes, summed

ROWS = "word string, models array<int>, flat array<float>, y array<double>"
HISTORY_BYTES = 256 << 20
MOVED = -1  # the key of the displacement's sums

Rotations = dict[int, np.ndarray]


@dataclass
class Consensus:
    merged: DataFrame  # word, vec, n_present
    rotations: Rotations
    displacements: list[float] = field(default_factory=list)
    init: str = "random"


class _Rounds:
    """What a pass knows: the rotations since the table was written, and the principal components that Y begins with, where it does."""

    def __init__(self, n: int, d: int, missing: str, past: list[Rotations], start: Start | None = None) -> None:
        self.n, self.d, self.missing, self.past, self.start = n, d, missing, past, start

    def rows(self, b: pa.RecordBatch):
        """Models of the present vectors, the row of each, the vectors, Y before the last round, and Y."""
        lists = b.column("models")
        models, sizes = lists.flatten().to_numpy(), np.diff(lists.offsets.to_numpy())
        row = np.repeat(np.arange(b.num_rows), sizes)
        flat = b.column("flat").flatten().to_numpy().reshape(-1, self.d).astype(np.float64)
        old = y = b.column("y").flatten().to_numpy().reshape(-1, self.d)
        if self.start and (every := sizes == self.n).any():  # scaled to one model's size
            mean, load = self.start
            old = y = y.copy()
            y[every] = ((flat[every[row]].reshape(-1, self.n * self.d) - mean) @ load).astype(np.float32).astype(np.float64) / self.n**0.5
        own = [(int(k), np.flatnonzero(models == k)) for k in np.unique(models)]
        for w in self.past:
            new = np.zeros_like(y)
            for k, on in own:  # a model has a word once, so no row comes twice
                new[row[on]] += flat[on] @ w[k].astype(np.float64)
            old, y = y, (new + (self.n - sizes)[:, None] * y) / self.n if self.missing == "impute" else new / np.maximum(sizes, 1)[:, None]
        return own, row, flat, old, y

    def sums(self, cross: bool):
        """Cross-covariances with Y for the next rotations, and the squared distances of Y to each model's aligned rows.

        A missing row's estimate is where the old Y was, so its distance is the step of Y.
        """

        def part(batches: Iterator[pa.RecordBatch]):
            for b in batches:
                if not b.num_rows:
                    continue
                own, row, flat, old, y = self.rows(b)
                if cross:
                    for k, on in own:
                        yield k, flat[on].T @ y[row[on]]
                if self.past:
                    step = ((y - old) ** 2).sum(1)
                    out = np.full(self.n + 1, step.sum())
                    out[self.n] = len(y)
                    for k, on in own:
                        out[k] += ((y[row[on]] - flat[on] @ self.past[-1][k].astype(np.float64)) ** 2).sum() - step[row[on]].sum()
                    yield MOVED, out

        return part

    def rotation(self, key: int, m: np.ndarray) -> np.ndarray:
        return m if key == MOVED else procrustes(m.reshape(self.d, self.d)).reshape(-1)

    def now(self, whole: bool):
        """Rows with their Y: all columns, or (word, vec, n_present)."""

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                if not b.num_rows:
                    continue
                *_, y = self.rows(b)
                if whole:
                    yield pa.RecordBatch.from_arrays([b.column("word"), b.column("models"), b.column("flat"), lists_of(y, np.float64)], names=["word", "models", "flat", "y"])
                else:
                    yield pa.RecordBatch.from_arrays([b.column("word"), lists_of(y), b.column("models").value_lengths()], names=["word", "vec", "n_present"])

        return run


Start = tuple[np.ndarray, np.ndarray]


def init_y(blocks: DataFrame, n: int, d: int, init: str, seed: int) -> tuple[DataFrame, Start | None, str]:
    """Add ``y``: Gaussians drawn by word and position, or the first model's vector where there is one; and the mean and loadings of the principal components, which take its place where a word is common."""
    random = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: gaussian(seed, "init", F.col("word"), j) * (1.0 / d**0.5))
    first = F.get("models", F.lit(0)) == 0
    if init == "first" and not blocks.where(first).isEmpty():
        return blocks.withColumn("y", F.when(first, F.slice("flat", 1, d).cast("array<double>")).otherwise(random)), None, init
    start = None
    if init == "pca":
        try:
            start = principal(merge_concat(blocks, n), n, d)
        except ValueError:
            pass
    if start:
        random = F.when(F.size("models") == n, F.array_repeat(F.lit(0.0), d)).otherwise(random)
    return blocks.withColumn("y", random), start, init if start else "random"


def merge_consensus(sub: DataFrame, n: int, init: str = "pca", iters: int = 3, tol: float = 0.0, seed: int = 1, missing: str = "impute") -> Consensus:
    """Merge n sub-models; stops after ``iters`` rounds, or when the displacement changes by less than ``tol``.

    ``init='pca'`` falls back to random where no word is common; the result says which was used. No vectors give no vectors.
    """
    spark = sub.sparkSession
    ship(spark)
    grouped = "flat" in sub.columns
    blocks = by_word(sub).select("word", F.col("models").cast("array<int>").alias("models"), F.col("flat").cast("array<float>").alias("flat"))
    blocks = blocks if grouped else materialize(blocks, "by_word")
    one = blocks.select((F.size("flat") / F.size("models")).cast("int").alias("d")).first()
    d = one["d"] if one else 0
    if not d:
        return Consensus(spark.createDataFrame([], "word string, vec array<float>, n_present int"), {}, [], "random")
    first, start, used = init_y(blocks, n, d, init, seed)
    table = first.select("word", "models", "flat", "y")
    if not grouped:
        table = materialize(table, "consensus")
        discard(blocks)
    out = Consensus(table, {}, [], used)
    past: list[Rotations] = []
    for t in range(iters + 1):
        at = _Rounds(n, d, missing, list(past), start)
        got = summed(table.select("models", "flat", "y"), at.sums(cross=t < iters), at.rotation)
        moved = got.pop(MOVED, None)
        if moved is not None:
            out.displacements.append(float(np.sqrt(np.maximum(moved[:n], 0)).sum() / n / np.sqrt(max(1.0, moved[n]) * d)))
        if t == iters or len(out.displacements) > 1 and abs(out.displacements[-2] - out.displacements[-1]) < tol:
            break
        if len(past) > 1 and (len(past) + 1) * n * d * d * 4 > HISTORY_BYTES:
            before, table, past = table, materialize(table.mapInArrow(at.now(whole=True), ROWS), "consensus"), []
            discard(before)
            start = None
        past.append({k: m.reshape(d, d).astype(np.float32) for k, m in got.items()})
    if past:
        out.rotations = {k: m.astype(np.float64) for k, m in past[-1].items()}
    out.merged = table.mapInArrow(_Rounds(n, d, missing, past, start).now(whole=False), "word string, vec array<float>, n_present int")
    return out


def merge_procrustes(sub: DataFrame, n: int, init: str = "first", tol: float = 1e-6, max_iter: int = 20, seed: int = 1) -> Consensus:
    """The generic consensus on words that all models hold: align to the mean, average, repeat."""
    common = sub.groupBy("word").agg(F.countDistinct("model").alias("k")).where(F.col("k") == n).select("word")
    return merge_consensus(sub.join(common, "word", "left_semi"), n, init=init, iters=max_iter, tol=tol, seed=seed)


def merge_in_groups(sub: DataFrame, n: int, group: int = 16, init: str = "pca", iters: int = 3, seed: int = 1) -> Consensus:
    """For very many models: a consensus of each ``group`` of them, then the consensus of those; no more than ``group`` rotations are held at once."""
    if n <= group:
        return merge_consensus(sub, n, init, iters, seed=seed)
    parts, many = None, -(-n // group)
    for g in range(many):
        own = sub.where((F.col("model") >= g * group) & (F.col("model") < (g + 1) * group)).withColumn("model", F.col("model") - g * group)
        part = merge_consensus(own, min(group, n - g * group), init, iters, seed=seed).merged.select(F.lit(g).alias("model"), "word", "vec")
        parts = part if parts is None else parts.unionByName(part)
    return merge_in_groups(materialize(parts, "groups"), many, group, init, iters, seed)


def reconstruct(result: Consensus, sub: DataFrame, model: int) -> DataFrame:
    """(model, word, vec): vectors, in a sub-model's own space, of the words it lacks: Y rows turned back by its rotation."""
    back = result.rotations[model].T
    d = len(back)
    lacking = result.merged.join(sub.where(F.col("model") == model).select("word"), "word", "left_anti")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = b.column("vec").flatten().to_numpy().reshape(-1, d) @ back
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(x), model, np.int32)), b.column("word"), lists_of(x)], names=["model", "word", "vec"])

    return lacking.select("word", "vec").mapInArrow(run, "model int, word string, vec array<float>")
