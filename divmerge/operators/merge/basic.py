"""Merges over the common vocabulary: concatenation, principal components, unaligned mean; and single sub-models."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...session import materialize, ship
from .linalg import dimension, lists_of, matrix_of, signed, summed

#: Columns up to which ``solver='auto'`` makes the whole Gram matrix; beyond, subspaces are iterated until they stand.
GRAM_LIMIT = 4096


def word_blocks(sub: DataFrame) -> DataFrame:
    """(word, parts): the present vectors of each word, ordered by model; absent models are not there. One exchange by word."""
    return sub.groupBy("word").agg(F.array_sort(F.collect_list(F.struct("model", "vec"))).alias("parts"))


def by_word(sub: DataFrame) -> DataFrame:
    """(word, models, flat): the models that hold a word, in order, and their vectors side by side.

    A table that is so already is given back: one that is written serves all merges of the same sub-models.
    """
    if "flat" in sub.columns:
        return sub
    return word_blocks(sub).select("word", F.transform("parts", lambda p: p["model"].cast("int")).alias("models"), F.flatten(F.transform("parts", lambda p: p["vec"])).alias("flat"))


def merge_concat(sub: DataFrame, n: int) -> DataFrame:
    """(word, vec): vectors side by side, for words that all n sub-models hold; ``sub`` by rows or ``by_word``, as in all merges but the mean and the single."""
    return by_word(sub).where(F.size("models") == n).select("word", F.col("flat").alias("vec"))


def merge_mean(sub: DataFrame) -> DataFrame:
    """(word, vec, n_present): the plain mean of unaligned vectors; spaces differ, so this is the counter-example."""
    wide = F.transform("parts", lambda p: F.transform(p["vec"], lambda x: x.cast("double")))
    total = F.aggregate(F.slice("wide", F.lit(2), F.col("n_present")), F.get("wide", F.lit(0)), lambda s, v: F.zip_with(s, v, lambda x, y: x + y))
    rows = word_blocks(sub).select("word", wide.alias("wide"), F.size("parts").alias("n_present"))
    return rows.select("word", F.transform(total, lambda x: (x / F.col("n_present")).cast("float")).alias("vec"), "n_present")


def merge_single(sub: DataFrame, model: int) -> DataFrame:
    return sub.where(F.col("model") == model).select("word", "vec")


def _gram(dim: int, mean: np.ndarray):
    def part(batches: Iterator[pa.RecordBatch]):
        for b in batches:
            x = matrix_of(b.column("vec"), dim).astype(np.float64) - mean
            yield 0, x.T @ x

    return part


def column_means(rows: DataFrame, dim: int) -> tuple[np.ndarray, int]:
    def part(batches: Iterator[pa.RecordBatch]):
        for b in batches:
            x = matrix_of(b.column("vec"), dim)
            yield 0, np.append(x.sum(0, dtype=np.float64), len(x))

    got = summed(rows.select("vec"), part).get(0)
    if got is None or got[-1] == 0:
        return np.zeros(dim), 0
    return got[:-1] / got[-1], int(got[-1])


def _times(rows: DataFrame, dim: int, mean: np.ndarray, q: np.ndarray) -> np.ndarray:
    """X'X q without X'X: one pass, dim x k numbers back."""

    def part(batches: Iterator[pa.RecordBatch]):
        for b in batches:
            x = matrix_of(b.column("vec"), dim).astype(np.float64) - mean
            yield 0, x.T @ (x @ q)

    return summed(rows.select("vec"), part)[0].reshape(dim, -1)


def components(
    rows: DataFrame, dim: int, d: int, solver: str = "auto", center: bool = True, seed: int = 1, tol: float = 1e-7, max_rounds: int = 100
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(mean, loadings dim x d, variances) of ``rows(vec)``.

    ``gram`` decomposes the whole Gram matrix. ``randomized`` iterates a subspace somewhat larger than d, one pass a round and
    dim x d numbers back, until the variance it captures grows by less than ``tol`` of it.
    """
    ship(rows.sparkSession)
    mean, n = column_means(rows, dim)
    if n == 0:
        raise ValueError("no word is in all sub-models, so there are no principal components")
    mean = mean if center else np.zeros(dim)
    if solver == "gram" or solver == "auto" and dim <= GRAM_LIMIT:
        val, vec = np.linalg.eigh(summed(rows.select("vec"), _gram(dim, mean))[0].reshape(dim, dim))
        val, vec = val[::-1][:d], vec[:, ::-1][:, :d]
    elif solver in ("auto", "randomized"):
        q, _ = np.linalg.qr(np.random.default_rng(seed).standard_normal((dim, min(dim, d + max(10, d // 2)))))
        before = 0.0
        for _ in range(max_rounds):
            aq = _times(rows, dim, mean, q)
            t = q.T @ aq
            val, u = np.linalg.eigh((t + t.T) / 2)
            val, vec = val[::-1][:d], (q @ u[:, ::-1])[:, :d]
            if val.sum() - before <= tol * max(val.sum(), 1e-300):
                break
            before = float(val.sum())
            q, _ = np.linalg.qr(aq)
    else:
        raise ValueError(f"no such solver: {solver}")
    return mean, signed(vec), np.maximum(val, 0) / max(1, n - 1)


def principal(rows: DataFrame, n: int, d: int | None = None, solver: str = "auto", center: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(mean, loadings) of the first d principal components of a concatenation; d defaults to the sub-models' dimension."""
    dim = dimension(rows)
    if not dim:
        raise ValueError("no word is in all sub-models, so there are no principal components")
    return components(rows, dim, min(d or dim // n, dim), solver, center)[:2]


def merge_pca(sub: DataFrame, n: int, d: int | None = None, solver: str = "auto", center: bool = True) -> DataFrame:
    """(word, vec): the first d principal components of the concatenation; d defaults to the sub-models' dimension."""
    rows = merge_concat(sub, n)
    rows = rows if "flat" in sub.columns else materialize(rows, "concat")
    mean, vec = principal(rows, n, d, solver, center)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            x = (matrix_of(b.column("vec"), len(mean)) - mean) @ vec
            yield pa.RecordBatch.from_arrays([b.column("word"), lists_of(x)], names=["word", "vec"])

    return rows.select("word", "vec").mapInArrow(run, "word string, vec array<float>")
