"""Dense algebra on d x d (or nd x nd) matrices, and sums of matrices that tasks make."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame


def procrustes(a: np.ndarray) -> np.ndarray:
    """The orthogonal W that maximises trace(W' A) for a cross-covariance A = M'Y."""
    u, _, vt = np.linalg.svd(a)
    return u @ vt


def signed(v: np.ndarray) -> np.ndarray:
    """Columns with their largest loading positive."""
    s = np.sign(v[np.argmax(np.abs(v), 0), np.arange(v.shape[1])])
    return v * np.where(s == 0, 1, s)


def matrix_of(col: pa.Array | pa.ChunkedArray, dim: int) -> np.ndarray:
    """A list column of equal lengths as a matrix."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    return col.flatten().to_numpy(zero_copy_only=False).reshape(len(col), dim)


def lists_of(x: np.ndarray, kind: type = np.float32) -> pa.Array:
    n, d = x.shape
    return pa.ListArray.from_arrays(pa.array((np.arange(n + 1) * d).astype(np.int32)), pa.array(np.ascontiguousarray(x, kind).reshape(-1)))


SPREAD = 32


def summed(df: DataFrame, part: Callable, finish: Callable[[int, np.ndarray], np.ndarray] | None = None) -> dict[int, np.ndarray]:
    """Add up matrices that tasks make: ``part(batches)`` yields (key, matrix).

    Each task adds its own, the tasks' sums meet in ``SPREAD`` groups for each key and then in one, so no task holds a
    matrix of every other. ``finish`` is applied to a key's sum where that stands, in a task; what comes to the driver is its
    result, in ``float64``, one for each key.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for k, m in part(batches):
            total[k] = total[k] + m if k in total else m
        s = TaskContext.get().partitionId() % SPREAD
        for k in sorted(total):
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([s], pa.int32()), pa.array([total[k].astype(np.float64).tobytes()], pa.binary())], names=["k", "s", "m"])

    def add(last: bool):
        def of(key: tuple[pa.Scalar, ...], t: pa.Table) -> pa.Table:
            m = sum(np.frombuffer(x.as_py(), np.float64) for x in t["m"])
            m = np.ascontiguousarray(finish(key[0].as_py(), m), np.float64) if last and finish else m
            return pa.table({"k": pa.array([key[0].as_py()], pa.int32()), "s": pa.array([0], pa.int32()), "m": pa.array([m.tobytes()], pa.binary())})

        return of

    schema = "k int, s int, m binary"
    parts = df.mapInArrow(run, schema).groupBy("k", "s").applyInArrow(add(False), schema)
    rows = parts.groupBy("k").applyInArrow(add(True), schema).collect()
    return {r["k"]: np.frombuffer(r["m"], np.float64) for r in rows}


def dimension(df: DataFrame, col: str = "vec") -> int:
    from pyspark.sql import functions as F

    row = df.select(F.size(col).alias("d")).first()
    return int(row["d"]) if row else 0
