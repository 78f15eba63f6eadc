"""Substring dedup by difference-cover anchors.

A passage is a window of ``window`` consecutive words. Every word covered by a window whose word sequence also
starts earlier (a smaller id, or the same row at an earlier word) is removed; windows are judged on the input.

Method. Take the positions ``p`` of a row with ``p mod period`` in a difference cover of the period. For any two
positions there is a shift below the period which brings both onto the cover, so two equal windows share an equal,
aligned *anchor* of ``window - period + 1`` words. Only anchors are hashed and dealt out; where an anchor occurs
again, the windows around it are extended to their full length and compared by full hash.

Plan. Rows are dealt once by a bucket of their id and text (that exchange is read three times; rows that are equal in both are
spread by the partition they came from). A bucket sends each of its
distinct anchors once, in packed blobs keyed by hash range, so a passage shared by a third of all rows is one entry
for each bucket and not one for each row. Hash ranges answer with the anchors which two buckets hold; buckets send
the candidate windows with their least id; hash ranges answer with the windows that another bucket owns.
Buckets and ranges grow in number with the text, so that the memory of a task does not.

Defined results: null and empty texts have no words; rows with null id come first in the order and are kept; rows
with equal ids are ordered by a hash of their text, and equal rows anyhow; extra columns do not matter; no rows give no rows. Two different windows are taken for
equal with probability 2**-64 for a pair.
"""

from __future__ import annotations

import hashlib
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .textnum import chunks, covered, trim, windows, words

#: Difference covers: each residue modulo the period is a difference of two members. Fixed values.
COVERS = {3: (0, 1), 7: (0, 1, 3), 13: (0, 1, 3, 9)}
UNIT_BYTES = 4 << 20
LEAST_ID = -(1 << 63)
UNIT, TIE = "__unit", "__tie"
PARTITION_BYTES = 128 << 20  # text in a task, where the table has more than the session's partitions hold


def cover_of(window: int) -> tuple[int, tuple[int, ...]]:
    """The largest known period which leaves an anchor of a third of the window at least."""
    period = max((p for p in COVERS if window - p + 1 >= max(1, window // 3)), default=1)
    return period, COVERS.get(period, (0,))


def _parts(h: np.ndarray, n: int) -> np.ndarray:
    """Hash range 0..n-1 of each hash; monotonic in the hash."""
    return ((h >> np.uint64(32)) * np.uint64(n) >> np.uint64(32)).astype(np.int64)


def _sliced(h: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """For ascending hashes: the ranges that occur, and the borders of their runs."""
    part = _parts(h, n)
    at = np.flatnonzero(np.diff(part, prepend=-1))
    return part[at], np.append(at, len(h))


def _ordered(table: pa.Table) -> tuple[pa.Table, np.ndarray, np.ndarray]:
    """Rows in order, their ids, and what orders rows with equal ids."""
    ids, tie = table["doc_id"].fill_null(LEAST_ID).to_numpy(), table[TIE].to_numpy()
    order = np.lexsort((tie, ids))
    return table.take(pa.array(order)) if len(ids) > 1 else table, ids[order], tie[order]


def _anchors(w, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions of anchors in the chunk, and their hashes."""
    period, cover = cover_of(window)
    h, fits = windows(w, window - period + 1)
    if not len(h):
        return np.zeros(0, np.int64), h
    on = np.zeros(period, bool)
    on[list(cover)] = True
    pos = np.arange(len(h)) - np.repeat(w.first[:-1], w.count)
    at = np.flatnonzero(fits & on[pos % period])
    return at, h[at]


def _send_anchors(window: int, n_parts: int):
    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        found = [np.unique(_anchors(words(c), window)[1]) for c in chunks(table["text"])]
        h = np.unique(np.concatenate(found)) if found else np.zeros(0, np.uint64)
        part, at = _sliced(h, n_parts)
        return pa.table({
            "part": pa.array(part, pa.int64()), "unit": pa.array([key[0].as_py()] * len(part), pa.int64()),
            "hashes": pa.array([h[a:b].tobytes() for a, b in zip(at[:-1], at[1:])], pa.binary()),
        })

    return run


def _again(h: np.ndarray) -> np.ndarray:
    """Mask of hashes that occur twice or more."""
    order = np.argsort(h, kind="stable")
    same = h[order][1:] == h[order][:-1]
    hit = np.zeros(len(h), bool)
    hit[order[1:][same]] = hit[order[:-1][same]] = True
    return hit


def _not_least(h: np.ndarray, ids: np.ndarray, tie: np.ndarray, unit: np.ndarray) -> np.ndarray:
    """Mask of occurrences of a hash that are not its first, by id, tie and unit."""
    order = np.lexsort((unit, tie, ids, h))
    hit = np.zeros(len(h), bool)
    hit[order[1:][h[order][1:] == h[order][:-1]]] = True
    return hit


def _answer(with_ids: bool):
    def run(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        unit = table["unit"].to_pylist()
        blobs = [np.frombuffer(x, np.uint64) for x in table["hashes"].to_pylist()]
        h = np.concatenate(blobs)
        if with_ids:
            ids, tie = (np.concatenate([np.frombuffer(x, np.int64) for x in table[c].to_pylist()]) for c in ("ids", "ties"))
            hit = _not_least(h, ids, tie, np.repeat(unit, [len(b) for b in blobs]))
        else:
            hit = _again(h)
        border = np.cumsum([0, *map(len, blobs)])
        kept = [(u, b[hit[x : x + len(b)]]) for u, b, x in zip(unit, blobs, border)]
        kept = [(u, b.tobytes()) for u, b in kept if len(b)]
        return pa.table({"unit": pa.array([u for u, _ in kept], pa.int64()), "hashes": pa.array([b for _, b in kept], pa.binary())})

    return run


def _gathered(table: pa.Table) -> np.ndarray:
    blobs = [np.frombuffer(x, np.uint64) for x in table["hashes"].to_pylist()]
    return np.sort(np.concatenate(blobs)) if blobs else np.zeros(0, np.uint64)


def _in_sorted(x: np.ndarray, known: np.ndarray) -> np.ndarray:
    if not len(known) or not len(x):
        return np.zeros(len(x), bool)
    order = np.argsort(x)  # ascending probes keep to the cache
    at = np.searchsorted(known, x[order])
    out = np.empty(len(x), bool)
    out[order] = known[np.minimum(at, len(known) - 1)] == x[order]
    return out


def _send_windows(window: int, n_parts: int):
    period, _ = cover_of(window)

    def run(key: tuple[pa.Scalar, ...], docs: pa.Table, seen: pa.Table) -> pa.Table:
        trim()
        (docs, ids, tie), known = _ordered(docs), _gathered(seen)
        ws = [(c, words(c)) for c in chunks(docs["text"])]
        anchors = [_anchors(w, window) for _, w in ws]
        every = np.sort(np.concatenate([h for _, h in anchors])) if anchors else np.zeros(0, np.uint64)
        local = np.unique(every[1:][every[1:] == every[:-1]])
        none = np.zeros(0, np.int64)
        out_h, out_i, out_t = [none.view(np.uint64)], [none], [none]
        for (c, w), (at, h) in zip(ws, anchors):
            again = at[_in_sorted(h, known) | _in_sorted(h, local)]
            if not len(again):
                continue
            near = np.cumsum(np.bincount(again + 1, minlength=len(w.start) + period + 1))
            wh, fits = windows(w, window)
            n = len(wh)
            cand = np.flatnonzero(fits & (near[np.minimum(np.arange(n) + period, len(near) - 1)] > near[:n]))
            u, first = np.unique(wh[cand], return_index=True)
            row = c.lo + w.doc[cand[first]]
            out_h.append(u), out_i.append(ids[row]), out_t.append(tie[row])
        h, i, t = (np.concatenate(x) for x in (out_h, out_i, out_t))
        order = np.lexsort((t, i, h))
        order = order[np.concatenate([[True], h[order][1:] != h[order][:-1]])] if len(order) else order
        h, i, t = h[order], i[order], t[order]
        part, at = _sliced(h, n_parts)
        runs = list(zip(at[:-1], at[1:]))
        return pa.table({
            "part": pa.array(part, pa.int64()), "unit": pa.array([key[0].as_py()] * len(part), pa.int64()),
            "hashes": pa.array([h[a:b].tobytes() for a, b in runs], pa.binary()), "ids": pa.array([i[a:b].tobytes() for a, b in runs], pa.binary()),
            "ties": pa.array([t[a:b].tobytes() for a, b in runs], pa.binary()),
        })

    return run


def _finish(window: int, what: str):
    def run(key: tuple[pa.Scalar, ...], docs: pa.Table, seen: pa.Table) -> pa.Table:
        trim()
        (docs, _, _), elsewhere = _ordered(docs), _gathered(seen)
        ws = [(c, words(c)) for c in chunks(docs["text"])]
        full = [windows(w, window) for _, w in ws]
        at = [np.flatnonzero(f) for _, f in full]
        h = np.concatenate([x[a] for (x, _), a in zip(full, at)]) if full else np.zeros(0, np.uint64)
        order = np.argsort(h, kind="stable")
        s = h[order]
        later = np.zeros(len(h), bool)
        later[order[1:][s[1:] == s[:-1]]] = True
        later |= _in_sorted(h, elsewhere)
        border = np.cumsum([0, *map(len, at)])
        n_words, n_removed, out = [], [], []
        for k, (c, w) in enumerate(ws):
            gone = covered(len(w.start), at[k][later[border[k] : border[k + 1]]], window)
            n_words.append(w.count)
            sums = np.concatenate([[0], np.cumsum(gone)])
            n_removed.append(lost := sums[w.first[1:]] - sums[w.first[:-1]])
            for j in range(c.n):
                if what == "digest":
                    x = c.text(j).split()
                    if lost[j]:
                        x = list(compress(x, (~gone[w.first[j] : w.first[j + 1]]).tolist()))
                    out.append(hashlib.sha256(b" ".join(x)).hexdigest())
                elif not lost[j]:
                    out.append(c.text(j))
                else:
                    out.append(_cut(c, w, gone, j))
        if what == "rows":
            docs = docs.select([c for c in docs.column_names if c not in (UNIT, TIE)])
            return docs.set_column(docs.column_names.index("text"), "text", pa.array(out, pa.binary()).cast(pa.string()))
        ints = lambda x: pa.array(np.concatenate(x) if x else np.zeros(0, np.int64), pa.int64())
        return pa.table({"doc_id": docs["doc_id"], "n_words": ints(n_words), "n_removed": ints(n_removed), "kept_sha256": pa.array(out, pa.string())})

    return run


def _cut(c, w, gone: np.ndarray, j: int) -> bytes:
    """Row j without its removed words, each with the space after it; what stays keeps its spacing."""
    a, b = w.first[j], w.first[j + 1]
    begin = w.start[a:b]
    until = np.append(begin[1:], c.offs[j + 1])
    keep = ~gone[a:b]
    head = c.data[c.offs[j] : begin[0]].tobytes()
    edge = np.flatnonzero(np.diff(np.concatenate([[False], keep, [False]]).astype(np.int8)))
    return (head + b"".join(c.data[begin[x] : until[y - 1]].tobytes() for x, y in zip(edge[::2], edge[1::2]))).strip()


def remove_repeats(docs: DataFrame, window: int = 20, what: str = "digest", unit_bytes: int = UNIT_BYTES) -> DataFrame:
    """``docs(doc_id, text, ...)`` to (doc_id, n_words, n_removed, kept_sha256), or for ``what='rows'`` to the same rows with the repeats cut out of ``text``.

    ``kept_sha256`` is that of the kept words joined by one space; cut rows keep the spacing of what stays, and their other columns.
    """
    spark = docs.sparkSession
    ship(spark)
    docs = docs.withColumn("doc_id", F.col("doc_id").cast("long"))
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(64, -(-size // unit_bytes))
    width = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // PARTITION_BYTES))
    own = (docs if what == "rows" else docs.select("doc_id", "text")).withColumn(TIE, F.xxhash64("text"))
    own = own.withColumn(UNIT, F.pmod(F.xxhash64("doc_id", TIE, F.spark_partition_id()), F.lit(n))).repartition(width, UNIT)
    blob = "part long, unit long, hashes binary"
    sent = own.groupBy(UNIT).applyInArrow(_send_anchors(window, n), blob).repartition(width, "part")
    twice = sent.groupBy("part").applyInArrow(_answer(False), "unit long, hashes binary")
    cand = own.groupBy(UNIT).cogroup(twice.groupBy("unit")).applyInArrow(_send_windows(window, n), blob + ", ids binary, ties binary").repartition(width, "part")
    owned = cand.groupBy("part").applyInArrow(_answer(True), "unit long, hashes binary")
    schema = docs.schema if what == "rows" else "doc_id long, n_words long, n_removed long, kept_sha256 string"
    return own.groupBy(UNIT).cogroup(owned.groupBy("unit")).applyInArrow(_finish(window, what), schema)
