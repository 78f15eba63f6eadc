"""Near-duplicate classes by ProbMinHash signatures, banding and exact verification.

Texts are multisets of 5-word shingles (a shorter text is one shingle of all its words). The similarity is the
probability Jaccard of the counts: the sum over shared shingles d of 1 / sum_e max(x_e/x_d, y_e/y_d); for texts that
repeat no shingle it is the plain Jaccard similarity. Two texts are linked at 0.8 or more; classes are the connected
components of the links.

Signature. Every shingle starts a Poisson process with its count as rate, seeded by the shingle; each arrival falls
into one of ``slots`` slots and the first arrival of a slot names it. Two texts agree in a slot with exactly their
probability Jaccard. Processes stop at a horizon by which the slots of the text have been reached; texts with a slot
still open go on to twice the horizon. Arrivals after that cannot win a slot, so none is made.

Plan. Equal word sequences collapse first (a map-side combined aggregate), so a text with thousands of copies is one
row from there on; it is known by a 64-bit fingerprint of its words, so rows that share an id are told apart. In each
bucket of each band all members are paired with the least member only, and verified. Where the members of a bucket are
still in more than one component, those outside its largest component are compared with all its members, exactly, in
blocks of bounded size; only links leave a block, never its pairs. After that every pair of a bucket is linked, known
to be unlike, or joined already. Components come from alternating star contractions on tables; nothing is collected.
Rows meet their class in a join in which heavy texts (a third of all rows may be one text) are broadcast, by count.

Defined results: null and wordless texts are classes of their own, named by their id; a row with null id belongs to the class of its
text, and a class in which no row has an id has a null name; of rows with equal ids each is in the class of its own text; repeated
rows are repeated in the result; extra columns do not matter; no rows give no rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import discard, materialize, ship
from .joins import join_counted, only, without
from .textnum import Words, chunks, mix64, trim, unit, whole, windows, words

SHINGLE, SIMILARITY = 5, 0.8
#: So many nodes at most are broadcast to find their texts.
BROADCAST_TEXTS = 300_000
SLOTS, ROWS = 120, 5  # 24 bands: a pair at 0.8 is missed with probability 7e-5
_GAMMA, _SLOT = np.uint64(0x9E3779B97F4A7C15), np.uint64(0x5851F42D4C957F2D)


def shingles(w: Words, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct shingles of each row: (row, hash, count), ordered by row and hash."""
    h, fits = windows(w, size)
    doc = w.doc[fits]
    h = h[fits]
    short = np.flatnonzero((w.count > 0) & (w.count < size))
    if len(short):
        doc, h = np.concatenate([doc, short]), np.concatenate([h, whole(w, 7)[short]])
    order = np.lexsort((h, doc))
    doc, h = doc[order], h[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (doc[1:] != doc[:-1])
    at = np.flatnonzero(new)
    return doc[at], h[at], np.diff(np.append(at, len(h)))


def signatures(doc: np.ndarray, h: np.ndarray, count: np.ndarray, n: int, slots: int = SLOTS) -> np.ndarray:
    """(n, slots) winners of the slots; rows without shingles are 0."""
    out = np.zeros((n, slots), np.uint64)
    total = np.bincount(doc, weights=count, minlength=n)
    todo = total > 0
    horizon = np.where(todo, slots * (np.log(slots) + 4.0) / np.maximum(total, 1), 0.0)
    use = np.arange(len(h))
    while todo.any():
        d, e, rate, limit = doc[use], h[use], count[use].astype(float), horizon[doc[use]]
        t, k = np.zeros(len(d)), np.zeros(1, np.uint64)
        got: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(d):
            k += np.uint64(1)
            x = mix64(e + k * _GAMMA)
            t = t - np.log(unit(x)) / rate
            on = t <= limit
            d, e, rate, limit, t, x = d[on], e[on], rate[on], limit[on], t[on], x[on]
            slot = (mix64(x + _SLOT) >> np.uint64(32)) * np.uint64(slots) >> np.uint64(32)
            got.append((d * slots + slot.astype(np.int64), t, e))
        key, at, e = (np.concatenate(x) for x in zip(*got))
        order = np.lexsort((at, key))
        key, e = key[order], e[order]
        first = np.diff(key, prepend=-1) != 0
        key, e = key[first], e[first]
        filled = np.bincount(key // slots, minlength=n) == slots
        done = filled & todo
        mine = done[key // slots]
        out.reshape(-1)[key[mine]] = mix64(e[mine])
        todo &= ~done
        horizon = horizon * 2
        use = np.flatnonzero(todo[doc])
    return out


def _sketch(slots: int, rows: int):
    schema = pa.schema([("doc_id", pa.int64()), ("key", pa.int64()), ("fp1", pa.int64()), ("fp2", pa.int64()), ("bands", pa.list_(pa.int64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for c in chunks(b.column("text")):
                w = words(c)
                sig = signatures(*shingles(w), c.n, slots)
                band = np.zeros((c.n, slots // rows), np.uint64)
                for r in range(rows):
                    band = mix64(band * np.uint64(3) + sig[:, r :: rows])
                has = w.count > 0
                flat, size = band[has].astype(np.int64, copy=False).view(np.int64).reshape(-1), band.shape[1]
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(has * size)]).astype(np.int32)), pa.array(flat))
                yield pa.RecordBatch.from_arrays([
                    b.column("doc_id").slice(c.lo, c.n), b.column("key").slice(c.lo, c.n), pa.array(whole(w, 1).view(np.int64)), pa.array(whole(w, 2).view(np.int64)),
                    lists,
                ], schema=schema)
        trim()

    return run


def probability_jaccard(hx: np.ndarray, x: np.ndarray, hy: np.ndarray, y: np.ndarray) -> float:
    """Exact, from ascending shingle hashes and their counts."""
    every = np.union1d(hx, hy)
    fx, fy = np.zeros(len(every)), np.zeros(len(every))
    fx[np.searchsorted(every, hx)] = x
    fy[np.searchsorted(every, hy)] = y
    ratio = np.divide(fy, fx, out=np.full(len(every), np.inf), where=fx > 0)
    order = np.argsort(ratio, kind="stable")
    fx, fy, ratio = fx[order], fy[order], ratio[order]
    upto = np.searchsorted(ratio, ratio, "right")
    sx, sy = np.concatenate([[0], np.cumsum(fx)]), np.concatenate([[0], np.cumsum(fy)])
    both = (fx > 0) & (fy > 0)
    u = upto[both]
    return float((1.0 / (sx[u] / fx[both] + (sy[-1] - sy[u]) / fy[both])).sum())


def _sets(text: pa.ChunkedArray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Shingles of all rows of a column: (row, hash, count)."""
    parts = []
    for c in chunks(text):
        doc, h, n = shingles(words(c), size)
        parts.append((doc + c.lo, h, n))
    if not parts:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.int64)
    return tuple(np.concatenate(x) for x in zip(*parts))  # type: ignore[return-value]


def links(left: pa.ChunkedArray, right: pa.ChunkedArray, size: int, least: float, lids: np.ndarray | None = None, rids: np.ndarray | None = None) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For each row of ``left`` the rows of ``right`` at ``least`` or more, and their similarities.

    Three bounds, none of which loses a link. A shingle that only one text of the block holds is shared with none, so the
    shingles that a text can share bound what any two have in common: most pairs of much edited copies end
    there. Then, for the rest of a row's partners at once, the sum of min(x_d / X, y_d / Y) over shared shingles, which
    is no less than the similarity. Only what passes is worked out. Ids tell a text on both sides.
    """
    ld, lh, lx = _sets(left, size)
    rd, rh, ry = _sets(right, size)
    n, m = len(right), len(left)
    if not len(lh) or not len(rh):
        return
    known, at = np.unique(np.concatenate([rh, lh]), return_inverse=True)
    rk, lk = at[: len(rh)], at[len(rh) :]
    twin = np.isin(lids, rids) if lids is not None and rids is not None else np.zeros(m, bool)
    common = np.bincount(rk, minlength=len(known)) + np.bincount(lk[~twin[ld]], minlength=len(known)) > 1

    def sizes(doc: np.ndarray, x: np.ndarray, k: np.ndarray, rows: int):
        total = np.maximum(np.bincount(doc, weights=x, minlength=rows), 1)
        most = np.ones(rows)
        np.maximum.at(most, doc, x)
        return np.bincount(doc, minlength=rows), np.bincount(doc, weights=common[k], minlength=rows), np.bincount(doc, weights=x * common[k], minlength=rows) / total, most, np.searchsorted(doc, np.arange(rows + 1)), total

    rn, rs, rf, rmost, rat, rtotal = sizes(rd, ry, rk, n)
    ln, ls, lf, lmost, lat, _ = sizes(ld, lx, lk, m)
    share = ry / rtotal[rd]
    weight = np.zeros(len(known))
    for i in np.flatnonzero((ln > 0) & (lf >= least - 1e-9)):
        both = np.minimum(ls[i], rs)
        plain = (rmost <= 1) & (lmost[i] <= 1)
        may = np.where(plain, both >= (least - 1e-9) * (ln[i] + rn - both), rf >= least - 1e-9) & (rn > 0)
        cand = np.flatnonzero(may)
        if not len(cand):
            continue
        length = rat[cand + 1] - rat[cand]
        own = np.arange(length.sum()) + np.repeat(rat[cand] - (np.cumsum(length) - length), length)
        of = np.repeat(np.arange(len(cand)), length)
        h, x = lh[lat[i] : lat[i + 1]], lx[lat[i] : lat[i + 1]]
        k = lk[lat[i] : lat[i + 1]]
        weight[k] = x / x.sum()
        w = weight[rk[own]]
        weight[k] = 0
        near = np.bincount(of, weights=np.minimum(w, share[own]), minlength=len(cand)) >= least - 1e-9
        shared = np.bincount(of, weights=w > 0, minlength=len(cand))
        sim = shared / (ln[i] + rn[cand] - shared)
        for j in np.flatnonzero(near & ~plain[cand]):
            a, b = rat[cand[j]], rat[cand[j] + 1]
            sim[j] = probability_jaccard(h, x, rh[a:b], ry[a:b])
        ok = near & (sim >= least - 1e-12)
        if ok.any():
            yield int(i), cand[ok], sim[ok]


def _verify(size: int, least: float):
    def run(key: tuple[pa.Scalar, ...], leader: pa.Table, members: pa.Table) -> pa.Table:
        b, s = np.zeros(0, np.int64), np.zeros(0)
        for _, j, s in links(leader["text"].slice(0, 1), members["text"], size, least):
            b = members["b"].to_numpy()[j]
        return pa.table({"a": pa.array(np.full(len(b), key[0].as_py() or 0), pa.int64()), "b": pa.array(b, pa.int64()), "similarity": pa.array(s, pa.float64())})

    return run


def verify_pairs(texts: DataFrame, pairs: DataFrame, size: int = SHINGLE, least: float = SIMILARITY, per_task: int = 64) -> DataFrame:
    """``pairs(a, b)`` of nodes with the exact similarity of their ``texts(node, text)`` where it is ``least`` or more.

    A text that leads many pairs is sent once for each ``per_task`` of them.
    """
    ship(texts.sparkSession)
    salts = pairs.groupBy("a").agg(F.count("*").alias("n")).withColumn("salts", F.ceil(F.col("n") / per_task)).select("a", "salts")
    keyed = pairs.join(salts, "a").select("a", F.pmod(F.xxhash64("b"), F.col("salts")).alias("salt"), "b")
    left = keyed.select("a", "salt").distinct().join(texts.withColumnRenamed("node", "a"), "a")
    right = keyed.join(texts.withColumnRenamed("node", "b"), "b")
    left, right = left.select("a", "salt", "text").toDF("a1", "salt1", "text"), right.select("a", "salt", "b", "text").toDF("a2", "salt2", "b", "text")
    return left.groupBy("a1", "salt1").cogroup(right.groupBy("a2", "salt2")).applyInArrow(_verify(size, least), "a long, b long, similarity double")


def connected_components(edges: DataFrame, name: str = "cc") -> DataFrame:
    """``edges(a, b)`` to (node, component), the component being its least node: stars contracted until nothing moves."""

    def star(e: DataFrame, large: bool) -> DataFrame:
        if large:
            both = e.union(e.select(F.col("b"), F.col("a"))).toDF("u", "v")
        else:
            both = e.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        out = both.join(least, "u")
        moved = out.where("v > u").select(F.col("v"), "m") if large else out.select("v", "m").union(least.select(F.col("u"), "m"))
        return moved.where("v <> m").toDF("a", "b").distinct()

    def mark(e: DataFrame) -> tuple:
        return tuple(e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    now = materialize(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), name)
    seen = mark(now)
    while True:
        nxt = materialize(star(star(now, True), False), name)
        told = mark(nxt)
        discard(now)
        now = nxt
        if told == seen:
            break
        seen = told
    return materialize(now.select(F.col("a").alias("node"), F.col("b").alias("component")).union(now.select("b", "b").distinct()), name)


def _compare(size: int, least: float):
    """Links between stragglers and members of one block whose components differ."""

    def run(key: tuple[pa.Scalar, ...], left: pa.Table, right: pa.Table) -> pa.Table:
        a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        if left.num_rows and right.num_rows:
            ids, comp = ([t[c].to_numpy() for t in (left, right)] for c in ("node", "component"))
            for i, j, _ in links(left["text"], right["text"], size, least, *ids):
                j = j[comp[1][j] != comp[0][i]]
                j = j[np.unique(comp[1][j], return_index=True)[1]]  # one link joins two components
                a.append(np.minimum(ids[1][j], ids[0][i])), b.append(np.maximum(ids[1][j], ids[0][i]))
        return pa.table({"a": pa.array(np.concatenate(a)), "b": pa.array(np.concatenate(b))})

    return run


def _straggler_links(texts: DataFrame, open_: DataFrame, size: int, least: float, block: int) -> DataFrame:
    """Verified links (a, b) between each member outside its bucket's main component and all members of the bucket."""
    rows = open_.join(texts, "node")
    n_i, n_j = (F.ceil(F.col(c) / block).cast("int") for c in ("strays", "n"))
    of = lambda n: F.pmod(F.xxhash64("node"), n).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), n - 1))
    left = rows.where("component <> main").select("band", "value", of(n_i).alias("i"), every(n_j).alias("j"), "node", "component", "text")
    right = rows.select("band", "value", every(n_i).alias("i"), of(n_j).alias("j"), "node", "component", "text")
    left, right = left.toDF("b1", "v1", "i1", "j1", "node", "component", "text"), right.toDF("b2", "v2", "i2", "j2", "node", "component", "text")
    return left.groupBy("b1", "v1", "i1", "j1").cogroup(right.groupBy("b2", "v2", "i2", "j2")).applyInArrow(_compare(size, least), "a long, b long").distinct()


def _row_key() -> Column:
    """Tells rows with equal ids apart."""
    return F.xxhash64("text")


def _sketched(docs: DataFrame, slots: int, rows: int) -> tuple[DataFrame, DataFrame]:
    """The rows to be compared (doc_id, key, text), and their sketches, written."""
    ship(docs.sparkSession)
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), _row_key().alias("key"), "text")
    return docs, materialize(docs.mapInArrow(_sketch(slots, rows), "doc_id long, key long, fp1 long, fp2 long, bands array<long>"), "sketch")


def _classes(docs: DataFrame, sketch: DataFrame, size: int, least: float, block: int) -> DataFrame:
    """One row for each distinct word sequence: (fp1, fp2, n, rep_id, class_id, class_key); n of its rows, and the first row of its class."""
    first = F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "key")  # rows with an id come first
    texts = sketch.where("size(bands) > 0").groupBy("fp1", "fp2").agg(F.min(first).alias("first"), F.count("*").alias("n"))
    texts = materialize(texts, "texts")
    own = texts.select(F.col("fp1").alias("node"), F.col("first.key").alias("key"), F.col("first.doc_id").alias("id"))
    bands = sketch.join(own, (sketch.key == own.key) & sketch.doc_id.eqNullSafe(own.id)).where(F.col("fp1") == F.col("node"))
    bands = materialize(bands.select("node", "bands").dropDuplicates(["node"]), "bands")

    each = bands.select("node", F.posexplode("bands").alias("band", "value"))
    leaders = each.groupBy("band", "value").agg(F.min("node").alias("lead"), F.count("*").alias("n")).where("n > 1")
    hot = materialize(each.join(leaders, ["band", "value"]), "buckets")
    discard(bands)
    pairs = materialize(hot.where("node <> lead").select(F.col("lead").alias("a"), F.col("node").alias("b")).distinct(), "pairs")

    def of(nodes: DataFrame) -> DataFrame:
        """(node, text) of some nodes; the row is found by its id and key."""
        wanted = materialize(own.join(nodes.distinct(), "node", "left_semi"), "wanted")
        side = F.broadcast(wanted) if wanted.count() <= BROADCAST_TEXTS else wanted
        return docs.join(side, (docs.key == side.key) & docs.doc_id.eqNullSafe(side.id)).select("node", "text").dropDuplicates(["node"])

    edges = materialize(verify_pairs(of(pairs.select(F.col("a").alias("node")).union(pairs.select("b"))), pairs, size, least).select("a", "b"), "edges")
    comp = connected_components(edges)

    # Buckets that are not yet one component.
    told = hot.drop("n", "lead").join(comp, "node", "left").withColumn("component", F.coalesce("component", "node"))
    parts = told.groupBy("band", "value", "component").agg(F.count("*").alias("k"))
    most = parts.groupBy("band", "value").agg(F.max(F.struct("k", F.negative("component").alias("c"))).alias("top"), F.count("*").alias("parts"), F.sum("k").alias("n")).where("parts > 1")
    most = most.select("band", "value", F.negative("top.c").alias("main"), "n", (F.col("n") - F.col("top.k")).alias("strays"))
    open_ = materialize(told.join(most, ["band", "value"]).select("band", "value", "node", "component", "main", "n", "strays"), "open")
    more = _straggler_links(of(open_.select("node")), open_, size, least, block)
    all_edges = materialize(more.union(comp.where("node <> component").select("component", "node")), "edges")
    comp = connected_components(all_edges)
    for t in (hot, pairs, edges, open_, all_edges):
        discard(t)

    linked = texts.join(comp.withColumnRenamed("node", "fp1"), "fp1")
    lead = linked.groupBy("component").agg(F.min("first").alias("lead"), F.count("*").alias("k"))
    linked = join_counted(linked.select("fp1", "component"), lead, ["component"], "k").select("fp1", "lead")
    named = texts.join(linked, "fp1", "left").withColumn("lead", F.coalesce("lead", "first"))
    return named.select("fp1", "fp2", "n", F.col("first.doc_id").alias("rep_id"), F.col("lead.doc_id").alias("class_id"), F.col("lead.key").alias("class_key"))


def near_duplicates(docs: DataFrame, slots: int = SLOTS, rows: int = ROWS, size: int = SHINGLE, least: float = SIMILARITY, block: int = 256) -> DataFrame:
    """``docs(doc_id, text, ...)`` to (doc_id, class_id, rep_id): the least id of the class, and of the equal texts."""
    docs, sketch = _sketched(docs, slots, rows)
    classes = materialize(_classes(docs, sketch, size, least, block).drop("class_key"), "classes")
    found = join_counted(sketch.where("size(bands) > 0").select("doc_id", "fp1", "fp2"), classes, ["fp1", "fp2"])
    alone = sketch.where("size(bands) = 0").select("doc_id", F.col("doc_id").alias("class_id"), F.col("doc_id").alias("rep_id"))
    return found.select("doc_id", "class_id", "rep_id").unionByName(alone)


def one_of_each(docs: DataFrame, slots: int = SLOTS, rows: int = ROWS, size: int = SHINGLE, least: float = SIMILARITY, block: int = 256) -> DataFrame:
    """``docs`` with one row of each class: that with the least id (a null id last, ties by a hash of the text; of equal rows any one).

    Rows without a word stay, each for itself.
    """
    own, sketch = _sketched(docs, slots, rows)
    classes = materialize(_classes(own, sketch, size, least, block), "classes")
    told = join_counted(sketch.where("size(bands) > 0").select("doc_id", "key", "fp1", "fp2"), classes, ["fp1", "fp2"])
    first = F.col("doc_id").eqNullSafe(F.col("class_id")) & (F.col("key") == F.col("class_key"))
    rows_ = told.groupBy("doc_id", "key").agg(F.max(first).alias("first"), F.count("*").alias("k"))
    rows_ = materialize(rows_.where("not first or k > 1").select(F.col("doc_id").alias("_id"), F.col("key").alias("_key"), "first"), "not-first")
    same = F.col("_row_id").eqNullSafe(F.col("_id")) & (F.col("_row_key") == F.col("_key"))
    keyed = docs.withColumn("_row_id", F.col("doc_id").cast("long")).withColumn("_row_key", _row_key())
    kept = without(keyed, rows_, same)
    if not rows_.where("first").isEmpty():  # equal rows
        kept = kept.unionByName(only(keyed, rows_.where("first"), same).dropDuplicates(["_row_id", "_row_key"]))
    return kept.select(*docs.columns)
