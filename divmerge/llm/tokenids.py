"""Token ids in patched frame-of-reference files.

A *segment* is one file image: a header, the document table, the index of block starts, and blocks of 256 ids. A block
stores its least id, a bit width chosen as that of a percentile of the differences, the packed low bits, and a list of
exceptions (position, high part) for the differences that need more. Any block can be decoded alone from the index.

Layout, little-endian: ``PFR1``, u32 documents, u32 blocks, u32 ids in the last block, u64 ids; i64 ids of the
documents; u32 lengths; u64 block starts (one more than blocks, from the first block); then for each block u32 least,
u8 width, u8 zero, u16 exceptions, the packed words (u64, 4 x width), exception positions (u8) and values (u32).

Segments are written by Spark's own committer, as rows of one binary column beside (part, seg), so a lost or repeated
task leaves no half file and any store Spark writes to will do. Rows are dealt by ranges of the id and sorted, so
segments in order of (part, seg) hold the documents in ascending id order.

Words are encoded once for each worker, where the tokenizer never joins text across ASCII white space and cuts words before their
trailing marks: the ids of a text are then those of its words in turn. Each worker tries this on ``PROBE`` when it loads a file;
a tokenizer that does otherwise gets whole texts.

Defined results: null and empty texts have the end id alone; null ids come first; rows with equal ids are ordered by text;
extra columns do not matter.
"""

from __future__ import annotations

import os
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import scratch, ship
from .textnum import WORD_CHUNK_BYTES, Chunk, Words, chunks, prefix_hash, span_hash, words

MAGIC, BLOCK = b"PFR1", 256
PERCENTILE = 0.97
SEGMENT_IDS = 1 << 20
NULL_ID = -(1 << 63)
#: Spacing, marks, digits, capitals and other scripts in the ways that tokenizers differ in.
PROBE = "The cat's 12 mats,  don't\tLIE... here!? a.b c_d 3.5% (x) [y] <z>\n\n\u00c9t\u00e9, na\u00efve: \u6f22\u5b57 \U0001f600! end.\r\n#tag @me $5 & |so on| -- \u201cq\u201d w;;  "
_HEAD = struct.Struct("<4sIIIQ")
_BLOCK = struct.Struct("<IBBH")


def _bits(x: np.ndarray) -> np.ndarray:
    """Bit lengths."""
    return np.frexp(x.astype(np.float64))[1].astype(np.int64)


def _pack(low: np.ndarray, width: int) -> np.ndarray:
    """(k, 256) of ``width``-bit values to (k, 4 * width) words."""
    cols = np.ascontiguousarray(low.T)
    out = np.zeros((4 * width, low.shape[0]), np.uint64)
    for i in range(BLOCK if width else 0):
        at, shift = divmod(i * width, 64)
        out[at] |= cols[i] << np.uint64(shift)
        if shift + width > 64:
            out[at + 1] |= cols[i] >> np.uint64(64 - shift)
    return np.ascontiguousarray(out.T)


def _unpack(packed: np.ndarray, width: int) -> np.ndarray:
    cols = np.ascontiguousarray(packed.T)
    out = np.zeros((BLOCK, packed.shape[0]), np.uint64)
    mask = np.uint64((1 << width) - 1)
    for i in range(BLOCK if width else 0):
        at, shift = divmod(i * width, 64)
        x = cols[at] >> np.uint64(shift)
        if shift + width > 64:
            x = x | cols[at + 1] << np.uint64(64 - shift)
        out[i] = x & mask
    return np.ascontiguousarray(out.T)


def encode_segment(doc_ids: np.ndarray, lengths: np.ndarray, ids: np.ndarray, percentile: float = PERCENTILE) -> bytes:
    """Documents' ids (all in one array) to a file image."""
    n = len(ids)
    k = -(-n // BLOCK)
    grid = np.empty(k * BLOCK, np.uint64)
    grid[:n] = ids
    grid[n:] = ids[-1] if n else 0
    grid = grid.reshape(k, BLOCK)
    least = grid.min(1) if k else np.zeros(0, np.uint64)
    diff = grid - least[:, None]
    rank = min(BLOCK - 1, int(percentile * BLOCK))
    width = _bits(np.partition(diff, rank, 1)[:, rank]) if k else np.zeros(0, np.int64)
    high = diff >> width.astype(np.uint64)[:, None]
    over = high != 0
    n_over = over.sum(1)
    bodies: list[bytes] = [b""] * k
    for w in np.unique(width):
        rows = np.flatnonzero(width == w)
        packed = _pack(diff[rows] & np.uint64((1 << int(w)) - 1), int(w))
        for r, p in zip(rows, packed):
            bodies[r] = p.tobytes()
    row, pos = np.nonzero(over)
    value = high[row, pos].astype("<u4")
    pos = pos.astype(np.uint8)
    border = np.concatenate([[0], np.cumsum(n_over)])
    blocks = []
    for r in range(k):
        a, b = border[r], border[r + 1]
        blocks.append(_BLOCK.pack(int(least[r]), int(width[r]), 0, b - a) + bodies[r] + pos[a:b].tobytes() + value[a:b].tobytes())
    starts = np.concatenate([[0], np.cumsum([len(x) for x in blocks])]).astype("<u8")
    last = n - (k - 1) * BLOCK if k else 0
    return b"".join([_HEAD.pack(MAGIC, len(doc_ids), k, last, n), doc_ids.astype("<i8").tobytes(), lengths.astype("<u4").tobytes(), starts.tobytes(), *blocks])


class Segment:
    """Reader of one file image."""

    def __init__(self, data: bytes) -> None:
        magic, docs, self.blocks, self.last, self.n = _HEAD.unpack_from(data)
        if magic != MAGIC:
            raise ValueError("not a PFR1 segment")
        at = _HEAD.size
        self.doc_ids = np.frombuffer(data, "<i8", docs, at)
        self.lengths = np.frombuffer(data, "<u4", docs, at + 8 * docs).astype(np.int64)
        self.starts = np.frombuffer(data, "<u8", self.blocks + 1, at + 12 * docs).astype(np.int64)
        self.first = at + 12 * docs + 8 * (self.blocks + 1)
        self.data = np.frombuffer(data, np.uint8)
        if self.first + int(self.starts[-1]) != len(data):
            raise ValueError("segment cut short")

    def ids(self, lo: int = 0, hi: int | None = None) -> np.ndarray:
        """Ids of blocks lo..hi; only these blocks are read."""
        hi = self.blocks if hi is None else min(hi, self.blocks)
        at = self.first + self.starts[lo:hi]
        head = self.data[at[:, None] + np.arange(8)]
        least = head[:, :4].copy().view("<u4")[:, 0].astype(np.uint64)
        width, n_over = head[:, 4].astype(np.int64), head[:, 6:8].copy().view("<u2")[:, 0].astype(np.int64)
        out = np.empty((hi - lo, BLOCK), np.uint64)
        for w in np.unique(width):
            rows = np.flatnonzero(width == w)
            packed = self.data[(at[rows] + 8)[:, None] + np.arange(32 * w)].copy().view("<u8")
            out[rows] = _unpack(packed, int(w))
        row = np.repeat(np.arange(hi - lo), n_over)
        k = np.arange(len(row)) - np.repeat(np.cumsum(n_over) - n_over, n_over)
        tail = at + 8 + 32 * width
        pos = self.data[tail[row] + k]
        value = self.data[(tail[row] + n_over[row] + 4 * k)[:, None] + np.arange(4)].copy().view("<u4").reshape(-1).astype(np.uint64)
        out[row, pos] |= value << width[row].astype(np.uint64)
        out += least[:, None]
        flat = out.reshape(-1)
        return flat[: len(flat) - BLOCK + self.last] if hi == self.blocks and self.blocks else flat

    def document(self, i: int) -> np.ndarray:
        """Ids of the i-th document, from its own blocks."""
        a = int(self.lengths[:i].sum())
        b = a + int(self.lengths[i])
        lo = a // BLOCK
        return self.ids(lo, -(-b // BLOCK))[a - lo * BLOCK : b - lo * BLOCK]


_TAIL, _ALNUM = np.zeros(256, bool), np.zeros(256, bool)
_TAIL[list(b".,;:!?|*#$%&")] = True
_ALNUM[[*range(48, 58), *range(65, 91), *range(97, 123)]] = True


def spans(c: Chunk) -> Words:
    """Words, those that end in marks after a letter or digit cut there: the tokenizer cuts there too, and far fewer spans are distinct."""
    w = words(c, hashed=False)
    core = w.end.copy()
    for _ in range(8):
        more = np.flatnonzero((core - w.start > 1) & _TAIL[c.data[core - 1]])
        if not len(more):
            break
        core[more] -= 1
    last, before = c.data[core - 1], c.data[np.maximum(core - 2, 0)]
    latin = (before == 0xC3) & (last >= 0x80) & (last != 0x97) & (last != 0xB7) & (core - w.start > 1)
    cut = (core < w.end) & (_ALNUM[last] | latin)
    n = 1 + cut
    at = np.cumsum(n) - n
    start, end = np.repeat(w.start, n), np.repeat(w.end, n)
    end[at[cut]] = start[at[cut] + 1] = core[cut]
    first = np.concatenate([[0], np.cumsum(n)])[w.first]
    return Words(start, end, first, span_hash(prefix_hash(c.data), start, end))


class WordIds:
    """Ids of words, kept for a worker's life in sorted hash arrays; emptied when it holds ``most`` words."""

    def __init__(self, path: str, most: int = 1_500_000) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tok, self.most = Tokenizer.from_file(path), most
        specials = {t.content: i for i, t in self.tok.get_added_tokens_decoder().items() if not t.normalized}
        self.mark, self.mark_id = next(iter(specials.items()), (None, -1))
        self._clear()
        col, self.by_words = pa.array([PROBE, PROBE.strip(), "a b", " "]), True
        probe = next(chunks(col))
        flat, size = self(probe, spans(probe))
        whole = [i for e in self.tok.encode_batch_fast(col.to_pylist(), add_special_tokens=False) for i in e.ids]
        self.by_words = flat.tolist() == whole

    def _clear(self) -> None:
        self.hash, self.at, self.size, self.flat = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)

    def encode_words(self, found: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words, and how many each has. Words are sent together, parted by a special token that none of them holds."""
        if self.mark is None or any(self.mark in x for x in found):
            got = [e.ids for e in self.tok.encode_batch_fast(found, add_special_tokens=False)]
            return np.array([i for x in got for i in x], np.uint32), np.array(list(map(len, got)), np.int64)
        flat, size = [], []
        for e in self.tok.encode_batch_fast([self.mark.join(found[lo : lo + 512]) for lo in range(0, len(found), 512)], add_special_tokens=False):
            ids = np.array(e.ids, np.uint32)
            cut = np.flatnonzero(ids == self.mark_id)
            size.append(np.diff(np.concatenate([[-1], cut, [len(ids)]])) - 1)
            flat.append(np.delete(ids, cut))
        return np.concatenate(flat), np.concatenate(size)

    def texts(self, c: Chunk) -> tuple[np.ndarray, np.ndarray]:
        """For a chunk: its ids, and how many each row has."""
        if self.by_words:
            w = spans(c)
            flat, size = self(c, w)
            total = np.concatenate([[0], np.cumsum(size)])
            return flat, total[w.first[1:]] - total[w.first[:-1]]
        got = [e.ids for e in self.tok.encode_batch_fast([c.text(i).decode() for i in range(c.n)], add_special_tokens=False)]
        return np.array([i for x in got for i in x], np.uint32), np.array(list(map(len, got)), np.int64)

    def __call__(self, c, w) -> tuple[np.ndarray, np.ndarray]:
        """For a chunk: its ids, and how many each word has."""
        u, first, inverse = np.unique(w.hash, return_index=True, return_inverse=True)
        where = np.searchsorted(self.hash, u)
        known = np.zeros(len(u), bool)
        if len(self.hash):
            known = self.hash[np.minimum(where, len(self.hash) - 1)] == u
        if not known.all():
            if len(self.hash) + (~known).sum() > self.most:
                self._clear()
                known[:] = False
            new = first[~known]
            data = c.data.tobytes()
            flat, size = self.encode_words([data[a:b].decode("utf-8", "replace") for a, b in zip(w.start[new].tolist(), w.end[new].tolist())])
            at = len(self.flat) + np.cumsum(size) - size
            self.hash = np.concatenate([self.hash, u[~known]])
            order = np.argsort(self.hash, kind="stable")
            self.hash, self.at, self.size = self.hash[order], np.concatenate([self.at, at])[order], np.concatenate([self.size, size])[order]
            self.flat = np.concatenate([self.flat, flat])
            where = np.searchsorted(self.hash, u)
        at, size = self.at[where][inverse], self.size[where][inverse]
        end = np.cumsum(size)
        index = np.arange(end[-1] if len(end) else 0) + np.repeat(at - (end - size), size)
        return self.flat[index], size


_caches: dict[str, WordIds] = {}


def word_ids(path: str) -> WordIds:
    if path not in _caches:
        _caches[path] = WordIds(path)
    return _caches[path]


def _write(path: str, end_id: int, most: int, percentile: float):
    schema = pa.schema([("part", pa.int32()), ("seg", pa.int32()), ("n_ids", pa.int64()), ("segment", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, seg = TaskContext.get().partitionId(), 0
        encode = word_ids(path)
        docs: list[np.ndarray] = []
        sizes: list[np.ndarray] = []
        ids: list[np.ndarray] = []
        held = 0

        def out() -> pa.RecordBatch:
            image = encode_segment(np.concatenate(docs), np.concatenate(sizes), np.concatenate(ids), percentile)
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([seg], pa.int32()), pa.array([held], pa.int64()), pa.array([image], pa.binary())], schema=schema)

        for b in batches:
            key = b.column("doc_id").fill_null(NULL_ID).to_numpy(zero_copy_only=False)
            for c in chunks(b.column("text"), WORD_CHUNK_BYTES):
                flat, size = encode.texts(c)
                full = np.insert(flat, np.cumsum(size), np.uint32(end_id))  # the end id after each document
                docs.append(key[c.lo : c.hi]), sizes.append(size + 1), ids.append(full)
                held += len(full)
                if held >= most:
                    yield out()
                    docs, sizes, ids, held, seg = [], [], [], 0, seg + 1
        if docs:
            yield out()

    return run


def write_token_files(docs: DataFrame, tokenizer: str, path: str, end_id: int = 2, most: int = SEGMENT_IDS, percentile: float = PERCENTILE) -> None:
    """Encode ``docs(doc_id, text)`` and write segments (part, seg, n_ids, segment) under ``path``."""
    ship(docs.sparkSession)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    done = rows.mapInArrow(_write(tokenizer, end_id, most, percentile), "part int, seg int, n_ids long, segment binary")
    done.write.option("compression", "uncompressed").parquet(path)


def segment_starts(spark: SparkSession, path: str) -> DataFrame:
    """(part, seg, before): ids in all segments before each; first over parts, then inside a part."""
    seg = spark.read.parquet(path).select("part", "seg", "n_ids")
    seg.createOrReplaceTempView("_segments")
    return spark.sql("""
        WITH parts AS (SELECT part, sum(sum(n_ids)) OVER (ORDER BY part) - sum(n_ids) AS base FROM _segments GROUP BY part)
        SELECT s.part, s.seg, p.base + sum(n_ids) OVER (PARTITION BY s.part ORDER BY s.seg) - n_ids AS before FROM _segments s JOIN parts p ON s.part = p.part""")


def _read(with_ids: bool):
    names = ["part", "seg", "doc_id", "local", "n_tokens", "ids_crc32"] + ["ids"] * with_ids

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for i in range(b.num_rows):
                s = Segment(b.column("segment")[i].as_py())
                ids = s.ids().astype("<u4")
                end = np.cumsum(s.lengths)
                begin = end - s.lengths
                raw = memoryview(ids.tobytes())
                crc = [zlib.crc32(raw[4 * x : 4 * y]) for x, y in zip(begin.tolist(), end.tolist())]
                n = len(s.doc_ids)
                cols = [pa.array([b.column(k)[i].as_py()] * n, pa.int32()) for k in ("part", "seg")]
                cols += [pa.array(s.doc_ids, pa.int64(), mask=s.doc_ids == NULL_ID), pa.array(begin), pa.array(s.lengths), pa.array(crc, pa.int64())]
                if with_ids:
                    cols.append(pa.ListArray.from_arrays(pa.array(np.append(begin, end[-1:]).astype(np.int32)), pa.array(ids.astype(np.int32))))
                yield pa.RecordBatch.from_arrays(cols, names=names)

    return run


def read_token_files(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32[, ids]) of each document, from the files."""
    ship(spark)
    schema = "part int, seg int, doc_id long, local long, n_tokens long, ids_crc32 long" + ", ids array<int>" * with_ids
    rows = spark.read.parquet(path).select("part", "seg", "segment").mapInArrow(_read(with_ids), schema)
    found = rows.join(segment_starts(spark, path), ["part", "seg"])
    return found.select("doc_id", (F.col("before") + F.col("local")).alias("start"), "n_tokens", "ids_crc32", *["ids"] * with_ids)


def token_files(docs: DataFrame, tokenizer: str, end_id: int = 2, path: str | None = None) -> DataFrame:
    """Write all documents' ids and read them back."""
    spark = docs.sparkSession
    path = path or scratch(spark, "token-files")
    write_token_files(docs, tokenizer, path, end_id)
    return read_token_files(spark, path)
