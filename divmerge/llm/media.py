"""PNG media columns: encode bytes as 8-bit samples, read PNG back with checksum tests, and hash low cosine frequencies.

The reader walks the chunks of a file, tests each CRC, inflates the image data and undoes the row filters with numpy.
It reads 8-bit grey, grey-alpha, RGB and RGBA images without interlacing; anything else, and any damage, is a
``PngError`` (in :func:`read_media`: a row with a null image and the reason).

The feature is a 64-bit perceptual hash: luma, averaged down to 32 x 32, two-dimensional cosine transform, the 8 x 8
lowest frequencies, one bit for each above their median.

Rows are filtered one by one with that of the allowed filters which leaves the least sum of absolute differences, and the
filters are undone with numpy: row-wise sums for the left filter, column-wise sums for the one above, and for the other two, whose
pixels wait for their neighbours, all pixels of a diagonal at once.

Defined results: null and empty texts are a payload of one row of spaces; a text of any length is one image; equal texts give
equal rows; extra columns do not matter. Every step is narrow: no row leaves its partition.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.types import StructType

from ..session import ship

SIGNATURE = b"\x89PNG\r\n\x1a\n"
CHANNELS = {0: 1, 2: 3, 4: 2, 6: 4}  # colour type: samples a pixel; fixed values of the format
WIDTH = 64
ROW_BYTES = WIDTH * 3
SIDE, LOW = 32, 8
#: Row filters of written images: those undone by sums. The reader undoes all five.
WRITTEN = (0, 1, 2)


class PngError(ValueError):
    pass


def _chunk(kind: bytes, body: bytes) -> bytes:
    return struct.pack(">I", len(body)) + kind + body + struct.pack(">I", zlib.crc32(body, zlib.crc32(kind)))


def _residues(rows: np.ndarray, bpp: int, kind: int) -> np.ndarray:
    """All rows under one filter: 0 none, 1 left, 2 above, 3 mean of both, 4 nearest of three. Bytes wrap."""
    if kind == 0:
        return rows
    out = rows.copy()
    if kind == 1:
        out[:, bpp:] -= rows[:, :-bpp]
        return out
    if kind == 2:
        out[1:] -= rows[:-1]
        return out
    up = np.vstack([np.zeros_like(rows[:1]), rows[:-1]]).astype(np.int16)
    left, corner = np.zeros_like(up), np.zeros_like(up)
    left[:, bpp:], corner[:, bpp:] = rows[:, :-bpp], up[:, :-bpp]
    return (rows - ((left + up) >> 1 if kind == 3 else _nearest(left, up, corner))).astype(np.uint8)


def filter_rows(rows: np.ndarray, bpp: int, kinds: np.ndarray) -> np.ndarray:
    """Apply row filter ``kinds[i]`` to each row."""
    out = np.empty_like(rows)
    for k in np.unique(kinds):
        out[kinds == k] = _residues(rows, bpp, int(k))[kinds == k]
    return out


def _nearest(a: np.ndarray, b: np.ndarray, c: np.ndarray) -> np.ndarray:
    """Of left, above and corner, the one nearest to left + above - corner; ties in that order."""
    pa_, pb, pc = np.abs(b - c), np.abs(a - c), np.abs(a + b - 2 * c)
    return np.where((pa_ <= pb) & (pa_ <= pc), a, np.where(pb <= pc, b, c))


def _diagonals(raw: np.ndarray, kinds: np.ndarray, above: np.ndarray) -> np.ndarray:
    """Undo filters 3 and 4 over a run of rows (rows, pixels, samples): a pixel needs its left, above and corner, so a diagonal is done at once."""
    n, width, bpp = raw.shape
    out = np.zeros((n + 1, width + 1, bpp), np.int16)
    out[0, 1:] = above
    mean = (kinds == 3)[:, None]
    for t in range(n + width - 1):
        i = np.arange(max(0, t - width + 1), min(n, t + 1))
        x = t - i
        a, b, c = out[i + 1, x], out[i, x + 1], out[i, x]
        out[i + 1, x + 1] = (raw[i, x] + np.where(mean[i], (a + b) >> 1, _nearest(a, b, c))) & 255
    return out[1:, 1:].astype(np.uint8)


def unfilter_rows(rows: np.ndarray, bpp: int, kinds: np.ndarray) -> np.ndarray:
    """Undo :func:`filter_rows`: left filters of all rows first, then from above to below the runs that lean on the row above."""
    if (kinds > 4).any():
        raise PngError("unknown row filter")
    out = rows.copy()
    n, width = rows.shape
    if len(on := np.flatnonzero(kinds == 1)):
        out[on] = np.cumsum(rows[on].reshape(len(on), width // bpp, bpp), 1, dtype=np.uint8).reshape(len(on), width)
    group = np.array([0, 0, 1, 2, 2])[kinds]
    edges = np.flatnonzero(np.diff(group, prepend=-1))
    for a, b in zip(edges.tolist(), [*edges[1:].tolist(), n]):
        if group[a] == 1:
            out[a:b] = np.cumsum(np.vstack([out[a - 1 : a], rows[a:b]]) if a else rows[a:b], 0, dtype=np.uint8)[1 if a else 0 :]
        elif group[a] == 2:
            above = (out[a - 1] if a else np.zeros(width, np.uint8)).reshape(-1, bpp)
            out[a:b] = _diagonals(rows[a:b].reshape(b - a, -1, bpp).astype(np.int16), kinds[a:b], above).reshape(b - a, width)
    return out


def choose_filters(rows: np.ndarray, bpp: int, allowed: tuple[int, ...] = (0, 1, 2, 3, 4)) -> tuple[np.ndarray, np.ndarray]:
    """For each row the allowed filter with the least sum of absolute differences (ties: the first), and the rows under it."""
    every = [_residues(rows, bpp, k) for k in allowed]
    at = np.argmin([np.minimum(r, 0 - r).sum(1, dtype=np.int64) for r in every], 0)
    return np.array(allowed)[at], np.stack(every)[at, np.arange(len(rows))]


def encode_png(samples: np.ndarray, filters: tuple[int, ...] = (0, 1, 2, 3, 4), level: int = 1) -> bytes:
    """(height, width, channels) of 8-bit samples to a PNG file, each row under one of ``filters``."""
    h, w, c = samples.shape
    colour = {v: k for k, v in CHANNELS.items()}[c]
    body = np.empty((h, w * c + 1), np.uint8)
    body[:, 0], body[:, 1:] = choose_filters(samples.reshape(h, w * c), c, filters)
    return SIGNATURE + _chunk(b"IHDR", struct.pack(">IIBBBBB", w, h, 8, colour, 0, 0, 0)) + _chunk(b"IDAT", zlib.compress(body.tobytes(), level)) + _chunk(b"IEND", b"")


def decode_png(data: bytes) -> np.ndarray:
    """A PNG file to (height, width, channels) of 8-bit samples."""
    if data[:8] != SIGNATURE:
        raise PngError("no PNG signature")
    at, head, body, ended = 8, None, [], False
    while at < len(data) and not ended:
        if at + 12 > len(data):
            raise PngError("cut short")
        size, kind = struct.unpack_from(">I4s", data, at)
        if at + 12 + size > len(data):
            raise PngError("cut short")
        part = data[at + 8 : at + 8 + size]
        if zlib.crc32(part, zlib.crc32(kind)) != struct.unpack_from(">I", data, at + 8 + size)[0]:
            raise PngError(f"checksum of {kind.decode('latin-1')}")
        if kind == b"IHDR":
            head = struct.unpack(">IIBBBBB", part)
        elif kind == b"IDAT":
            body.append(part)
        elif kind == b"IEND":
            ended = True
        elif not kind[0] & 32:
            raise PngError(f"unknown chunk {kind.decode('latin-1')}")
        at += 12 + size
    if head is None or not ended:
        raise PngError("no header" if head is None else "no end")
    w, h, depth, colour, packing, filtering, lacing = head
    if depth != 8 or colour not in CHANNELS or packing or filtering or lacing or not w or not h:
        raise PngError("kind of image not read here")
    c = CHANNELS[colour]
    try:
        raw = zlib.decompress(b"".join(body))
    except zlib.error as e:
        raise PngError(f"image data: {e}") from e
    if len(raw) != h * (w * c + 1):
        raise PngError("size of image data")
    rows = np.frombuffer(raw, np.uint8).reshape(h, w * c + 1)
    return unfilter_rows(rows[:, 1:], c, rows[:, 0].astype(np.int64)).reshape(h, w, c)


def _cosines(n: int, k: int) -> np.ndarray:
    return np.cos(np.pi * np.outer(np.arange(k), 2 * np.arange(n) + 1) / (2 * n))


_BASIS = _cosines(SIDE, LOW)


def _shrunk(luma: np.ndarray, side: int, axis: int) -> np.ndarray:
    """Averages of ``side`` equal stretches along an axis (a pixel on a border counts by its share)."""
    n = luma.shape[axis]
    if n % side == 0:
        shape = luma.shape[:axis] + (side, n // side) + luma.shape[axis + 1 :]
        return luma.reshape(shape).mean(axis + 1)
    zero = np.zeros_like(np.take(luma, [0], axis))
    sums = np.concatenate([zero, np.cumsum(luma, axis)], axis)
    at = np.arange(side + 1) * n / side
    low = np.minimum(at.astype(np.int64), n - 1)
    shape = [1, 1]
    shape[axis] = -1
    edge = np.take(sums, low, axis) + np.take(luma, low, axis) * (at - low).reshape(shape)
    return np.diff(edge, axis=axis) * (side / n)


def cosine_hash(samples: np.ndarray) -> bytes:
    """64-bit perceptual hash of an image, as 8 bytes."""
    luma = samples[:, :, :3] @ np.array([0.299, 0.587, 0.114], np.float32) if samples.shape[2] >= 3 else samples[:, :, 0].astype(np.float32)
    small = _shrunk(_shrunk(luma, SIDE, 1).astype(np.float64), SIDE, 0)
    low = np.round(_BASIS @ small @ _BASIS.T, 6).reshape(-1)
    return np.packbits(low > np.median(low[1:])).tobytes()


def as_samples(text: bytes) -> np.ndarray:
    """Text padded with spaces to whole rows of 64 RGB pixels."""
    rows = max(1, -(-len(text) // ROW_BYTES))
    return np.frombuffer(text.ljust(rows * ROW_BYTES, b" "), np.uint8).reshape(rows, WIDTH, 3)


def _write(filters: tuple[int, ...], level: int):
    schema = pa.schema([("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("media", pa.binary())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                texts = [(x or "").encode() for x in part.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([
                    part.column("doc_id"), pa.array(list(map(len, texts)), pa.int64()),
                    pa.array([encode_png(as_samples(x), filters, level) for x in texts], pa.binary()),
                ], schema=schema)

    return run


def write_media(docs: DataFrame, filters: tuple[int, ...] = WRITTEN, level: int = 1) -> DataFrame:
    """``docs(doc_id, text)`` to (doc_id, n_bytes, media): each text as a PNG file, its rows under the best of ``filters``."""
    ship(docs.sparkSession)
    src = docs.selectExpr("cast(doc_id as long) as doc_id", "text")
    return src.mapInArrow(_write(filters, level), "doc_id long, n_bytes long, media binary")


MEDIA_COLUMNS = "payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string, phash binary, width int, height int, channels int, error string"


def _media_row(data: bytes | None) -> tuple:
    if data is None:
        return (None,) * 10 + ("no media",)
    own = (len(data), hashlib.sha256(data).hexdigest())
    try:
        image = decode_png(data)
    except PngError as e:
        return (None, None, None, *own, None, None, None, None, None, str(e))
    payload, mark = image.tobytes(), cosine_hash(image)
    return (len(payload), hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-16:]), *own, mark.hex(), mark, image.shape[1], image.shape[0], image.shape[2], None)


def read_media(df: DataFrame) -> DataFrame:
    """Decode column ``media``; the other columns stay. Adds digests of what was read back, and the perceptual hash."""
    ship(df.sparkSession)
    added = [x.split() for x in MEDIA_COLUMNS.split(", ")]
    arrow = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary(), "int": pa.int32()}
    clash = {n for n, _ in added} & set(df.columns)
    kept = [c for c in df.columns if c != "media" and c not in clash]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                rows = [_media_row(x) for x in part.column("media").to_pylist()]
                cols = [pa.array([r[i] for r in rows], arrow[t]) for i, (_, t) in enumerate(added)]
                yield pa.RecordBatch.from_arrays([part.column(c) for c in kept] + cols, names=kept + [n for n, _ in added])

    schema = StructType([df.schema[c] for c in kept] + StructType.fromDDL(MEDIA_COLUMNS).fields)
    return df.mapInArrow(run, schema)
