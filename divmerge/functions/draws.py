"""Seeded draws as columns: counters through a hash, never ``rand()``, so a retried task draws the same.

``md5`` draws can be repeated by other engines (the SQL twins use them); ``xxhash64`` draws are the quick ones for large runs.
"""

from __future__ import annotations

import math
from collections.abc import Iterator, Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 60
SPAN = 1 << BITS


def u60(seed: int, tag: str, *keys: Column | str | int, hash_fn: str = "md5") -> Column:
    """A uniform integer in [0, 2**60) for each key."""
    cols = [F.lit(str(seed)), F.lit(tag)] + [F.lit(str(k)) if isinstance(k, int) else (F.col(k) if isinstance(k, str) else k).cast("string") for k in keys]
    if hash_fn == "md5":
        return F.conv(F.substring(F.md5(F.concat_ws(":", *cols)), 1, 15), 16, 10).cast("long")
    if hash_fn == "xxhash64":
        return F.shiftrightunsigned(F.xxhash64(*cols), 64 - BITS)
    raise ValueError(f"no such hash: {hash_fn}")


def unit(seed: int, tag: str, *keys: Column | str | int, hash_fn: str = "md5") -> Column:
    """A uniform double in [0, 1)."""
    return u60(seed, tag, *keys, hash_fn=hash_fn).cast("double") / float(SPAN)


def below(draw: Column, rate: float) -> Column:
    """True with probability ``rate`` for a u60 draw."""
    return draw < F.lit(int(rate * SPAN))


def gaussian(seed: int, tag: str, *keys: Column | str | int, hash_fn: str = "xxhash64") -> Column:
    """A standard normal from two draws."""
    a = (u60(seed, tag + "/a", *keys, hash_fn=hash_fn).cast("double") + 0.5) / float(SPAN)
    b = unit(seed, tag + "/b", *keys, hash_fn=hash_fn)
    return F.sqrt(-2.0 * F.log(a)) * F.cos(b * (2 * 3.141592653589793))


_SHIFTS = np.repeat(np.array([[7, 12, 17, 22], [5, 9, 14, 20], [4, 11, 16, 23], [6, 10, 15, 21]]), 4, axis=0).reshape(-1)
_SINES = [int(abs(math.sin(i + 1)) * (1 << 32)) for i in range(64)]
_PLACES = [*range(16), *((5 * i + 1) % 16 for i in range(16)), *((3 * i + 5) % 16 for i in range(16)), *((7 * i) % 16 for i in range(16))]
_AT_ONCE = 1 << 15


def _md5_u60(words: list, n: int) -> np.ndarray:
    """The first 60 bits of the MD5 of n messages of one block, given as 16 words, each an array or one number for all."""
    a, b, c, d = (np.full(n, x, np.uint32) for x in (0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476))
    f, g = np.empty(n, np.uint32), np.empty(n, np.uint32)
    for i in range(64):
        if i < 16:
            np.bitwise_xor(c, d, out=f), np.bitwise_and(f, b, out=f), np.bitwise_xor(f, d, out=f)
        elif i < 32:
            np.bitwise_xor(b, c, out=f), np.bitwise_and(f, d, out=f), np.bitwise_xor(f, c, out=f)
        elif i < 48:
            np.bitwise_xor(b, c, out=f), np.bitwise_xor(f, d, out=f)
        else:
            np.bitwise_not(d, out=f), np.bitwise_or(f, b, out=f), np.bitwise_xor(f, c, out=f)
        x = words[_PLACES[i]]
        if isinstance(x, int):
            np.add(a, np.uint32((x + _SINES[i]) & 0xFFFFFFFF), out=a)
        else:
            np.add(a, x, out=a), np.add(a, np.uint32(_SINES[i]), out=a)
        np.add(a, f, out=a)
        s = int(_SHIFTS[i])
        np.left_shift(a, np.uint32(s), out=f), np.right_shift(a, np.uint32(32 - s), out=g), np.bitwise_or(f, g, out=f)
        np.add(f, b, out=a)
        a, b, c, d = d, a, b, c
    first, second = a + np.uint32(0x67452301), b + np.uint32(0xEFCDAB89)
    return (first.byteswap().astype(np.uint64) << np.uint64(28)) | (second.byteswap().astype(np.uint64) >> np.uint64(4))


def _digits(ids: np.ndarray, many: int, at: int) -> dict[int, np.ndarray]:
    """The words of a message in which the ``many`` decimal digits of each id begin at byte ``at``."""
    out, rest = {}, ids
    for pos in range(at + many - 1, at - 1, -1):
        rest, digit = np.divmod(rest, 10)
        part = (digit + 48).astype(np.uint32) << np.uint32(8 * (pos % 4))
        out[pos // 4] = out[pos // 4] | part if pos // 4 in out else part
    return out


def md5_draws(prefixes: Sequence[str], ids: np.ndarray) -> Iterator[tuple[int, slice, np.ndarray]]:
    """The ``md5`` draws of :func:`u60` whose keys end with an id, in arrays: for each prefix ('seed:tag:key:') and run of the ascending ``ids``, (prefix, run, draws)."""
    ids = np.asarray(ids, np.int64)
    lo = 0
    while lo < len(ids):
        many = len(str(int(ids[lo])))
        hi = min(lo + _AT_ONCE, int(np.searchsorted(ids, 10**many)))
        known: dict[int, dict[int, np.ndarray]] = {}
        for k, prefix in enumerate(prefixes):
            head = prefix.encode()
            if len(head) + many > 55:
                raise ValueError("a key is too long for one block")
            at = len(head)
            if at not in known:
                known[at] = _digits(ids[lo:hi], many, at)
            block = bytearray(64)
            block[:at], block[at + many] = head, 0x80
            words = [int.from_bytes(block[4 * i : 4 * i + 4], "little") for i in range(14)] + [8 * (at + many), 0]
            yield k, slice(lo, hi), _md5_u60([known[at][i] | np.uint32(x) if i in known[at] else x for i, x in enumerate(words)], hi - lo)
        lo = hi
