"""Sampled segmentations without replacement: Gumbel top-k by perturbed A-star search over the piece lattice.

The lattice of a text has an edge for each vocabulary piece that fits (and one, made of byte pieces, for a character that
no piece holds). A piece's weight comes from its rank in the vocabulary (rank in a merge list falls with frequency, so
``-log(rank + 3)`` stands for its log probability), times ``alpha``; a segmentation's probability is the product over
its pieces, normalised over the lattice by backward sums.

Search. A node of the search is a set of segmentations: a common prefix, and a choice of next piece from which some
pieces are already taken. Its bound is the largest perturbed log probability inside it, a Gumbel variable at the node's
log mass, truncated at the bound of its parent; the backward sums make that bound exact, so the best node in the queue
yields the next segmentation at once. It leaves behind the nodes that branch off its path. The k segmentations that come out
first are a sample of k distinct ones, without replacement, in order of their perturbed log probability; with kappa the
bound that is left in the queue, ``1 - exp(-exp(log_prob - kappa))`` is the inclusion score of each.
Branch nodes far down a path are held as one node with their total mass until that node is drawn.

The parts that every text pays for are numpy over a batch: the lattice of each distinct unit (a text is cut into units
where no piece can cross), and one free path for every unit of every text. A unit's lattice is kept for the batches after it, up
to ``MAX_ENTRIES`` edges, and made in runs of ``RUN_CHARS`` characters. Random bits come from counters keyed by (seed, row
key, rank, position), so results depend on neither batches nor partitions. Memory follows the distinct units of a batch (or of one
long text, which is a batch of its own) and the longest run of characters without a break.

Decoding joins pieces, turns byte pieces into bytes and the space mark into spaces. It returns the text exactly, but that
U+2581 in a text comes back as a space, as in the public library.

Defined results: null and empty texts have one segmentation, the empty one, with inclusion 1; a text with fewer than k segmentations yields
them all, each with inclusion 1; rows with equal keys draw alike; extra columns do not matter.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import ship
from .textnum import _Powers, flat, mix64, mix_int, trim, unit

MARK = 0x2581
ALPHA = 0.25
SAMPLES = 2
CHUNK_CHARS = 1 << 18
#: Edges of the lattice that are kept from batch to batch, and characters whose lattice is made at once.
MAX_ENTRIES = 1_000_000
RUN_CHARS = 1 << 17
HEAD = 96  # branch nodes that a path lists one by one
_PIECE_BASE = 0xC2B2AE3D27D4EB4F
_pow = _Powers(_PIECE_BASE)
_A, _B, _C = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F)


class Pieces:
    """The vocabulary: hashes of the pieces for the lattice, bytes of the pieces for decoding."""

    def __init__(self, path: str, alpha: float = ALPHA) -> None:
        import sentencepiece

        sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        names = [sp.id_to_piece(i) for i in range(n)]
        byte = [sp.is_byte(i) for i in range(n)]
        plain = [i for i in range(n) if not (byte[i] or sp.is_control(i) or sp.is_unknown(i) or sp.is_unused(i))]
        self.n, self.byte_id = n, np.full(256, -1)
        for i in range(n):
            if byte[i]:
                self.byte_id[int(names[i][1:-1], 16)] = i
        self.unknown = sp.unk_id()
        if (self.byte_id < 0).any():
            raise ValueError("this vocabulary has no byte pieces")
        self.score = np.full(n, -alpha * np.log(n + 3.0))
        self.score[plain] = -alpha * np.log(np.arange(len(plain)) + 3.0)
        self.byte_score = float(self.score[self.byte_id[0]])
        self.longest = max(len(names[i]) for i in plain)
        if any(chr(MARK) in names[i].lstrip(chr(MARK)) for i in plain):
            raise ValueError("a piece holds a space mark after another character")
        self.known = np.zeros(0x110000, bool)
        self.known[[ord(c) for i in plain for c in names[i]]] = True
        # slot table over hashes of pieces and of what longer pieces begin with; the few that meet in a slot are searched
        of: dict[str, int] = {}
        for i in plain:
            of[names[i]] = i
            for m in range(1, len(names[i])):
                of.setdefault(names[i][:m], -3)
        size = np.array([len(x) for x in of])
        points = np.frombuffer("".join(of).encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64) + np.uint64(1)
        up, _ = _pow.get(self.longest + 1)
        begin = np.cumsum(size) - size
        h = np.add.reduceat(points * up[np.arange(len(points)) - np.repeat(begin, size)], begin) + size.astype(np.uint64) * _C
        self.key, self.key_id = h, np.fromiter(of.values(), np.int32, len(of))
        at = (h * _A >> np.uint64(44)).astype(np.int64)
        _, first = np.unique(at, return_index=True)
        self.slot = np.full(1 << 20, -1, np.int32)
        self.slot[at[first]] = first
        rest = np.setdiff1d(np.arange(len(h)), first)
        self.more = rest[np.argsort(h[rest])]
        self.more_slot = np.zeros(1 << 20, bool)
        self.more_slot[at[rest]] = True
        out = [bytes([int(names[i][1:-1], 16)]) if byte[i] else b"" if i not in set_plain else names[i].replace(chr(MARK), " ").encode() for set_plain in [set(plain)] for i in range(n)]
        self.piece_bytes = np.array(out, object)
        self.flat = np.frombuffer(b"".join(out), np.uint8)
        self.width = np.array([len(x) for x in out], np.int32)
        self.begin = (np.cumsum(self.width) - self.width).astype(np.int32)

    def find(self, h: np.ndarray) -> np.ndarray:
        """Ids of hashes; -1 where there is no such piece, -3 where only longer pieces begin so."""
        at = (h * _A >> np.uint64(44)).astype(np.int64)
        place = self.slot[at]
        wrong = np.flatnonzero((place < 0) | (self.key[place] != h))
        got = self.key_id[place]
        got[wrong] = -1
        again = wrong[self.more_slot[at[wrong]]]
        if len(again):
            j = self.more[np.minimum(np.searchsorted(self.key[self.more], h[again]), len(self.more) - 1)]
            same = self.key[j] == h[again]
            got[again[same]] = self.key_id[j[same]]
        return got

    def spell(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The bytes of a run of pieces, and where each piece's begin (one border more than pieces)."""
        width = self.width[ids]
        at = np.zeros(len(ids) + 1, np.int32)
        np.cumsum(width, out=at[1:])
        index = np.repeat(self.begin[ids] - at[:-1], width)
        index += np.arange(at[-1], dtype=np.int32)
        return self.flat[index], at

    def decode(self, ids: np.ndarray) -> str:
        return b"".join(self.piece_bytes[ids])[1:].decode("utf-8", "replace")


def _edges(points: np.ndarray, size: np.ndarray, pieces: Pieces) -> dict[str, np.ndarray]:
    """The lattice of units: ``points`` are their characters in one array, ``size`` their lengths.

    A state is a position in a unit (one more than characters); its next pieces are ``count`` edges from ``ptr`` on.
    """
    n = len(points)
    end_of = np.repeat(np.cumsum(size), size)
    left = end_of - np.arange(n)  # characters from here to the unit's end
    state = np.arange(n) + np.repeat(np.arange(len(size)), size)
    n_states = n + len(size)
    up, down = _pow.get(n + 1)
    pre = np.zeros(n + 1, np.uint64)
    np.cumsum((points.astype(np.uint64) + np.uint64(1)) * up[:n], out=pre[1:])
    longest = int(min(pieces.longest, size.max(initial=0)))
    odd = ~pieces.known[points]
    hits: list[tuple[np.ndarray, np.ndarray]] = []
    at = np.arange(n)
    for length in range(1, longest + 1):
        at = at[left[at] >= length]
        if not len(at):
            break
        got = pieces.find((pre[at + length] - pre[at]) * down[at] + np.array([length], np.uint64) * _C)
        more = got != -1
        if length == 1:
            odd |= got < 0
            got[odd] = np.where(points[odd] < 0x80, pieces.byte_id[np.minimum(points[odd], 0x7F)], -2)  # -2: spelt in several bytes
            hits.append((at, got))
        else:
            hit = got >= 0
            hits.append((at[hit], got[hit]))
        at = at[more]
    # Edges stand by distance to the unit's end, so that backward sums need one pass over slices.
    order = np.argsort(left.astype(np.int16) if left.max(initial=0) < 1 << 15 else left, kind="stable")
    count = np.zeros(n, np.int64)
    for at, _ in hits:
        count[at] += 1
    begin = np.zeros(n, np.int64)
    begin[order] = np.cumsum(count[order]) - count[order]
    total = int(count.sum())
    piece, step, source, score = np.empty(total, np.int32), np.empty(total, np.int16), np.empty(total, np.int32), np.empty(total)
    fill = begin.copy()
    for length in range(1, len(hits) + 1):
        at, got = hits[length - 1]
        to = fill[at]
        fill[at] += 1
        hits[length - 1] = (at[:0], got[:0])  # done with
        piece[to], step[to], source[to], score[to] = got, length, at, pieces.score[np.maximum(got, 0)]
    many_bytes = np.flatnonzero(piece == -2)
    x = points[source[many_bytes]]
    score[many_bytes] = np.where(x < 0x800, 2, np.where(x < 0x10000, 3, 4)) * pieces.byte_score
    entry_state = state[source].astype(np.int32)
    after = entry_state + step
    beta = np.zeros(n_states)
    border = np.searchsorted(left[order], np.arange(1, int(left.max(initial=0)) + 2))
    heads = begin[order]
    for d in range(1, len(border)):
        lo, hi = border[d - 1], border[d]
        if lo == hi:
            continue
        e0, e1 = heads[lo], heads[hi] if hi < n else total
        v = score[e0:e1] + beta[after[e0:e1]]
        at = heads[lo:hi] - e0
        top = np.maximum.reduceat(v, at)
        beta[state[order[lo:hi]]] = top + np.log(np.add.reduceat(np.exp(v - np.repeat(top, count[order[lo:hi]])), at))
    logp = np.minimum(score + beta[after] - beta[entry_state], 0.0)
    cum = np.exp(logp)
    on = begin[count > 1]
    more, k = count[count > 1], 1
    while len(on):  # sums inside a state only, so that they do not depend on what stands beside it
        cum[on + k] += cum[on + k - 1]
        k += 1
        on, more = on[more > k], more[more > k]
    cum[begin + count - 1] = 2.0  # no draw falls off the end
    ptr, wide, point_at = np.zeros(n_states, np.int64), np.zeros(n_states, np.int16), np.zeros(n_states, np.uint32)
    ptr[state], wide[state], point_at[state] = begin, count, points
    return {
        "piece": piece, "step": step, "logp": logp, "cum": cum, "entry_state": entry_state, "entry_many": wide[entry_state] > 1, "entry_last": wide[after] == 0,
        "ptr": ptr, "count": wide, "many": wide > 1, "at_end": wide == 0, "point_at": point_at,
    }


_OF_EDGES = {"piece": np.int32, "step": np.int16, "logp": np.float64, "cum": np.float64, "entry_state": np.int32, "entry_many": bool, "entry_last": bool}
_OF_STATES = {"ptr": np.int64, "count": np.int16, "many": bool, "at_end": bool, "point_at": np.uint32}


class Lattice:
    """The edges of the units met so far, found by the units' hashes; rare units go when there are too many edges."""

    def __init__(self, pieces: Pieces) -> None:
        self.pieces = pieces
        self.clear()

    def clear(self) -> None:
        self.hash, self.start, self.open, self.seen = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, bool), np.zeros(0, np.int32)
        self._room = {name: np.zeros(0, kind) for name, kind in (_OF_EDGES | _OF_STATES).items()}
        self._views(0, 0)
        self.any_odd = False

    def _views(self, n_edges: int, n_states: int) -> None:
        for names, n in ((_OF_EDGES, n_edges), (_OF_STATES, n_states)):
            for name in names:
                setattr(self, name, self._room[name][:n])

    def _append(self, part: dict[str, np.ndarray]) -> None:
        n_edges, n_states = len(self.piece), len(self.ptr)
        part["ptr"] += n_edges
        part["entry_state"] += n_states
        self.any_odd |= bool((part["piece"] < 0).any())
        for name, x in part.items():
            n, old = (n_edges if name in _OF_EDGES else n_states), self._room[name]
            if n + len(x) > len(old):
                self._room[name] = np.empty((n + len(x)) * 5 // 4, old.dtype)
                self._room[name][:n] = old[:n]
            self._room[name][n : n + len(x)] = x
        self._views(n_edges + len(part["piece"]), n_states + len(part["many"]))

    def _keep(self, on: np.ndarray) -> None:
        """Only the units where ``on`` holds; their states and edges move together."""
        order = np.argsort(self.start)
        size = np.diff(np.append(self.start[order], len(self.ptr)))
        state = np.repeat(on[order], size)
        edge = state[self.entry_state]
        moved, at = np.cumsum(state) - 1, np.cumsum(edge) - 1
        for names, mask in ((_OF_EDGES, edge), (_OF_STATES, state)):
            for name in names:
                self._room[name] = getattr(self, name)[mask]
        self._views(int(edge.sum()), int(state.sum()))
        self.entry_state[:] = moved[self.entry_state]
        inner = ~self.at_end
        self.ptr[inner] = at[self.ptr[inner]]
        self.hash, self.start, self.open, self.seen = self.hash[on], moved[self.start[on]], self.open[on], self.seen[on] // 2

    def units(self, h: np.ndarray, first: np.ndarray, size: np.ndarray, points: np.ndarray) -> np.ndarray:
        """Where each unit (ascending hash, first character, length) is in ``hash``, ``start`` and ``open``; new ones are added."""
        least = 2
        while len(self.piece) > MAX_ENTRIES // (1 if least == 2 else 2):
            self._keep(self.seen >= least)
            least *= 2
        at = np.searchsorted(self.hash, h)
        new = np.flatnonzero(self.hash[np.minimum(at, len(self.hash) - 1)] != h) if len(self.hash) else np.arange(len(h))
        if len(new):
            run = (np.cumsum(size[new]) - 1) // RUN_CHARS
            border = np.append(np.flatnonzero(np.diff(run, prepend=-1)), len(new))
            starts, opens = [self.start], [self.open]
            for a, b in zip(border[:-1], border[1:]):
                own = size[new[a:b]]
                index = np.arange(own.sum()) + np.repeat(first[new[a:b]] - (np.cumsum(own) - own), own)
                part = _edges(points[index], own, self.pieces)
                local = np.concatenate([[0], np.cumsum(own + 1)])
                several = np.concatenate([[0], np.cumsum(part["many"])])[local]
                starts.append(local[:-1] + len(self.ptr))
                opens.append(several[1:] > several[:-1])
                self._append(part)
            known = np.concatenate([self.hash, h[new]])
            order = np.argsort(known, kind="stable")
            self.hash, self.start, self.open = known[order], np.concatenate(starts)[order], np.concatenate(opens)[order]
            self.seen = np.concatenate([self.seen, np.zeros(len(new), np.int32)])[order]
            at = np.searchsorted(self.hash, h)
        self.seen[at] += 1
        return at


def _uniform(key: np.ndarray | np.uint64, n: np.ndarray) -> np.ndarray:
    return unit(mix64(key + n.astype(np.uint64) * _A))


def cut_units(points: np.ndarray, row_start: np.ndarray, pieces: Pieces) -> np.ndarray:
    """First positions of units: row starts, a space mark after another character, and both sides of unknown characters."""
    odd = ~pieces.known[points]
    mark = points == MARK
    new = np.zeros(len(points), bool)
    new[1:] = (mark[1:] & ~mark[:-1]) | odd[1:] | odd[:-1]
    new[row_start[row_start < len(points)]] = True
    return np.flatnonzero(new)


class _Search:
    """The queue of one text. Its random bits are a counter's, in the order of the search."""

    def __init__(self, sampler: Sampler, key: np.uint64, held: np.ndarray) -> None:
        self.sampler, self.lat, self.k, self.key, self.held, self.spent = sampler, sampler.lat, sampler.k, key, held, 0
        self.queue: list[tuple] = []
        self.out: list[tuple[float, float, np.ndarray]] = []
        self.tick = 0

    def draws(self, n: int) -> np.ndarray:
        self.spent += n
        return self.held[self.spent - n : self.spent] if self.spent <= len(self.held) else _uniform(self.key, np.arange(self.spent - n, self.spent))

    def draw(self) -> float:
        return float(self.draws(1)[0])

    def gumbel(self) -> float:
        return -math.log(-math.log(self.draw()))

    def truncated(self, mass: float, top: float) -> float:
        return -float(np.logaddexp(-top, -(mass + self.gumbel())))

    def push(self, bound: float, kind: str, path: np.ndarray, at: int, before: float, taken: tuple = ()) -> None:
        self.tick += 1
        heapq.heappush(self.queue, (-bound, self.tick, kind, path, at, before, taken))

    def push_far(self, path: np.ndarray, at: int, before: float, top: float) -> None:
        """All that branches off from piece ``at`` on, as one node."""
        tail = float(self.lat.logp[path[at:]].sum())
        if tail < -1e-12:
            self.push(self.truncated(before + math.log(-math.expm1(tail)), top), "far", path, at, before)

    def open_far(self, path: np.ndarray, at: int, before: float, top: float) -> None:
        """The branches of such a node once it is drawn: one of them, drawn by mass, has the node's bound."""
        lat, head = self.lat, path[at:]
        left = -np.expm1(lat.logp[head])
        own = np.flatnonzero(lat.entry_many[head] & (left > 1e-15))
        if not len(own):
            return
        sums = np.cumsum(lat.logp[head])
        start = before + np.where(own > 0, sums[own - 1], 0.0)
        mass = start + np.log(left[own])
        got = -np.logaddexp(-top, -(mass - np.log(-np.log(self.draws(len(own))))))
        w = np.cumsum(np.exp(mass - mass.max()))
        got[min(int(np.searchsorted(w, self.draw() * w[-1])), len(own) - 1)] = top
        for j in np.argsort(-got, kind="stable")[: self.k + 1 - len(self.out)]:
            self.push(float(got[j]), "branch", path, at + int(own[j]), float(start[j]), (int(head[own[j]]),))

    def next(self, paths: list, lo: int, hi: int) -> tuple[np.ndarray, int, float, float] | None:
        """The next segmentation, from the best node; what is to branch off it: (path, first piece, log probability before, bound)."""
        lat = self.lat
        while self.queue and self.queue[0][2] == "far":
            neg, _, _, path, at, before, _ = heapq.heappop(self.queue)
            self.open_far(path, at, before, -neg)
        if not self.queue or len(self.out) == self.k:
            return None
        neg, _, _, path, at, before, taken = heapq.heappop(self.queue)
        state = int(lat.entry_state[path[at]])
        begin = int(lat.ptr[state])
        cand = np.array([x for x in range(begin, begin + int(lat.count[state])) if x not in taken])
        p = np.exp(lat.logp[cand])
        w = np.cumsum(p)
        chosen = min(int(np.searchsorted(w, self.draw() * w[-1])), len(cand) - 1)
        c = int(cand[chosen])
        tail = [c]
        s = state + int(lat.step[c])
        while not lat.at_end[s]:
            a, n = int(lat.ptr[s]), int(lat.count[s])
            x = a + int(np.searchsorted(lat.cum[a : a + n - 1], self.draw())) if n > 1 else a
            tail.append(x)
            s += int(lat.step[x])
        rest, off = paths[len(self.out)]  # a fresh free path for the units after this one
        after = lo + int(np.count_nonzero(lat.entry_last[path[:at]])) + 1
        new = np.concatenate([path[:at], np.array(tail, np.int64), rest[off[after] : off[hi]]])
        self.out.append((float(lat.logp[new].sum()), -neg, new))
        left = float(w[-1] - p[chosen])
        if len(cand) > 1 and left > 1e-15:
            self.push(self.truncated(before + math.log(left), -neg), "branch", path, at, before, (*taken, c))
        return new, at + 1, before + float(lat.logp[c]), -neg

    def told(self) -> list[tuple[float, float, float, np.ndarray]]:
        kappa = -self.queue[0][0] if self.queue else -math.inf
        return [(f, g, float(-np.expm1(-np.exp(min(f - kappa, 700.0)))) if kappa > -math.inf else 1.0, self.sampler._ids(x)) for f, g, x in self.out]


class Sampler:
    def __init__(self, path: str, k: int = SAMPLES, alpha: float = ALPHA, seed: int = 1) -> None:
        self.pieces, self.k, self.seed = Pieces(path, alpha), k, seed
        self.lat = Lattice(self.pieces)

    def batch(self, texts: list[str], keys: list[int]) -> Iterator[list[tuple[float, float, float, np.ndarray]]]:
        """For each text its samples: (log probability, perturbed, inclusion, ids), best first."""
        rows = [chr(MARK) + x.replace(" ", chr(MARK)) if x else "" for x in texts]
        points = np.frombuffer("".join(rows).encode("utf-32-le", "surrogatepass"), np.uint32)
        if not len(points):
            for k in keys:
                yield [(0.0, float(-np.log(-np.log(_uniform(np.uint64(mix_int(mix_int(mix_int(self.seed) ^ (k & (1 << 64) - 1)) + 77)), np.zeros(1))[0]))), 1.0, np.zeros(0, np.int32))]
            return
        length = np.array([len(x) for x in rows], np.int64)
        begin = np.cumsum(length) - length
        cut = cut_units(points, begin[length > 0], self.pieces)
        until = np.append(cut[1:], len(points))
        up, down = _pow.get(len(points) + 1)
        pre = np.zeros(len(points) + 1, np.uint64)
        np.cumsum((points.astype(np.uint64) + np.uint64(1)) * up[: len(points)], out=pre[1:])
        h = mix64((pre[until] - pre[cut]) * down[cut] + (until - cut).astype(np.uint64) * _C)
        h, first, inverse = np.unique(h, return_index=True, return_inverse=True)
        lat = self.lat
        at = lat.units(h, cut[first], (until - cut)[first], points)[inverse]
        start = lat.start[at]
        unit_of_row = np.searchsorted(cut, np.append(begin, len(points)))
        salt = np.array([mix_int(mix_int(self.seed) ^ (k & (1 << 64) - 1)) for k in keys], np.uint64)
        n_units = np.diff(unit_of_row)
        unit_key = np.repeat(salt, n_units)
        local = np.arange(len(start)) - np.repeat(unit_of_row[:-1], n_units)
        self.ambiguous = np.bincount(np.repeat(np.arange(len(rows)), n_units), weights=lat.open[at], minlength=len(rows)) > 0
        paths = [self._free(start, unit_key, local, r) for r in range(self.k if self.ambiguous.any() else 1)]
        size = 4 + (HEAD + 8) * self.k
        own = np.array([mix_int(x + 77) for x in salt.tolist()], np.uint64)
        searches = [_Search(self, key, u) for key, u in zip(own, unit(mix64(own[:, None] + np.arange(size, dtype=np.uint64) * _A)))]
        out0, off0 = paths[0]
        border = off0[unit_of_row]
        busy = []
        for i, search in enumerate(searches):
            first = out0[border[i] : border[i + 1]]
            logp = float(lat.logp[first].sum()) if self.ambiguous[i] else 0.0
            search.out.append((logp, search.gumbel(), first))
            if self.ambiguous[i]:
                busy.append((search, first, 0, 0.0, search.out[0][1], unit_of_row[i], unit_of_row[i + 1]))
        while busy:
            self._branch([b[:5] for b in busy])
            more = []
            for search, *_, lo, hi in busy:
                if (new := search.next(paths, lo, hi)) is not None:
                    more.append((search, *new, lo, hi))
            busy = more
        for search in searches:
            yield search.told()

    def _branch(self, todo: list[tuple[_Search, np.ndarray, int, float, float]]) -> None:
        """For (search, path, at, before, top): queue what branches off ``path`` from piece ``at`` on; ``before`` is the log probability of the path up to there."""
        lat, m = self.lat, len(todo)
        size = np.array([min(HEAD, len(path) - at) for _, path, at, _, _ in todo])
        head = np.zeros((m, max(1, int(size.max()))), np.int64)
        for row, n, (_, path, at, _, _) in zip(head, size, todo):
            row[:n] = path[at : at + n]
        real = np.arange(head.shape[1]) < size[:, None]
        logp = np.where(real, lat.logp[head], 0.0)
        sums = np.cumsum(logp, 1)
        left = -np.expm1(logp)  # what the other pieces have
        own = real & lat.entry_many[head] & (left > 1e-15)
        who, at_piece = np.nonzero(own)
        count = own.sum(1)
        begin = np.cumsum(count) - count
        before, top = (np.array([t[j] for t in todo]) for j in (3, 4))
        start = before[who] + np.where(at_piece > 0, sums[who, at_piece - 1], 0.0)
        noise = -np.log(-np.log(np.concatenate([t[0].draws(n) for t, n in zip(todo, count.tolist())]))) if len(who) else np.zeros(0)
        bound = -np.logaddexp(-top[who], -(start + np.log(left[who, at_piece]) + noise))
        for i, (search, path, at, _, best) in enumerate(todo):
            a, b = begin[i], begin[i] + count[i]
            room = self.k + 1 - len(search.out)  # no more of them can come out
            pick = range(a, b) if b - a <= room else a + np.argsort(-bound[a:b], kind="stable")[:room]
            for j in pick:
                x = int(at_piece[j])
                search.push(float(bound[j]), "branch", path, at + x, float(start[j]), (int(head[i, x]),))
            if size[i] < len(path) - at:
                search.push_far(path, at + HEAD, float(before[i] + sums[i, HEAD - 1]), best)

    def _free(self, start: np.ndarray, key: np.ndarray, local: np.ndarray, replica: int) -> tuple[np.ndarray, np.ndarray]:
        """A random path through every unit: entries of the lattice in order, and where each unit's begin."""
        lat = self.lat
        alive, state = np.arange(len(start)), start.copy()
        who, what = [], []
        base = mix64(key + (local.astype(np.uint64) << np.uint64(8)) * _B + np.array([replica], np.uint64) * _C)
        step = 0
        while len(alive):
            c = lat.ptr[state]
            many = np.flatnonzero(lat.many[state])
            if len(many):
                u = unit(mix64(base[alive[many]] + np.array([step + 1], np.uint64) * _A))
                cm = c[many]
                on = np.arange(len(many))
                while len(on):
                    on = on[u[on] > lat.cum[cm[on]]]
                    cm[on] += 1
                c[many] = cm
            who.append(alive), what.append(c)
            state = state + lat.step[c]
            go = ~lat.at_end[state]
            alive, state = alive[go], state[go]
            step += 1
        n = np.zeros(len(start), np.int64)
        for a in who:
            n[a] += 1
        off = np.concatenate([[0], np.cumsum(n)])
        out = np.empty(off[-1], np.int64)
        for s, (a, c) in enumerate(zip(who, what)):
            out[off[a] + s] = c
        return out, off

    def _ids(self, entries: np.ndarray) -> np.ndarray:
        lat = self.lat
        ids = lat.piece[entries]
        if not lat.any_odd:
            return ids
        odd = np.flatnonzero(ids < 0)
        if not len(odd):
            return ids
        state = lat.entry_state[entries[odd]]
        out, last = [], 0
        for o, s in zip(odd, state):
            out.append(ids[last:o])
            out.append(self.pieces.byte_id[np.frombuffer(chr(lat.point_at[s]).encode("utf-8", "surrogatepass"), np.uint8)].astype(np.int32))
            last = o + 1
        return np.concatenate([*out, ids[last:]])


def agree(pieces: Pieces, ids: np.ndarray, size: np.ndarray, texts: list[str]) -> list[bool]:
    """Whether each run of ``size`` ids decodes to its text."""
    flat, at = pieces.spell(ids)
    border = at[np.concatenate([[0], np.cumsum(size)])].tolist()
    data, out, last, want = flat.tobytes(), [], None, b""
    for a, b, text in zip(border[:-1], border[1:], texts):
        if text is not last:
            last, want = text, text.replace(chr(MARK), " ").encode()
        out.append(data[a + 1 : b] == want if b > a else not want)
    return out


_samplers: dict[tuple, Sampler] = {}


def _sample(path: str, k: int, alpha: float, seed: int, check: bool):
    names = ["doc_id", "rank", "log_prob", "perturbed", "inclusion", "n_pieces", "ids"] + ["round_trip"] * check

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        trim()
        who = (path, k, alpha, seed)
        if who not in _samplers:
            _samplers.clear()
            _samplers[who] = Sampler(path, k, alpha, seed)
        sampler = _samplers[who]
        for b in batches:
            _, offs = flat(b.column("text"))
            lo = 0
            while lo < b.num_rows:
                hi = max(lo + 1, int(np.searchsorted(offs, offs[lo] + CHUNK_CHARS, "right")) - 1)
                part = b.slice(lo, hi - lo)
                texts = [x or "" for x in part.column("text").to_pylist()]
                ids = part.column("doc_id").to_pylist()
                cols: list[list] = [[] for _ in range(6)]
                pieces: list[np.ndarray] = []
                own: list[str] = []
                for key, text, samples in zip(ids, texts, sampler.batch(texts, [x or 0 for x in ids])):
                    for r, (f, g, inc, x) in enumerate(samples, 1):
                        for c, v in zip(cols, (key, r, f, g, inc, len(x))):
                            c.append(v)
                        pieces.append(x)
                        own.append(text)
                size = np.array(cols[5], np.int64)
                every = np.concatenate(pieces).astype(np.int32, copy=False) if pieces else np.zeros(0, np.int32)
                lists = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32)), pa.array(every))
                arrays = [pa.array(cols[0], pa.int64()), pa.array(cols[1], pa.int32()), *(pa.array(c, pa.float64()) for c in cols[2:5]), pa.array(cols[5], pa.int64()), lists]
                yield pa.RecordBatch.from_arrays(arrays + ([pa.array(agree(sampler.pieces, every, size, own))] if check else []), names=names)
                del arrays, lists, pieces, cols, every, own, texts
                lo = hi
        sampler.lat.clear()
        trim()

    return run


def sample_segmentations(docs: DataFrame, model: str, k: int = SAMPLES, alpha: float = ALPHA, seed: int = 1, check: bool = False) -> DataFrame:
    """``docs(doc_id, text)`` to (doc_id, rank, log_prob, perturbed, inclusion, n_pieces, ids[, round_trip]), up to k rows for each text."""
    ship(docs.sparkSession)
    schema = "doc_id long, rank int, log_prob double, perturbed double, inclusion double, n_pieces long, ids array<int>" + ", round_trip boolean" * check
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(_sample(model, k, alpha, seed, check), schema)


def decode_pieces(df: DataFrame, model: str, ids: str = "ids", out: str = "text") -> DataFrame:
    """Add ``out``, the text of a column of ids; null ids give null."""
    from pyspark.sql.types import StringType, StructField, StructType

    ship(df.sparkSession)
    kept = [c for c in df.columns if c != out]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces = Pieces(model)
        for b in batches:
            texts = [None if x is None else pieces.decode(np.array(x, np.int64)) if len(x) else "" for x in b.column(ids).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(c) for c in kept] + [pa.array(texts, pa.string())], names=[*kept, out])

    return df.mapInArrow(run, StructType([df.schema[c] for c in kept] + [StructField(out, StringType())]))
