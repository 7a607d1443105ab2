"""Tables of a batch of rings, so that a box test or a pixel's test costs the same whatever the number of edges.

A ring's distinct x and y coordinates are its cuts. Between them lie pieces of edges of one cut's length, which are
counted in a summed table: the pieces inside an open box, and so whether an edge meets it, follow from four entries.
The pixels of a row between two y cuts are the same, so a ring's pixels are kept as one row of bits for each such band;
boxes count them row by row, 64 pixels a word. Rings beyond the bounds have no tables and are tested edge by edge.
"""

from __future__ import annotations

from typing import TYPE_CHECKING

import numpy as np

if TYPE_CHECKING:
    from .vector import Rings

#: Entries of a ring's tables and coordinates in its box, beyond which it is tested edge by edge.
MOST = 1 << 20
#: Entries of the tables of the pairs that are taken at once.
AT_ONCE = 1 << 21
#: Parts of boxes, or words of pixels, that are looked up in one go.
_LOOKED_UP = 1 << 15


def cuts(owner: np.ndarray, v: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(sorted distinct values of each owner, one owner after another; their starts; their counts; the place of each v among its owner's)."""
    order = np.lexsort((v, owner))
    o, x = owner[order], v[order]
    new = np.r_[True, (o[1:] != o[:-1]) | (x[1:] != x[:-1])] if len(x) else np.zeros(0, bool)
    count = np.bincount(o[new], minlength=n)
    start = np.cumsum(count) - count
    place = np.empty(len(v), np.int64)
    place[order] = np.cumsum(new) - 1
    return x[new], start, count, place - start[owner]


def numbered(count: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(k, 0 .. count[k] - 1) for each k."""
    of = np.repeat(np.arange(len(count)), count)
    return of, np.arange(len(of)) - np.repeat(np.cumsum(count) - count, count)


def _rounded(n: np.ndarray) -> np.ndarray:
    """Up to multiples of four and of about an eighth of n, so that few sizes occur."""
    step = 1 << np.maximum(np.frexp(n)[1] - 3, 2)
    return -(-n // step) * step


def costs(p: Rings, q: Rings) -> np.ndarray:
    """Entries of each pair's tables, about: no more cuts occur than half of the vertices or than coordinates."""
    total = np.zeros(len(p.count), np.int64)
    for r in (p, q):
        w, h = r.box[2] - r.box[0], r.box[3] - r.box[1]
        total += np.minimum(r.count + 2, 2 * w + 4) * np.minimum(r.count + 2, 2 * h + 4) + w + h
    return total


class Axis:
    """For each ring with tables and each coordinate: how many of its cuts are not beyond it."""

    def __init__(self, cut: np.ndarray, start: np.ndarray, count: np.ndarray, low: np.ndarray, high: np.ndarray, some: np.ndarray):
        self.low, self.span = low - 1, np.where(some, high - low + 1, 0)
        size = np.where(some, self.span + 1, 0)
        self.at = np.cumsum(size) - size
        owner = np.repeat(np.arange(len(count)), count)
        own = some[owner]
        mark = np.zeros(int(size.sum()), np.int32)
        mark[(self.at - self.low)[owner[own]] + cut[own]] = 1
        self.upto = np.cumsum(mark, dtype=np.int32)
        before = np.cumsum(np.where(some, count, 0)) - np.where(some, count, 0)
        self.upto -= np.repeat(before, size).astype(np.int32)

    def __call__(self, ring: np.ndarray, v: np.ndarray) -> np.ndarray:
        """ring: one a row of v, or one an entry."""
        low, span, at = self.low[ring], self.span[ring], self.at[ring]
        if v.ndim == 2:
            low, span, at = low[:, None], span[:, None], at[:, None]
        return self.upto[at + np.minimum(np.maximum(v - low, 0), span)].astype(np.int64)


class Tables:
    """Of a batch of rings; `some` tells those that have them."""

    def __init__(self, r: Rings):
        n = len(r.count)
        owner = np.repeat(np.arange(n), r.count)
        xs, x_start, nx, xi = cuts(owner, r.xs, n)
        ys, y_start, ny, yi = cuts(owner, r.ys, n)
        flat = r.ay == r.by
        self.some = np.bincount(owner[r.up == flat], minlength=n) == 0
        u, v = _rounded(2 * nx + 2), _rounded(2 * ny + 2)
        self.some &= (u * v <= MOST) & (r.box[2] - r.box[0] + r.box[3] - r.box[1] <= MOST) & (r.count > 0)
        self.x = Axis(xs, x_start, nx, r.box[0], r.box[2], self.some)
        self.y = Axis(ys, y_start, ny, r.box[1], r.box[3], self.some)
        self.bands = np.where(self.some, ny + 1, 0)
        # rings of the same table size lie behind one another
        size = np.where(self.some, u * v, 0)
        order = np.lexsort((v, u, ~self.some))
        self.base = np.empty(n, np.int64)
        self.base[order] = np.cumsum(size[order]) - size[order]
        self.stride = v
        mine = self.some[owner]
        xj, yj = xi[r.following], yi[r.following]
        self.upright = tuple(k[mine & r.up] for k in (owner, r.xs, xi, np.minimum(yi, yj), np.maximum(yi, yj)))
        level = mine & flat
        self.flat = tuple(k[level] for k in (owner, yi, np.minimum(xi, xj), np.maximum(xi, xj)))
        self.size = np.stack([u, v], 1)
        self.made: tuple[np.ndarray, np.ndarray] | None = None

    def _pieces(self) -> tuple[np.ndarray, np.ndarray]:
        """The summed tables of pieces of edges, and whether the space after each cut lies inside; made when first asked for."""
        if self.made is not None:
            return self.made
        u, v = self.size.T
        size = np.where(self.some, u * v, 0)
        order = np.argsort(self.base, kind="stable")
        order = order[self.some[order]]
        o, _, at, lo, hi = self.upright
        e, k = numbered(hi - lo)
        o, at, band = o[e], at[e], lo[e] + k
        # cuts have even and spaces between them odd places; an entry counts what lies two places before it or less
        places = [self.base[o] + (2 * at + 2) * v[o] + 2 * band + 3]
        half = self.base[o] // 4 + (at + 1) * (v[o] // 2) + band + 1
        o, at, lo, hi = self.flat
        e, k = numbered(hi - lo)
        places.append(self.base[o[e]] + (2 * (lo[e] + k) + 3) * v[o[e]] + 2 * at[e] + 2)
        total = int(size.sum())
        pieces = np.bincount(np.concatenate(places), minlength=total).astype(np.int32)
        inside = (np.bincount(half, minlength=total // 4) & 1).astype(np.int8)
        kinds, first, many = np.unique(self.size[order], axis=0, return_index=True, return_counts=True)
        for (a, b), k, m in zip(kinds.tolist(), self.base[order[first]].tolist() if len(first) else (), many.tolist(), strict=True):
            table = pieces[k : k + m * a * b].reshape(m, a, b)
            np.cumsum(np.cumsum(table, 1, dtype=np.int32), 2, dtype=np.int32, out=table)
            table = inside[k // 4 : (k + m * a * b) // 4].reshape(m, a // 2, b // 2)
            np.bitwise_xor.accumulate(table, 1, out=table)
        self.made = (pieces, inside)
        return self.made

    def positions(self, ring: np.ndarray, xs: np.ndarray, ys: np.ndarray) -> np.ndarray:
        """1 inside, 0 outside or -1 straddling for the parts of boxes cut at xs and ys (a row a box), by box, x and y."""
        left, right, low, high = self.x(ring, xs[:, :-1]), self.x(ring, xs[:, 1:] - 1), self.y(ring, ys[:, :-1]), self.y(ring, ys[:, 1:] - 1)
        base, stride = self.base[ring][:, None], self.stride[ring][:, None]
        corner = (base // 4 + left * (stride // 2))[:, :, None] + low[:, None, :]
        left, right = (base + 2 * left * stride)[:, :, None], (base + (2 * right + 1) * stride)[:, :, None]
        low, high = (2 * low)[:, None, :], (2 * high + 1)[:, None, :]
        t, inside = self._pieces()
        found = t[right + high] - t[right + low] - t[left + high] + t[left + low]
        return np.where(found != 0, np.int8(-1), inside[corner])


class Bits:
    """Pixels of the rings of pairs as bits, one row of words for each band, from the left border of the pair's joint box on."""

    def __init__(self, p: Rings, q: Rings, some: np.ndarray):
        self.left = np.minimum(p.box[0], q.box[0])
        self.words = ((np.maximum(p.box[2], q.box[2]) - self.left) >> 6) + 1
        self.tables = [r.tables() for r in (p, q)]
        self.some = some & (self.words * np.maximum(*(t.bands for t in self.tables)) <= MOST)
        made = [self._made(t) for t in self.tables]
        self.base, self.rows = [m[0] for m in made], [m[1] for m in made]

    def _made(self, t: Tables) -> tuple[np.ndarray, np.ndarray]:
        size = np.where(self.some, t.bands * self.words, 0)
        base = np.cumsum(size) - size
        total = int(size.sum())
        owner, xs, _, lo, hi = (v[self.some[t.upright[0]]] for v in t.upright)
        e, k = numbered(hi - lo)
        o, x = owner[e], xs[e] - self.left[owner[e]]
        at = base[o] + (lo[e] + k + 1) * self.words[o] + (x >> 6)
        bit = np.uint64(1) << (x & 63).astype(np.uint64)
        rows = np.zeros(total, np.uint64)
        np.add.at(rows, at, bit)
        if int(np.bitwise_count(rows).sum(dtype=np.int64)) != len(at):  # edges that lie on one another
            rows[:] = 0
            np.bitwise_xor.at(rows, at, bit)
        odd = np.bitwise_count(rows) & 1
        for k in (1, 2, 4, 8, 16, 32):  # a pixel is inside after an odd number of edges
            rows ^= rows << np.uint64(k)
        # a ring is left as often as entered, so no row leaves anything to the next one
        before = np.bitwise_xor.accumulate(odd) ^ odd if total else odd
        rows ^= np.where(before == 1, ~np.uint64(0), np.uint64(0))
        return base, rows

    def counts(self, pair: np.ndarray, x0: np.ndarray, y0: np.ndarray, x1: np.ndarray, y1: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Pixels of each box in both rings, and in any."""
        first = (x0 - self.left[pair]) >> 6
        words = ((x1 - 1 - self.left[pair]) >> 6) - first + 1
        both, any_ = np.zeros(len(pair), np.int64), np.zeros(len(pair), np.int64)
        steps = words * (y1 - y0)
        for part in np.split(np.arange(len(pair)), np.flatnonzero(np.diff(np.cumsum(steps) // _LOOKED_UP)) + 1) if len(pair) else ():
            of, k = numbered(words[part])
            box = part[of]
            own, word = pair[box], first[box] + k
            start = self.left[own] + 64 * word
            lo, hi = np.maximum(x0[box] - start, 0), np.minimum(x1[box] - start, 64)
            mask = (~np.uint64(0) >> (64 - (hi - lo)).astype(np.uint64)) << lo.astype(np.uint64)
            row, k = numbered((y1 - y0)[box])
            own, y, mask = own[row], y0[box][row] + k, mask[row]
            a, b = (rows[(base[own] + t.y(own, y) * self.words[own]) + word[row]] & mask for t, base, rows in zip(self.tables, self.base, self.rows, strict=True))
            ends = np.cumsum(steps[part]) - steps[part]
            both[part], any_[part] = (np.add.reduceat(np.bitwise_count(v), ends, dtype=np.int64) for v in (a & b, a | b))
        return both, any_
