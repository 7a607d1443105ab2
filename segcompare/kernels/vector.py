"""Kernels on Arrow batches: adaptive boxes with pixel counting below a threshold, pixel counting, exact overlay.

A batch of pairs advances together. The frontier is five parallel arrays (pair, x0, y0, x1, y1). A box smaller
than the threshold is counted pixel by pixel; a larger one is split into fan-out parts, and each part is judged
against both rings: a part that an edge meets is undecided, any other is wholly inside or outside. Only parts
whose contribution is open go on; the first box is never judged. At most `frontier_boxes` boxes advance at once,
the others wait on a stack, and at most `chunk_cells` pixels are counted at once, a larger box strip by strip.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..schema import AREAS, BOXES, COUNTERS
from . import lookup
from .lookup import cuts

INSIDE, OUTSIDE, STRADDLE = 1, 0, -1


@dataclass(frozen=True)
class Options:
    """How the kernel runs; no option changes an area.

    fan_out n = g * g parts of a split; threshold T: boxes below it are counted by pixels (default n * n / 2);
    union "indirect" (from the ring areas) or "direct"; root "joint" box of the pair or "overlap" of the boxes;
    layout "records" (an array of boxes) or "columns" (parallel arrays); edge_block edges are tested at once;
    rings of up to edge_cache edges are kept as dense blocks; frontier "level" or "stack" (bounded memory);
    tables: boxes and pixels are looked up in tables of the rings (see lookup) where these are small enough, in place
    of a look at each edge; the variants of layout and edges are without.
    """

    fan_out: int = 16
    threshold: int | None = None
    union: str = "indirect"
    root: str = "joint"
    layout: str = "columns"
    edge_block: int = 8
    edge_cache: int = 256
    frontier: str = "level"
    chunk_cells: int = 4_000_000
    frontier_boxes: int = 1 << 18
    pixels_only: bool = False
    tables: bool = True

    @property
    def side(self) -> int:
        g = round(self.fan_out**0.5)
        if g * g != self.fan_out or g < 2:
            raise ValueError("the fan-out is a square of 2 or more")
        return g

    @property
    def limit(self) -> int:
        t = default_threshold(self.fan_out) if self.threshold is None else self.threshold
        if t < 2:
            raise ValueError("the threshold is 2 or more")
        return t

    @property
    def at_once(self) -> int:
        """Boxes that advance at once: their parts are a million at most."""
        return max(1, min(self.frontier_boxes, (1 << 20) // self.fan_out))


#: Rows of boxes and edges that are compared in one go.
_ROWS = 1 << 14


def default_threshold(fan_out: int) -> int:
    return fan_out * fan_out // 2


class Rings:
    """The edges of a batch of rings: by ring, from `start`, `count` each; ax <= bx, ay <= by."""

    def __init__(self, xs: np.ndarray, ys: np.ndarray, offsets: np.ndarray):
        n = np.diff(offsets)
        following = np.arange(1, len(xs) + 1)
        following[offsets[1:][n > 0] - 1] = offsets[:-1][n > 0]
        nx, ny = xs[following], ys[following]
        self.start, self.count, self.following = offsets[:-1], n, following
        self.xs, self.ys = xs, ys
        self.ax, self.bx, self.ay, self.by = np.minimum(xs, nx), np.maximum(xs, nx), np.minimum(ys, ny), np.maximum(ys, ny)
        self.up = xs == nx
        owner = np.repeat(np.arange(len(n)), n)
        ox, oy = np.repeat(xs[np.minimum(offsets[:-1], max(len(xs) - 1, 0))], n) if len(xs) else xs, np.repeat(ys[np.minimum(offsets[:-1], max(len(ys) - 1, 0))], n) if len(ys) else ys
        cross = (xs - ox) * (ny - oy) - (nx - ox) * (ys - oy)
        twice = np.zeros(len(n), np.int64)
        np.add.at(twice, owner, cross)
        self.area = np.abs(twice) // 2
        ends = lambda f, v: f.reduceat(v, self.start) if len(v) else np.zeros(0, np.int64)
        self.box = (ends(np.minimum, self.ax), ends(np.minimum, self.ay), ends(np.maximum, self.bx), ends(np.maximum, self.by))
        self.dense: tuple[np.ndarray, ...] | None = None
        self.looked_up: lookup.Tables | None = None
        self.bits: tuple[Rings, lookup.Bits] | None = None

    @classmethod
    def of(cls, column: pa.Array) -> Rings:
        flat = column.flatten()
        offsets = np.asarray(column.offsets, np.int64) - (column.offsets[0].as_py() if len(column.offsets) else 0)
        return cls(np.asarray(flat.field(0), np.int64), np.asarray(flat.field(1), np.int64), offsets)

    def part(self, lo: int, hi: int) -> Rings:
        """The rings lo to hi - 1."""
        ends = np.r_[self.start, len(self.xs)][lo : hi + 1]
        return Rings(self.xs[ends[0] : ends[-1]], self.ys[ends[0] : ends[-1]], ends - ends[0])

    def scaled(self, factor: int) -> Rings:
        return Rings(self.xs * factor, self.ys * factor, np.r_[self.start, len(self.xs)])

    def tables(self) -> lookup.Tables:
        if self.looked_up is None:
            self.looked_up = lookup.Tables(self)
        return self.looked_up

    def bits_with(self, other: Rings) -> lookup.Bits:
        if self.bits is None or self.bits[0] is not other:
            self.bits = (other, lookup.Bits(self, other, self.tables().some & other.tables().some))
        return self.bits[1]

    def upright(self) -> tuple[np.ndarray, np.ndarray, tuple[np.ndarray, ...]]:
        """(start and count of each ring's vertical edges; their x, lower and upper end, sign: 1 downwards, else -1)."""
        at = np.flatnonzero(self.up)
        owner = np.repeat(np.arange(len(self.count)), self.count)[at]
        count = np.bincount(owner, minlength=len(self.count))
        return np.cumsum(count) - count, count, (self.xs[at], self.ay[at], self.by[at], np.where(self.ys[at] > self.ay[at], 1, -1))

    def cached(self, cap: int) -> tuple[np.ndarray, ...]:
        """Edges of the rings of up to cap edges as dense blocks, padded with edges that meet nothing."""
        if self.dense is None or self.dense[0].shape[1] < min(cap, int(self.count.max(initial=0))):
            width = min(cap, int(self.count.max(initial=0)))
            at = self.start[:, None] + np.arange(width)[None, :]
            live = (np.arange(width)[None, :] < self.count[:, None]) & (self.count[:, None] <= cap)
            at = np.where(live, at, 0)
            far = np.iinfo(np.int64).max // 4
            self.dense = tuple(np.where(live, v[at], fill) for v, fill in ((self.ax, far), (self.bx, -far), (self.ay, far), (self.by, -far))) + (live & self.up[at],)
        return self.dense

    def positions(self, pair: np.ndarray, x0: np.ndarray, y0: np.ndarray, x1: np.ndarray, y1: np.ndarray, options: Options) -> np.ndarray:
        """INSIDE, OUTSIDE or STRADDLE of each box against its pair's ring."""
        if options.edge_cache:
            self.cached(options.edge_cache)
        parts = [self._positions(*(v[k : k + _ROWS] for v in (pair, x0, y0, x1, y1)), options) for k in range(0, len(pair), _ROWS)]
        return np.concatenate(parts) if parts else np.zeros(0, np.int64)

    def _positions(self, pair: np.ndarray, x0: np.ndarray, y0: np.ndarray, x1: np.ndarray, y1: np.ndarray, options: Options) -> np.ndarray:
        n = len(pair)
        meets, odd = np.zeros(n, bool), np.zeros(n, np.int64)
        count = self.count[pair]
        short = np.flatnonzero(count <= options.edge_cache)
        step = max(1, options.edge_block)

        def test(rows, ax, bx, ay, by, up):
            b = (slice(None), None)
            X0, Y0, X1, Y1 = x0[rows][b], y0[rows][b], x1[rows][b], y1[rows][b]
            inner_x, inner_y = (ax < X1) & (bx > X0), (ay < Y1) & (by > Y0)
            through = inner_x & inner_y & np.where(up, ax > X0, ay > Y0)
            meets[rows] |= through.any(1)
            odd[rows] += (up & (ax > X0) & (ay <= Y0) & (Y0 < by)).sum(1)

        if len(short):
            dense = self.cached(options.edge_cache)
            owner = pair[short]
            for k in range(0, int(count[short].max()), step):
                rows = short if k == 0 else short[count[short] > k]
                own = owner if k == 0 else pair[rows]
                test(rows, *(d[own, k : k + step] for d in dense))
        long = np.flatnonzero(count > options.edge_cache)
        for k in range(0, int(count[long].max(initial=0)), step):
            rows = long[count[long] > k]
            at = self.start[pair[rows]][:, None] + np.arange(k, k + step)[None, :]
            live = np.arange(k, k + step)[None, :] < count[rows][:, None]
            at = np.where(live, at, 0)
            test(rows, np.where(live, self.ax[at], np.iinfo(np.int64).max // 4), self.bx[at], self.ay[at], self.by[at], self.up[at] & live)
        return np.where(meets, STRADDLE, np.where(odd % 2 == 1, INSIDE, OUTSIDE))

    def raster(self, pair: np.ndarray, x0: np.ndarray, y0: np.ndarray, x1: np.ndarray, y1: np.ndarray, base: np.ndarray, total: int) -> np.ndarray:
        """Inside flags of the boxes' pixels, row by row, box k from base[k]: crossings to the left, modulo 2."""
        width = x1 - x0
        count = self.count[pair]
        box = np.repeat(np.arange(len(pair)), count)
        edge = np.repeat(self.start[pair] - np.cumsum(count) + count, count) + np.arange(int(count.sum()))
        lo, hi = np.maximum(self.ay[edge], y0[box]), np.minimum(self.by[edge], y1[box])
        live = self.up[edge] & (hi > lo)
        box, edge, lo, hi = box[live], edge[live], lo[live], hi[live]
        rows = hi - lo
        # an edge beyond the right border is taken at the row's end: a closed ring then leaves nothing to the next row
        at = base[box] + (lo - y0[box]) * width[box] + np.clip(self.ax[edge] - x0[box], 0, width[box])
        step = np.arange(int(rows.sum())) - np.repeat(np.cumsum(rows) - rows, rows)
        flips = np.bincount(np.repeat(at, rows) + step * np.repeat(width[box], rows), minlength=total + 1)[:total].astype(np.uint8)
        return np.bitwise_xor.accumulate(flips & 1).view(bool)


def split(x0: np.ndarray, y0: np.ndarray, x1: np.ndarray, y1: np.ndarray, g: int) -> tuple[np.ndarray, ...]:
    """(parent, x0, y0, x1, y1) of the non-empty parts of a g by g split; the parts tile the parent."""
    k = np.arange(g + 1)
    xs = x0[:, None] + k[None, :] * (x1 - x0)[:, None] // g
    ys = y0[:, None] + k[None, :] * (y1 - y0)[:, None] // g
    shape = (len(x0), g, g)
    cut = lambda v, a: np.broadcast_to(v[:, :, None] if a else v[:, None, :], shape).ravel()
    parts = (np.repeat(np.arange(len(x0)), g * g), cut(xs[:, :-1], 1), cut(ys[:, :-1], 0), cut(xs[:, 1:], 1), cut(ys[:, 1:], 0))
    some = (parts[3] > parts[1]) & (parts[4] > parts[2])
    return tuple(v[some] for v in parts)


def needs_split(f1: np.ndarray, f2: np.ndarray) -> np.ndarray:
    """For the intersection alone: a part goes on where one ring is undecided and none lies outside of it."""
    return ((f1 == STRADDLE) | (f2 == STRADDLE)) & (f1 != OUTSIDE) & (f2 != OUTSIDE)


def needs_split_joint(f1: np.ndarray, f2: np.ndarray) -> np.ndarray:
    """For intersection and union together: a part goes on where any ring is undecided."""
    return (f1 == STRADDLE) | (f2 == STRADDLE)


class _Work:
    """Sums per pair: areas and counters."""

    def __init__(self, n: int):
        self.inter, self.union, self.pixels, self.boxes, self.partitions, self.level = (np.zeros(n, np.int64) for _ in range(6))


def strips(box: tuple[np.ndarray, ...], cells: int) -> tuple[np.ndarray, ...]:
    """The same pixels with boxes of more than `cells` cut into strips of whole rows."""
    pair, x0, y0, x1, y1 = box
    rows = np.maximum(1, cells // np.maximum(x1 - x0, 1))
    strips = np.maximum(1, -(-(y1 - y0) // rows))
    if (strips == 1).all():
        return box
    of = np.repeat(np.arange(len(pair)), strips)
    k = np.arange(len(of)) - np.repeat(np.cumsum(strips) - strips, strips)
    lo = y0[of] + k * rows[of]
    return pair[of], x0[of], lo, x1[of], np.minimum(lo + rows[of], y1[of])


def _count_pixels(p: Rings, q: Rings, box: tuple[np.ndarray, ...], work: _Work, options: Options) -> None:
    pair, x0, y0, x1, y1 = box = strips(box, options.chunk_cells)
    size = (x1 - x0) * (y1 - y0)
    # a box costs its pixels and a look at each edge of both rings
    part = np.cumsum(np.maximum(size, 4 * (p.count[pair] + q.count[pair]))) // options.chunk_cells
    for rows in np.split(np.arange(len(pair)), np.flatnonzero(np.diff(part)) + 1) if len(pair) else ():
        own = tuple(v[rows] for v in box)
        base = np.cumsum(size[rows]) - size[rows]
        total = int(size[rows].sum())
        a, b = p.raster(*own, base, total), q.raster(*own, base, total)
        np.add.at(work.inter, own[0], np.add.reduceat((a & b).astype(np.int64), base))
        np.add.at(work.union, own[0], np.add.reduceat((a | b).astype(np.int64), base))
        np.add.at(work.pixels, own[0], size[rows])


def _advance(p: Rings, q: Rings, box: tuple[np.ndarray, ...], work: _Work, options: Options, level: int) -> tuple[np.ndarray, ...]:
    """Counts the small boxes, splits and judges the large ones, returns the parts that stay open."""
    pair, x0, y0, x1, y1 = box
    small = (x1 - x0) * (y1 - y0) < options.limit
    if options.pixels_only:
        small[:] = True
    _count_pixels(p, q, tuple(v[small] for v in box), work, options)
    large = tuple(v[~small] for v in box)
    np.add.at(work.partitions, large[0], 1)
    parent, *part = split(*large[1:], options.side)
    own = large[0][parent]
    np.add.at(work.boxes, own, 1)
    np.maximum.at(work.level, own, level + 1)
    f1, f2 = p.positions(own, *part, options), q.positions(own, *part, options)
    go_on = (needs_split_joint if options.union == "direct" else needs_split)(f1, f2)
    size = (part[2] - part[0]) * (part[3] - part[1])
    done = ~go_on
    both, any_ = done & (f1 == INSIDE) & (f2 == INSIDE), done & ((f1 == INSIDE) | (f2 == INSIDE))
    np.add.at(work.inter, own[both], size[both])
    np.add.at(work.union, own[any_], size[any_])
    return (own[go_on], *(v[go_on] for v in part))


def _interleaved(box: tuple[np.ndarray, ...]) -> tuple[np.ndarray, ...]:
    """The same boxes as one array of records; its fields lie five entries apart."""
    records = np.stack(box, 1)
    return tuple(records[:, k] for k in range(records.shape[1]))


class _Shared:
    """Sums per pair for several thresholds at once, least first: what is added holds for the thresholds lo to hi - 1."""

    def __init__(self, n: int, thresholds: int):
        self.n, self.level = n, np.zeros((thresholds, n), np.int64)
        self.sums = {c: np.zeros((thresholds + 1) * n, np.int64) for c in ("inter", "union", "pixels", "boxes", "partitions")}

    def add(self, what: str, pair: np.ndarray, lo: np.ndarray | int, hi: np.ndarray | int, value: np.ndarray | int) -> None:
        np.add.at(self.sums[what], lo * self.n + pair, value)
        np.subtract.at(self.sums[what], hi * self.n + pair, value)

    def works(self) -> list[_Work]:
        found = [_Work(self.n) for _ in self.level]
        for c, v in self.sums.items():
            for work, row in zip(found, np.cumsum(v.reshape(-1, self.n), 0), strict=False):
                setattr(work, c, row)
        for work, row in zip(found, self.level, strict=True):
            work.level = row
        return found


def _looked_up(tables: tuple[lookup.Tables, lookup.Tables], bits: lookup.Bits, box: tuple[np.ndarray, ...], limits: np.ndarray, work: _Shared, options: Options, level: int) -> tuple[np.ndarray, ...]:
    """As _advance, by tables and for all thresholds that have not yet counted a box (its last entry, so many of the least)."""
    pair, x0, y0, x1, y1, open_ = box
    g = options.side
    size = (x1 - x0) * (y1 - y0)
    large = np.zeros(len(size), np.int64) if options.pixels_only else np.minimum(np.searchsorted(limits, size, "right"), open_)
    some = np.flatnonzero(large < open_)
    of, *cut = strips((some, *(v[some] for v in (x0, y0, x1, y1))), options.chunk_cells)
    for what, v in zip(("inter", "union"), bits.counts(pair[of], *cut), strict=True):
        work.add(what, pair[of], large[of], open_[of], v)
    work.add("pixels", pair[some], large[some], open_[some], size[some])
    at = np.flatnonzero(large)
    pair, x0, y0, x1, y1, large = (v[at] for v in (pair, x0, y0, x1, y1, large))
    w, h = x1 - x0, y1 - y0
    work.add("partitions", pair, 0, large, 1)
    work.add("boxes", pair, 0, large, np.minimum(w, g) * np.minimum(h, g))
    for k, row in enumerate(work.level):
        own = pair[large > k]
        row[own] = np.maximum(row[own], level + 1)
    following = []
    for k in range(0, len(pair), max(1, (1 << 15) // options.fan_out)):
        now = slice(k, k + max(1, (1 << 15) // options.fan_out))
        own, many, cut = pair[now], large[now], np.arange(g + 1)
        xs, ys = x0[now, None] + cut * w[now, None] // g, y0[now, None] + cut * h[now, None] // g
        size = np.diff(xs)[:, :, None] * np.diff(ys)[:, None, :]
        f1, f2 = (t.positions(own, xs, ys) for t in tables)
        go_on = (needs_split_joint if options.union == "direct" else needs_split)(f1, f2)
        done = np.where(go_on, 0, size)
        work.add("inter", own, 0, many, np.where((f1 == INSIDE) & (f2 == INSIDE), done, 0).sum((1, 2)))
        work.add("union", own, 0, many, np.where((f1 == INSIDE) | (f2 == INSIDE), done, 0).sum((1, 2)))
        of, i, j = np.nonzero(go_on & (size > 0))
        following.append((own[of], xs[of, i], ys[of, j], xs[of, i + 1], ys[of, j + 1], many[of]))
    return tuple(np.concatenate(v) for v in zip(*following, strict=True)) if following else tuple(v[:0] for v in box)


def hybrid(p: Rings, q: Rings, options: Options = Options()) -> _Work:
    """Areas and counters of each pair of rings (p[k], q[k])."""
    return hybrids(p, q, options, [options.limit])[0]


def hybrids(p: Rings, q: Rings, options: Options, limits: list[int]) -> list[_Work]:
    """The same for several thresholds, in ascending order.

    A box that one threshold splits is split by all lower ones too, so by tables the boxes of the least are walked once,
    and each is judged, or its pixels counted, once for all thresholds that do so.
    """
    n = len(p.count)
    if not n:
        return [_Work(0) for _ in limits]
    mx, mn = (np.maximum, np.minimum)
    if options.root == "joint" or options.union == "direct":
        root = (np.arange(n), mn(p.box[0], q.box[0]), mn(p.box[1], q.box[1]), mx(p.box[2], q.box[2]), mx(p.box[3], q.box[3]))
    else:
        root = (np.arange(n), mx(p.box[0], q.box[0]), mx(p.box[1], q.box[1]), mn(p.box[2], q.box[2]), mn(p.box[3], q.box[3]))
    some = (root[3] > root[1]) & (root[4] > root[2])
    root = tuple(v[some] for v in root)
    batch = max(1, options.at_once if options.frontier == "level" else min(options.at_once, 4096))

    def walk(box, advance):
        stack = [(0, box)] if len(box[0]) else []
        while stack:
            level, box = stack.pop()
            if len(box[0]) > batch:
                stack.append((level, tuple(v[: len(box[0]) - batch] for v in box)))
                box = tuple(v[len(box[0]) - batch :] for v in box)
            following = advance(box, level)
            if len(following[0]):
                stack.append((level + 1, following))

    by_table = np.zeros(n, bool)
    works = [_Work(n) for _ in limits]
    if options.tables and options.layout == "columns":
        tables = (p.tables(), q.tables())
        bits = p.bits_with(q)
        by_table = bits.some
        shared, bounds, mine = _Shared(n, len(limits)), np.array(limits), by_table[root[0]]
        walk((*(v[mine] for v in root), np.full(int(mine.sum()), len(limits))), lambda box, level: _looked_up(tables, bits, box, bounds, shared, options, level))
        works = shared.works()
    others = ~by_table[root[0]]
    for limit, work in zip(limits, works, strict=True) if others.any() else ():
        o = replace(options, threshold=limit)
        walk(tuple(v[others] for v in root), lambda box, level, o=o, work=work: _advance(p, q, _interleaved(box) if o.layout == "records" else box, work, o, level))
    if options.union == "indirect" and not options.pixels_only:
        for work in works:
            work.union = p.area + q.area - work.inter
    return works


def portions(column_p: pa.Array, column_q: pa.Array) -> Iterator[tuple[slice, Rings, Rings]]:
    """The pairs of a batch in portions whose tables have about as many entries as fit."""
    p, q = Rings.of(column_p), Rings.of(column_q)
    part = np.cumsum(np.minimum(lookup.costs(p, q), 2 * lookup.MOST)) // lookup.AT_ONCE
    ends = np.r_[0, np.flatnonzero(np.diff(part)) + 1, len(part)].tolist()
    if len(ends) == 2:
        yield slice(0, len(part)), p, q
        return
    for lo, hi in zip(ends, ends[1:], strict=False):
        yield slice(lo, hi), p.part(lo, hi), q.part(lo, hi)


def hybrid_areas(pairs: DataFrame, options: Options = Options()) -> DataFrame:
    """pairs -> ids, inter, uni and the work counters; one Arrow pass, no exchange."""
    options.side, options.limit  # noqa: B018  # wrong settings fail here, not in a task
    names = ["image_id", "p_id", "q_id", "inter", "uni", "pixels", "boxes", "partitions", "max_level"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole, at, p, q in ((b, *part) for b in batches if len(b) for part in portions(b.column(3), b.column(4))):
            batch, work = whole.slice(at.start, at.stop - at.start), hybrid(p, q, options)
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], *(pa.array(v) for v in (work.inter, work.union, work.pixels, work.boxes, work.partitions)), pa.array(work.level.astype(np.int32))], names=names)

    return pairs.select("image_id", "p_id", "q_id", "ring_p", "ring_q").mapInArrow(run, f"{AREAS}, {COUNTERS}")


def sweep_work(pairs: DataFrame, factors: list[int], settings: list[Options]) -> DataFrame:
    """factor, setting (its number) and the sums of the counters over all pairs: one pass, whatever the number of settings."""
    for o in settings:
        o.side, o.limit  # noqa: B018
    # settings that differ in their threshold only walk the boxes together
    walks: dict[Options, list[int]] = {}
    for k in sorted(range(len(settings)), key=lambda k: settings[k].limit):
        walks.setdefault(replace(settings[k], threshold=None), []).append(k)
    names = ["factor", "setting", "pixels", "boxes", "partitions", "max_level"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[tuple[int, int], list[int]] = {}
        for _, *given in (part for b in batches if len(b) for part in portions(b.column(0), b.column(1))):
            for factor in factors:
                p, q = (r.scaled(factor) for r in given)
                for walked, same in walks.items():
                    for k, work in zip(same, hybrids(p, q, walked, [settings[k].limit for k in same]), strict=True):
                        sums = total.setdefault((factor, k), [0, 0, 0, 0])
                        for c, v in enumerate((work.pixels, work.boxes, work.partitions)):
                            sums[c] += int(v.sum())
                        sums[3] = max(sums[3], int(work.level.max()))
        yield pa.RecordBatch.from_arrays([pa.array(v, pa.int32() if c in (0, 1, 5) else pa.int64()) for c, v in enumerate(zip(*((*k, *v) for k, v in total.items()), strict=True) if total else [[]] * 6)], names=names)

    rows = pairs.select("ring_p", "ring_q").mapInArrow(run, "factor int, setting int, pixels long, boxes long, partitions long, max_level int")
    return rows.groupBy("factor", "setting").agg(*(F.sum(c).alias(c) for c in names[2:5]), F.max("max_level").alias("max_level"))


def pixel_areas(pairs: DataFrame) -> DataFrame:
    return hybrid_areas(pairs, Options(pixels_only=True, union="direct"))


def _cells(ring: np.ndarray, xs: np.ndarray, ys: np.ndarray) -> np.ndarray:
    """Inside flags of the cells between sorted coordinates."""
    flips = np.zeros((len(xs), len(ys)), np.int8)
    nxt = np.roll(ring, -1, 0)
    for (ax, ay), (bx, by) in zip(ring.tolist(), nxt.tolist(), strict=True):
        if ax == bx:
            lo, hi = np.searchsorted(ys, (min(ay, by), max(ay, by)))
            flips[np.searchsorted(xs, ax), lo:hi] ^= 1
    return np.bitwise_xor.accumulate(flips, 0)[:-1, :-1].astype(bool)


def overlay(ring_p: np.ndarray, ring_q: np.ndarray, union: bool = False) -> np.ndarray:
    """Boxes (x0, y0, x1, y1) that make up the exact intersection or union, slab by slab between all x cuts."""
    xs, ys = np.unique(np.r_[ring_p[:, 0], ring_q[:, 0]]), np.unique(np.r_[ring_p[:, 1], ring_q[:, 1]])
    a, b = _cells(ring_p, xs, ys), _cells(ring_q, xs, ys)
    hit = (a | b) if union else (a & b)
    edges = np.diff(np.pad(hit, ((0, 0), (1, 1))).astype(np.int8), axis=1)
    slab, lo = np.nonzero(edges == 1)
    _, hi = np.nonzero(edges == -1)
    return np.stack([xs[slab], ys[lo], xs[slab + 1], ys[hi]], 1)


def edge_form_sums(p: Rings, a: np.ndarray, q: Rings, b: np.ndarray, cells: int = 500_000) -> np.ndarray:
    """Intersection areas of the pairs (p[a[k]], q[b[k]]) from pairs of their vertical edges, in closed form."""
    out = np.zeros(len(a), np.int64)
    sides = [(r, *r.upright()) for r in (p, q)]
    (_, p_start, p_count, p_edges), (_, q_start, q_count, q_edges) = sides
    terms = p_count[a] * q_count[b]
    for rows in np.split(np.arange(len(a)), np.flatnonzero(np.diff(np.cumsum(terms) // cells)) + 1) if len(a) else ():
        n = terms[rows]
        of = np.repeat(np.arange(len(rows)), n)
        k = np.arange(len(of)) - np.repeat(np.cumsum(n) - n, n)
        width = q_count[b[rows]][of]
        e, f = p_start[a[rows]][of] + k // width, q_start[b[rows]][of] + k % width
        (px, plo, phi, psign), (qx, qlo, qhi, qsign) = (tuple(v[i] for v in edges) for edges, i in ((p_edges, e), (q_edges, f)))
        height = np.maximum(np.minimum(phi, qhi) - np.maximum(plo, qlo), 0)
        term = -psign * qsign * height * np.maximum(px, qx)
        some = n > 0
        out[rows[some]] = np.add.reduceat(term, (np.cumsum(n) - n)[some]) if len(term) else 0
    return out


def overlay_sums(p: Rings, q: Rings, union: bool = False, cells: int = 2_000_000) -> np.ndarray:
    """Areas of the exact intersection or union of each pair, from the slabs between all cuts of both rings.

    The slabs of many pairs lie behind one another in one array, of about `cells` entries or one pair's.
    """
    n = len(p.count)
    both = (p, q)
    grown = [np.cumsum((p.count + q.count) ** 2 // 4)]
    out = np.zeros(n, np.int64)
    for rows in np.split(np.arange(n), np.flatnonzero(np.diff(grown[0] // cells)) + 1) if n else ():
        lo, hi, m = rows[0], rows[-1] + 1, len(rows)
        spans = [slice(int(r.start[lo]), int(r.start[hi - 1] + r.count[hi - 1])) for r in both]
        owners = [np.repeat(np.arange(m), r.count[lo:hi]) for r in both]
        owner = np.concatenate(owners)
        if not len(owner):
            continue
        xs, x_start, nx, xi = cuts(owner, np.concatenate([r.ax[s] for r, s in zip(both, spans, strict=True)]), m)
        # an edge's lower end is another's upper end, so the lower ends and the upper ones are cut together
        ys, y_start, ny, yi = cuts(np.r_[owner, owner], np.concatenate([v for k in ("ay", "by") for v in (getattr(r, k)[s] for r, s in zip(both, spans, strict=True))]), m)
        bottom, top = yi[: len(owner)], yi[len(owner) :]
        base = np.cumsum(nx * ny) - nx * ny
        total = int((nx * ny).sum())
        upright = np.concatenate([r.up[s] for r, s in zip(both, spans, strict=True)])
        inside = []
        for first, last in ((0, len(owners[0])), (len(owners[0]), len(owner))):
            e = np.flatnonzero(upright[first:last]) + first
            height = top[e] - bottom[e]
            each = np.repeat(e, height)
            row = np.arange(len(each)) - np.repeat(np.cumsum(height) - height, height) + bottom[each]
            flips = np.bincount(base[owner[each]] + row * nx[owner[each]] + xi[each], minlength=total).astype(np.uint8) & 1
            inside.append(np.bitwise_xor.accumulate(flips))  # a ring is left as often as entered, so each row ends with 0
        hit = np.flatnonzero(inside[0] | inside[1] if union else inside[0] & inside[1])
        pair = np.searchsorted(base, hit, "right") - 1
        cell = hit - base[pair]
        row, column = cell // nx[pair], cell % nx[pair]
        x, y = x_start[pair] + column, y_start[pair] + row
        np.add.at(out, pair + lo, (xs[x + 1] - xs[x]) * (ys[y + 1] - ys[y]))
    return out


def overlay_areas(pairs: DataFrame, union: str = "indirect", with_boxes: bool = False) -> DataFrame:
    """The baseline: both boundaries are overlaid exactly, pair by pair; union "direct" overlays twice."""
    names = ["image_id", "p_id", "q_id", "inter", "uni", *(["boxes"] if with_boxes else [])]
    kind = pa.list_(pa.struct([(c, pa.int64()) for c in ("x0", "y0", "x1", "y1")]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b = Rings.of(batch.column(3)), Rings.of(batch.column(4))
            inter = overlay_sums(a, b)
            uni = overlay_sums(a, b, union=True) if union == "direct" else a.area + b.area - inter
            found = []
            if with_boxes:
                corners = [np.split(np.stack([r.xs, r.ys], 1), r.start[1:]) for r in (a, b)]
                found = [[dict(zip(("x0", "y0", "x1", "y1"), r, strict=True)) for r in overlay(x, y).tolist()] for x, y in zip(*corners, strict=True)] if len(batch) else []
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array(inter, pa.int64()), pa.array(uni, pa.int64()), *([pa.array(found, kind)] if with_boxes else [])], names=names)

    schema = AREAS + (f", boxes {BOXES}" if with_boxes else "")
    return pairs.select("image_id", "p_id", "q_id", "ring_p", "ring_q").mapInArrow(run, schema)


def work_summary(areas: DataFrame) -> DataFrame:
    """Sums of the counters over all pairs."""
    return areas.agg(*(F.sum(c).alias(c) for c in ("pixels", "boxes", "partitions")), F.max("max_level").alias("max_level"))
