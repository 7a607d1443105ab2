"""Tables of rings give what tests of each edge give, at a cost that does not follow the edges."""

from dataclasses import replace

import numpy as np
import pyarrow as pa
import pytest

from segcompare.kernels import lookup, vector

O = vector.Options
FIELDS = "inter union pixels boxes partitions level".split()


def skyline(rng, words, left=0):
    """A closed rectilinear ring over random heights."""
    h = rng.integers(1, 17, words)
    x = left + np.arange(words + 1)
    top = [(int(x[k + s]), int(h[k])) for k in range(words - 1, -1, -1) for s in (1, 0)]
    return [(left, 0), (left + words, 0), *(v for k, v in enumerate(top) if not k or v != top[k - 1])]


def rings(shapes):
    flat = np.array([v for s in shapes for v in s], np.int64)
    return vector.Rings(flat[:, 0].copy(), flat[:, 1].copy(), np.r_[0, np.cumsum([len(s) for s in shapes])])


def drawn(seed, n=12, most=40):
    rng = np.random.default_rng(seed)
    return [skyline(rng, int(rng.integers(1, most)), int(rng.integers(-20, 20))) for _ in range(n)]


def same(a, b):
    return all((getattr(a, c) == getattr(b, c)).all() for c in FIELDS)


@pytest.mark.parametrize("o", [O(pixels_only=True, union="direct"), O(), O(union="direct"), O(root="overlap"), O(fan_out=4, threshold=2), O(fan_out=64, threshold=16), O(chunk_cells=50)])
@pytest.mark.parametrize("factor", [1, 3])
def test_tables_change_nothing(o, factor):
    p, q = (rings(drawn(s)).scaled(factor) for s in (1, 2))
    assert same(vector.hybrid(p, q, o), vector.hybrid(p, q, replace(o, tables=False)))


def test_wide_rings_and_edges_on_one_another():
    """Words' borders, and a ring whose edges lie on one another or end where they began."""
    wide = [[(0, 0), (w, 0), (w, 5), (0, 5)] for w in (63, 64, 65, 128, 300)]
    spur = [[(0, 0), (9, 0), (9, 4), (5, 4), (5, 9), (5, 4), (0, 4)], [(0, 0), (4, 0), (4, 0), (4, 4), (0, 4)], [(-3, 1), (70, 1), (70, 9), (-3, 9)], [(1, 1), (2, 1), (2, 2), (1, 2)], [(0, 0), (64, 0), (64, 2), (0, 2)]]
    p, q = rings(wide), rings(spur)
    for o in (O(), O(union="direct", fan_out=4, threshold=2), O(pixels_only=True, union="direct")):
        assert same(vector.hybrid(p, q, o), vector.hybrid(p, q, replace(o, tables=False)))


def test_rings_beyond_the_bounds_are_tested_by_edges(monkeypatch):
    p, q = rings(drawn(3)), rings(drawn(4))
    want = vector.hybrid(p, q, O(tables=False))
    monkeypatch.setattr(lookup, "MOST", 500)
    p, q = rings(drawn(3)), rings(drawn(4))
    assert not p.bits_with(q).some.all() and p.bits_with(q).some.any()
    assert same(vector.hybrid(p, q), want)


@pytest.mark.parametrize("o", [O(), O(union="direct"), O(fan_out=64), O(layout="records")])
def test_thresholds_walked_together(o):
    limits = [4, 16, 32, 128, 2000]
    p, q = rings(drawn(5)), rings(drawn(6))
    for limit, work in zip(limits, vector.hybrids(p, q, o, limits), strict=True):
        assert same(work, vector.hybrid(p, q, replace(o, threshold=limit, tables=False)))


def test_one_walk_for_all_thresholds(spark, monkeypatch):
    """A box is judged once, not once a threshold."""
    calls, real = [], lookup.Tables.positions
    monkeypatch.setattr(lookup.Tables, "positions", lambda *a: calls.append(len(a[1])) or real(*a))
    p, q = rings(drawn(7)), rings(drawn(8))
    vector.hybrids(p, q, O(), [4])
    least = sum(calls)
    vector.hybrids(p, q, O(), [4, 16, 32, 128, 256])
    assert sum(calls) == 2 * least > 0


def test_box_tests_do_not_look_at_edges(monkeypatch):
    def never(*a):
        raise AssertionError("edges")

    monkeypatch.setattr(vector.Rings, "positions", never)
    monkeypatch.setattr(vector.Rings, "raster", never)
    work = vector.hybrid(rings(drawn(9, most=200)), rings(drawn(10, most=200)), O(fan_out=4, threshold=16))
    assert work.boxes.sum() > 0 < work.pixels.sum()


def test_portions_cover_all_pairs(monkeypatch):
    monkeypatch.setattr(lookup, "AT_ONCE", 4000)
    shapes = [drawn(11), drawn(12)]
    kind = pa.list_(pa.struct([("x", pa.int64()), ("y", pa.int64())]))
    columns = [pa.array([[{"x": x, "y": y} for x, y in s] for s in side], kind) for side in shapes]
    parts = list(vector.portions(*columns))
    assert len(parts) > 2 and [k for at, *_ in parts for k in range(at.start, at.stop)] == list(range(12))
    inter = np.concatenate([vector.hybrid(p, q).inter for _, p, q in parts])
    assert (inter == vector.overlay_sums(*map(rings, shapes))).all()
