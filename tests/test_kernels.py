"""Kernels, geometry, index, parser, simulator and measures against brute force and the invariants of the method."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from segcompare.functions import geometry as g
from segcompare.kernels import native, relational, vector
from segcompare.operators import index, pairing, relate, similarity
from segcompare.plans import metrics, pipeline, rebalance
from segcompare.schema import OBJECTS, RING
from segcompare.sources import fixtures as fx
from segcompare.sources import io, parse

D = "/root/testdata/sf0.001"
SQUARE = [(0, 0), (6, 0), (6, 6), (0, 6)]
NOTCH = [(0, 0), (12, 0), (12, 12), (8, 12), (8, 4), (4, 4), (4, 12), (0, 12)]
PLUS = fx.SHAPES[4]
PIXEL = [(2, 3), (3, 3), (3, 4), (2, 4)]
FAR = [(x + (1 << 40), y + (1 << 40)) for x, y in PLUS]
TOUCHED = [(0, 0), (2, 0), (2, 2), (4, 2), (4, 4), (2, 4), (2, 2), (0, 2)]  # meets itself in a point


def moved(ring, dx, dy):
    return [(x + dx, y + dy) for x, y in ring]


def pixels(ring):
    edges = [(a[0], min(a[1], b[1]), max(a[1], b[1])) for a, b in zip(ring, ring[1:] + ring[:1], strict=True) if a[0] == b[0]]
    xs, ys = [v[0] for v in ring], [v[1] for v in ring]
    return {(i, j) for i in range(min(xs), max(xs)) for j in range(min(ys), max(ys)) if sum(x > i and lo <= j < hi for x, lo, hi in edges) % 2}


CASES = [(SQUARE, SQUARE), (SQUARE, moved(SQUARE, 20, 0)), (SQUARE, moved(SQUARE, 6, 0)), (SQUARE, moved(SQUARE, 6, 6)), (NOTCH, moved(PIXEL, 3, 3)), (NOTCH, SQUARE), (PLUS, moved(NOTCH, -3, -2)), (NOTCH, moved(PIXEL, 0, 0)), ([(0, 0), (1, 0), (1, 40), (0, 40)], [(-5, 7), (30, 7), (30, 8), (-5, 8)]), (FAR, moved(FAR, 1, 2)), (TOUCHED, SQUARE)]
CASES += [(moved(fx.SHAPES[a], random.Random(a).randint(-3, 3), 1), [(2 * x, 3 * y) for x, y in fx.SHAPES[b]]) for a in range(8) for b in range(8)]


def truth(p, q):
    a, b = pixels(p), pixels(q)
    return len(a & b), len(a | b)


def frame(spark, cases):
    v = lambda r: [{"x": x, "y": y} for x, y in r]
    df = spark.createDataFrame([(0, k, k, v(p), v(q)) for k, (p, q) in enumerate(cases)], f"image_id int, p_id bigint, q_id bigint, ring_p {RING}, ring_q {RING}")
    return df.withColumns({f"{s}_{k}": c for s in "pq" for k, c in g.ring_mbr(F.col(f"ring_{s}")).items()})


def result(df):
    return {r.p_id: (r.inter, r.uni) for r in df.collect()}


@pytest.fixture(scope="module")
def want():
    return {k: truth(p, q) for k, (p, q) in enumerate(CASES)}


def test_native_kernels(spark, want):
    pairs = frame(spark, CASES)
    for kernel in (native.edge_form_areas, native.edge_form_areas_exploded, native.pixel_areas, native.pixel_span_areas):
        assert result(kernel(pairs)) == want, kernel.__name__


OPTIONS = [
    vector.Options(**o)
    for o in (
        {}, {"fan_out": 4, "threshold": 2}, {"fan_out": 4, "threshold": 2, "union": "direct"}, {"fan_out": 9, "threshold": 16, "root": "overlap"}, {"layout": "records", "edge_block": 1, "edge_cache": 0, "fan_out": 4, "threshold": 4},
        {"edge_cache": 5, "edge_block": 3, "fan_out": 4, "threshold": 2}, {"pixels_only": True, "union": "direct"}, {"frontier": "stack", "fan_out": 4, "threshold": 2, "chunk_cells": 7}, {"fan_out": 64, "threshold": 2048},
    )
]


@pytest.mark.parametrize("options", OPTIONS)
def test_adaptive_kernel(spark, want, options):
    assert result(vector.hybrid_areas(frame(spark, CASES), options)) == want


def test_overlay_and_relational(spark, want):
    pairs = frame(spark, CASES)
    assert result(vector.overlay_areas(pairs, union="direct", with_boxes=True)) == want
    assert result(relational.hybrid_relational(pairs, vector.Options(fan_out=4, threshold=4))) == want


def test_empty_pairs(spark):
    none = frame(spark, CASES).filter("false")
    for df in (vector.hybrid_areas(none), vector.overlay_areas(none), native.pixel_areas(none), native.edge_form_areas(none)):
        assert df.count() == 0
    assert similarity.mean_ratio(native.edge_form_areas(none), by=()).first().score is None


def test_work_falls_with_the_method(spark):
    p, q = fx.cells(spark, D, "P"), fx.cells(spark, D, "Q")
    pairs = pairing.candidate_pairs(p, q).filter("image_id >= 16")
    rows = metrics.sweep(pairs, [1, 3, 5], [vector.Options(pixels_only=True, union="direct"), vector.Options(union="direct"), vector.Options()]).collect()
    by = {(r.factor, r.method): r.pixels for r in rows}
    for k in (1, 3, 5):
        assert by[k, "hybrid"] <= by[k, "hybrid_joint"] <= by[k, "pixel"]
    assert by[5, "hybrid"] / by[5, "pixel"] < by[1, "hybrid"] / by[1, "pixel"]
    sweep = metrics.sweep(pairs, [3], [vector.Options(fan_out=16, threshold=t) for t in (2, 16, 128, 256)]).orderBy("threshold").collect()
    assert [r.pixels for r in sweep] == sorted(r.pixels for r in sweep)
    assert [r.boxes for r in sweep] == sorted((r.boxes for r in sweep), reverse=True)


def test_box_position_by_brute_force(spark):
    for ring in (NOTCH, PLUS, PIXEL, TOUCHED):
        inside = pixels(ring)
        boxes = [(x, y, x + w, y + h) for w in (1, 2, 4, 5) for h in (1, 3, 4) for x in range(-2, 13) for y in range(-2, 13)]
        count = lambda b: sum((i, j) in inside for i in range(b[0], b[2]) for j in range(b[1], b[3]))
        expected = [0 if not count(b) else 1 if count(b) == (b[2] - b[0]) * (b[3] - b[1]) else -1 for b in boxes]
        rings = vector.Rings(np.array([v[0] for v in ring], np.int64), np.array([v[1] for v in ring], np.int64), np.array([0, len(ring)]))
        cut = [np.array(c, np.int64) for c in zip(*boxes, strict=True)]
        assert rings.positions(np.zeros(len(boxes), np.int64), *cut, vector.Options()).tolist() == expected
        df = spark.createDataFrame(boxes, "a bigint, b bigint, c bigint, d bigint").withColumn("ring", F.array(*(F.struct(F.lit(x).cast("bigint").alias("x"), F.lit(y).cast("bigint").alias("y")) for x, y in ring)))
        got = {(r.a, r.b, r.c, r.d): r.p for r in df.select("a", "b", "c", "d", g.box_position(F.col("ring"), F.col("a"), F.col("b"), F.col("c"), F.col("d")).alias("p")).collect()}
        assert [got[b] for b in boxes] == expected


def test_splits_tile_the_parent():
    rng = random.Random(1)
    for _ in range(200):
        w, h, side = rng.randint(1, 30), rng.randint(1, 30), rng.randint(2, 8)
        _, x0, y0, x1, y1 = vector.split(*(np.array([v]) for v in (3, 5, 3 + w, 5 + h)), side)
        cells = {(i, j) for a, b, c, d in zip(x0, y0, x1, y1, strict=True) for i in range(a, c) for j in range(b, d)}
        assert len(cells) == w * h == int(((x1 - x0) * (y1 - y0)).sum())


def test_options_are_checked():
    for bad in ({"fan_out": 5}, {"threshold": 1}):
        o = vector.Options(**bad)
        with pytest.raises(ValueError, match="."):
            o.side, o.limit  # noqa: B018
    assert vector.default_threshold(64) == 2048


def test_relations(spark):
    cases = [(SQUARE, SQUARE), (SQUARE, moved(PIXEL, 0, 0)), (PIXEL, SQUARE), (SQUARE, moved(SQUARE, 6, 0)), (SQUARE, moved(SQUARE, 6, 6)), (SQUARE, moved(SQUARE, 3, 3)), (SQUARE, moved(SQUARE, 9, 0))]
    got = {r.p_id: r.relation for r in relate.relations(frame(spark, cases)).collect()}
    assert [got[k] for k in range(7)] == ["equals", "contains", "within", "touches", "touches", "overlaps", "disjoint"]
    meets = frame(spark, cases).select("p_id", g.poly_intersects(F.col("ring_p"), F.col("ring_q")).alias("m"))
    assert {r.p_id: r.m for r in meets.collect()} == {k: k != 6 for k in range(7)}


def test_sql_functions_agree(spark):
    g.register_sql_functions(spark)
    pairs = frame(spark, CASES)
    areas = native.edge_form_areas(pairs).select("p_id", "inter", "uni")
    rows = pairs.selectExpr("p_id", "seg_inter_area(ring_p, ring_q) AS i", "seg_union_area(ring_p, ring_q) AS u", "seg_touches(ring_p, ring_q) AS t", "seg_contains(ring_p, ring_q) AS c", "seg_ratio(ring_p, ring_q) AS r", "seg_box_position(ring_p, 1, 1, 4, 3) AS b", "seg_mbr(ring_p).maxx AS m", "ring_p", "ring_q", "p_maxx")
    rows = rows.join(areas, "p_id").withColumn("t2", g.poly_touches(F.col("ring_p"), F.col("ring_q"), F.col("inter"))).withColumn("b2", g.box_position(F.col("ring_p"), *(F.lit(v).cast("bigint") for v in (1, 1, 4, 3))))
    for r in rows.collect():
        assert (r.i, r.u, r.t, r.b, r.m) == (r.inter, r.uni, r.t2, r.b2, r.p_maxx)


def test_hilbert_curve_visits_each_place_once(spark):
    df = spark.range(256).select((F.col("id") % 16).alias("x"), F.floor(F.col("id") / 16).alias("y"))
    rows = df.select("x", "y", index.hilbert_key(F.col("x"), F.col("y"), 4).alias("d")).orderBy("d").collect()
    assert [r.d for r in rows] == list(range(256))
    assert all(abs(a.x - b.x) + abs(a.y - b.y) == 1 for a, b in zip(rows, rows[1:], strict=False))


def test_scores_and_missing(spark):
    v = lambda r: [{"x": x, "y": y} for x, y in r]
    make = lambda rings, algo: spark.createDataFrame([(0, 0, algo, k, v(r)) for k, r in enumerate(rings)], OBJECTS)
    p, q = make([SQUARE, moved(SQUARE, 50, 0)], "P"), make([moved(SQUARE, 3, 0)], "Q")
    areas = native.edge_form_areas(pairing.candidate_pairs(p, q))
    assert similarity.mean_ratio(areas).first().score == pytest.approx(18 / 54)
    lonely = make([SQUARE, moved(SQUARE, 50, 0), moved(SQUARE, 90, 90)], "P")
    assert similarity.mean_ratio(native.edge_form_areas(pairing.candidate_pairs(lonely, q))).first().score == pytest.approx(18 / 54)
    swapped = similarity.mean_ratio(native.edge_form_areas(pairing.candidate_pairs(q, p))).first().score
    assert swapped == pytest.approx(18 / 54)
    assert {(r.side, r.total, r.missing) for r in similarity.missing_objects(areas, p, q).collect()} == {("P", 2, 1), ("Q", 1, 0)}
    assert similarity.set_jaccard(p, p).first().score == 1.0


def test_parser_lanes_and_repairs(spark):
    lines = ["7 0 0 0 6 6 6 6 0", "8 0 0 6 0 6 6 0 6 0 0", "9 0 0 3 0 6 0 6 6 0 6", "1 0 0 5 5 5 0 0 5", "2 0 0 6 0 6 6", "3 0 0 6 0 6 0 6 6 0 6", "x", "", None, "4 1 2 3", "5 0 0 4 0 4 0.5 0 4", "6  0 0\t6 0 6 6 0 6", "10 0 0 4 0 0 0 4 0"]
    raw = spark.createDataFrame([(0, "P", 0, k, t) for k, t in enumerate(lines)], "image_id int, algo string, tile_id bigint, line_no bigint, text string")
    a, b = ({r.line_no: (r.reason, r.ring and [(v.x, v.y) for v in r.ring]) for r in parse.worked(raw, lane).collect()} for lane in ("native", "vector"))
    assert a == b
    assert a[7 - 7][1] == [(6, 0), (6, 6), (0, 6), (0, 0)] and a[1][1] == SQUARE and a[2][1] == SQUARE and a[11][1] == SQUARE
    assert [a[k][0] for k in (3, 4, 5, 6, 7, 8, 9, 10, 12)] == ["slanted edge", "too few vertices", "repeated vertex", "not integers", "not integers", "not integers", "odd count", "not integers", "no area"]


def test_rebalancer_never_loses_and_never_hurts(spark):
    rng = random.Random(2)
    tasks = [(k, rng.randint(1, 60), rng.randint(1, 90)) for k in range(120)]
    for name, rates in rebalance.CONFIGURATIONS.items():
        runs = [rebalance.simulate(tasks, rates, 8, m) for m in (False, True)]
        assert all(sorted(r["finished"]) == list(range(120)) for r in runs), name
        assert runs[1]["makespan"] <= runs[0]["makespan"], name
    assert rebalance.simulate([], rebalance.CONFIGURATIONS["I"], 4, True)["makespan"] == 0
    out = {(r.config, r.migrate): r.makespan for r in rebalance.simulate_pipeline(spark, pipeline.tasks(fx.cells(spark, D, "P"), fx.cells(spark, D, "Q"))).collect()}
    assert all(out[c, True] <= out[c, False] for c in rebalance.CONFIGURATIONS)


def test_measures():
    assert metrics.speedup(10, 2) == 5 and metrics.reduction(10, 6.6) == pytest.approx(0.34) and metrics.throughput(6, 2) == 3
    assert metrics.utilisation(4, 2, 4) == 0.5 and metrics.cost_effectiveness(6, 3) == 2


def test_sources(spark, tmp_path):
    made = io.generated(spark, images=2, tiles=3, cells=10)
    assert made.count() == 60 and io.valid_only(made)[1].count() == 0
    (tmp_path / "3_P_5.txt").write_text("7 0 0 6 0 6 6 0 6\nbad\n")
    read = io.read_polygon_text(spark, f"file://{tmp_path}/*.txt")
    objects, rejects = parse.parse_polygons(read)
    r = objects.first()
    assert (r.image_id, r.algo, r.tile_id, r.obj_id) == (3, "P", 5, 7) and rejects.count() == 1
    import struct

    wkb = spark.createDataFrame([(0, 0, "P", 1, [{"x": x, "y": y} for x, y in [(0, 3), (1000, 3), (1000, 77777), (0, 77777)]])], OBJECTS).select(io.ring_to_wkb(F.col("ring")).alias("b")).first().b
    assert struct.unpack("<BIII", bytes(wkb)[:13]) == (1, 3, 1, 5)
    assert struct.unpack("<10d", bytes(wkb)[13:]) == (0, 3, 1000, 3, 1000, 77777, 0, 77777, 0, 3)
    io.write_scores(made.limit(1).select("obj_id"), f"{tmp_path}/scores", 4)
    io.write_scores(made.limit(1).select("obj_id"), f"{tmp_path}/scores", 4)
    assert spark.read.parquet(f"{tmp_path}/scores").count() == 1
