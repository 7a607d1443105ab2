"""Skylines made in batches, and results that meet in one exchange."""

import numpy as np
from pyspark.sql import functions as F

from segcompare import queries
from segcompare.kernels import native
from segcompare.operators import similarity
from segcompare.sources import fixtures as fx


def outline(width, heights, shift):
    """One ring, vertex by vertex."""
    n, left = len(heights), width * shift
    ring = [(left, 0), (left + n * width, 0)]
    for k in range(n - 1, -1, -1):
        ring += [(left + (k + 1) * width, heights[k]), (left + k * width, heights[k])]
    straight = lambda k, c: ring[k - 1][c] == ring[k][c] == ring[(k + 1) % len(ring)][c]
    corners = [v for k, v in enumerate(ring) if not straight(k, 0) and not straight(k, 1)]
    turned = sum(a[0] * b[1] - b[0] * a[1] for a, b in zip(corners, corners[1:] + corners[:1], strict=True))
    return corners[::-1] if turned < 0 else corners


def test_skylines_of_a_batch():
    rng = np.random.default_rng(1)
    widths = np.array([1, 2, 3, 1, -1, 0])
    heights = [rng.integers(1, 4, n).tolist() for n in (1, 7, 128, 2, 9, 3)]
    for shift in (0, 1):
        x, y, n = fx.skyline_rings(widths, np.concatenate(heights), np.array([len(h) for h in heights]), shift)
        got = np.split(np.stack([x, y], 1), np.cumsum(n)[:-1])
        assert [[tuple(v) for v in r.tolist()] for r in got] == [outline(w, h, shift) for w, h in zip(widths.tolist(), heights, strict=True)]


def test_columns_are_made_in_batches(spark, tmp_path):
    docs = [(1, "a bb  cc ddd", 12), (2, None, 3), (3, "", 0), (4, "x y", None), (5, " ".join("w" * (k % 7 + 1) for k in range(300)), 1501)]
    spark.createDataFrame(docs, "doc_id long, text string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    df = fx.columns(spark, str(tmp_path), shift=1)
    assert "MapInArrow" in df._jdf.queryExecution().executedPlan().toString()
    want = {65536: outline(1, [2, 3, 3, 4], 1), 4 * 65536: []} | {5 * 65536 + p: outline(2, [k % 7 + 2 for k in range(300)][128 * p : 128 * (p + 1)], 1) for p in range(3)}
    assert {r.obj_id: [tuple(v) for v in r.ring] for r in df.collect()} == want


def test_agreement_counts_as_a_join_would(spark):
    """Missing, differing and repeated rows, null ids and null areas; each result is computed once."""
    schema = "image_id int, p_id long, q_id long, inter long, uni long"
    ref = [(0, 1, 1, 5, 9), (0, 1, 2, 5, 9), (0, 2, 2, 1, 1), (0, 2, 2, 2, 2), (0, 3, 3, None, 4), (0, None, 4, 1, 1)]
    a = [(0, 1, 1, 5, 9), (0, 1, 2, 5, 8), (0, 2, 2, 1, 1), (0, 2, 2, 1, 1), (0, 3, 3, None, 4), (0, None, 4, 1, 1), (0, 9, 9, 0, 0)]
    frames = [spark.createDataFrame(r, schema) for r in (ref, a, [])]
    got = similarity.agreement(frames[0], a=frames[1], none=frames[2])
    want = {}
    for name, df in (("a", frames[1]), ("none", frames[2])):
        j = frames[0].join(df.select(*native.KEYS, F.col("inter").alias("i"), F.col("uni").alias("u")), native.KEYS, "full_outer")
        bad = ~(F.col("inter").eqNullSafe(F.col("i")) & F.col("uni").eqNullSafe(F.col("u")))
        want[name] = tuple(j.agg(F.count(F.lit(1)), F.count_if(bad)).first())
    assert {r.method: (r.pairs, r.mismatches) for r in got.collect()} == want
    empty = similarity.agreement(frames[2], a=frames[2])
    assert [tuple(r) for r in empty.collect()] == [("a", 0, 0)]
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and plan.count("Exchange hashpartitioning") == plan.count("Exchange hashpartitioning(image_id")


def test_agreement_of_shapes_makes_its_pairs_once(spark, monkeypatch):
    made, real = [], queries.materialised
    monkeypatch.setattr(queries, "materialised", lambda df, name: made.append(name) or real(df, name))
    rows = queries.REGISTRY["agreement_shapes"](spark, "/root/testdata/sf0.001").collect()
    assert made == ["vessels", "columns"] and len(rows) == 6 and not any(r.mismatches for r in rows)
