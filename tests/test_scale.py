"""Queries that failed at larger sizes: the same results by ways that grow with their input."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from segcompare import queries
from segcompare.kernels import vector
from segcompare.operators import general, pairing
from segcompare.plans import metrics, rebalance
from segcompare.sources import fixtures as fx

D = "/root/testdata/sf0.001"


def rings(shapes):
    flat = np.concatenate([np.array(s, np.int64) for s in shapes])
    return vector.Rings(flat[:, 0].copy(), flat[:, 1].copy(), np.r_[0, np.cumsum([len(s) for s in shapes])])


def drawn(n, seed):
    rng = np.random.default_rng(seed)
    return [(np.array(fx.SHAPES[k]) * rng.integers(1, 5, 2) + rng.integers(0, 12, 2)).tolist() for k in rng.integers(0, 8, n)]


def test_batched_overlay_is_the_overlay_of_each_pair():
    a, b = drawn(300, 1), drawn(300, 2)
    for union in (False, True):
        boxes = [vector.overlay(np.array(x), np.array(y), union) for x, y in zip(a, b, strict=True)]
        want = [int(((v[:, 2] - v[:, 0]) * (v[:, 3] - v[:, 1])).sum()) for v in boxes]
        for cells in (1, 500, 2_000_000):
            assert vector.overlay_sums(rings(a), rings(b), union, cells).tolist() == want
    at = np.arange(300)
    assert vector.edge_form_sums(rings(a), at, rings(b), at, 50).tolist() == vector.overlay_sums(rings(a), rings(b)).tolist()


def test_records_are_batched_too(monkeypatch):
    """As many calls as levels, not as boxes."""
    calls, real = [], vector._advance
    monkeypatch.setattr(vector, "_advance", lambda *a: calls.append(1) or real(*a))
    vector.hybrid(rings(drawn(200, 3)), rings(drawn(200, 4)), vector.Options(layout="records"))
    assert len(calls) < 10


def test_no_more_than_a_million_parts_at_once():
    assert all(o.at_once * o.fan_out <= 1 << 20 for o in (vector.Options(), vector.Options(fan_out=256), vector.Options(fan_out=4)))


def test_sweep_is_one_pass(spark):
    pairs = pairing.candidate_pairs(fx.cells(spark, D, "P"), fx.cells(spark, D, "Q")).filter("image_id = 17")
    plan = metrics.sweep(pairs, [1, 3], [vector.Options(), vector.Options(threshold=4)])._jdf.queryExecution().executedPlan().toString()
    assert plan.count("MapInArrow") <= 2  # the plan shows an adaptive node's first and current form


def test_theta_join_makes_no_pairs(spark):
    assert "Join" not in general.op_join_theta(spark, D)._jdf.queryExecution().optimizedPlan().toString()


def test_nested_pairs_meet_in_bands(spark):
    p, q = fx.cells(spark, D, "P"), fx.cells(spark, D, "Q")
    ids = lambda df: sorted(map(tuple, pairing.ids(df, with_tile=False).collect()))
    want = ids(pairing.candidate_pairs(p, q, scope="image"))
    assert all(ids(pairing.nested_pairs(p, q, band=b)) == want for b in (7, 64, 100_000))
    condition = "band"
    assert condition in pairing.nested_pairs(p, q)._jdf.queryExecution().optimizedPlan().toString()


@pytest.mark.parametrize("name", ["objects_by_size", "touches_pairs"])
def test_rings_are_not_made_anew_in_filters(spark, name):
    """The outlines stand in the plan once for each set and place, not once for each use of a ring."""
    plan = queries.REGISTRY[name](spark, D)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("element_at") <= 3


def test_simulator_takes_tasks_one_by_one():
    rates = rebalance.CONFIGURATIONS["II"]
    made = [(k, 1 + k * 7 % 60, 1 + k * 11 % 90) for k in range(150_000)]
    held = rebalance.simulate(made[:3000], rates, 8, True)
    lazy = rebalance.simulate(iter(made[:3000]), rates, 8, True)
    assert {k: v for k, v in lazy.items() if k != "finished"} == {k: v for k, v in held.items() if k != "finished"}
    assert rebalance.simulate(iter(made), rates, 8, True)["makespan"] > held["makespan"]


def test_generated_objects_lie_where_the_orders_do(spark):
    want = fx.cells(spark, D, "P").groupBy("image_id").agg(F.count(F.lit(1)).alias("n"))
    got = queries.REGISTRY["io_generated"](spark, D).select("image_id", "n")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
