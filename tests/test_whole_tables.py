"""Queries without SQL run over whole tables."""

import pytest

from segcompare import queries
from segcompare.plans import metrics


@pytest.mark.parametrize("name", ["work_scale", "work_threshold"])
def test_sweeps_take_all_pairs(spark, monkeypatch, name):
    rows = [(3, 0), (17, 0), (17, 5), (12, 63)]
    monkeypatch.setattr(queries, "_pairs", lambda s, d: spark.createDataFrame(rows, "image_id int, tile_id long"))
    monkeypatch.setattr(metrics, "sweep", lambda pairs, factors, settings: pairs)
    assert sorted(map(tuple, queries.REGISTRY[name](spark, "").collect())) == sorted(rows)
