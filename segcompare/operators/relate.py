"""Spatial relations of pairs, from areas and boundary tests."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as g
from ..kernels.native import KEYS


def with_areas(pairs: DataFrame) -> DataFrame:
    """pairs with inter, area_p and area_q."""
    return pairs.withColumns({"inter": g.edge_form_inter(F.col("ring_p"), F.col("ring_q")), "area_p": g.ring_area(F.col("ring_p")), "area_q": g.ring_area(F.col("ring_q"))})


def poly_contains(inter: Column, area_of_contained: Column) -> Column:
    return inter == area_of_contained


def poly_relation(inter: Column, area_p: Column, area_q: Column, touches: Column) -> Column:
    """equals, contains, within, overlaps, touches or disjoint, the first that holds."""
    return (
        F.when((inter == area_p) & (inter == area_q), "equals").when(inter == area_q, "contains").when(inter == area_p, "within").when(inter > 0, "overlaps").when(touches, "touches").otherwise("disjoint")
    )


def contains_pairs(pairs: DataFrame) -> DataFrame:
    return with_areas(pairs).filter(poly_contains(F.col("inter"), F.col("area_q"))).select(*KEYS)


def touches_pairs(pairs: DataFrame) -> DataFrame:
    """Pairs without common area whose boundaries meet."""
    # computed once each: a filter on top would else put the whole closed form and all edges into every comparison
    none = g.once(pairs, inter=g.edge_form_inter(F.col("ring_p"), F.col("ring_q"))).filter("inter = 0")
    return g.touching(none.select(*KEYS, "ring_p", "ring_q")).select(*KEYS)


def relations(pairs: DataFrame) -> DataFrame:
    rows = with_areas(pairs)
    touches = g.poly_touches(F.col("ring_p"), F.col("ring_q"), F.col("inter"))
    return rows.select(*KEYS, poly_relation(F.col("inter"), F.col("area_p"), F.col("area_q"), touches).alias("relation"))
