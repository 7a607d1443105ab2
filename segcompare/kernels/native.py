"""Kernels of column expressions: signed-edge closed form, pixel counting, row spans."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as g

KEYS = ["image_id", "p_id", "q_id"]


def _finish(pairs: DataFrame, inter: Column) -> DataFrame:
    rows = pairs.select(*KEYS, inter.cast("bigint").alias("inter"), g.ring_area(F.col("ring_p")).alias("area_p"), g.ring_area(F.col("ring_q")).alias("area_q"))
    return rows.select(*KEYS, "inter", (F.col("area_p") + F.col("area_q") - F.col("inter")).alias("uni"), "area_p", "area_q")


def areas_only(df: DataFrame) -> DataFrame:
    return df.select(*KEYS, "inter", "uni")


def edge_form_areas(pairs: DataFrame) -> DataFrame:
    """The closed form over pairs of vertical edges, one projection and no exchange."""
    return _finish(pairs, g.edge_form_inter(F.col("ring_p"), F.col("ring_q")))


def edge_form_areas_exploded(pairs: DataFrame) -> DataFrame:
    """The same closed form for long rings: edges as rows, partial and final sums."""
    p = pairs.select(*KEYS, "ring_q", F.explode(g.vertical_edges(F.col("ring_p"))).alias("e"))
    both = p.select(*KEYS, "e", F.explode(g.vertical_edges(F.col("ring_q"))).alias("f"))
    height = F.least("e.hi", "f.hi") - F.greatest("e.lo", "f.lo")
    term = F.when(height > 0, -F.col("e.sgn") * F.col("f.sgn") * height * F.greatest("e.x", "f.x")).otherwise(0)
    inter = both.groupBy(*KEYS).agg(F.sum(term).cast("bigint").alias("inter"))
    sizes = pairs.select(*KEYS, g.ring_area(F.col("ring_p")).alias("area_p"), g.ring_area(F.col("ring_q")).alias("area_q"))
    return sizes.join(inter, KEYS).select(*KEYS, "inter", (F.col("area_p") + F.col("area_q") - F.col("inter")).alias("uni"))


def _pixels(pairs: DataFrame) -> DataFrame:
    """One row per pixel of the pair's joint box, with both tests."""
    lo = lambda c: F.least(f"p_{c}", f"q_{c}")
    hi = lambda c: F.greatest(f"p_{c}", f"q_{c}")
    edged = pairs.select(*KEYS, g.vertical_edges(F.col("ring_p")).alias("ep"), g.vertical_edges(F.col("ring_q")).alias("eq"), lo("minx").alias("x0"), hi("maxx").alias("x1"), lo("miny").alias("y0"), hi("maxy").alias("y1"))
    rows = edged.select(*KEYS, "x0", "x1", F.explode(F.sequence("y0", F.col("y1") - 1)).alias("j"), "ep", "eq")
    on_row = lambda e: F.transform(F.filter(e, lambda s: (s["lo"] <= F.col("j")) & (F.col("j") < s["hi"])), lambda s: s["x"])
    rows = rows.select(*KEYS, "x0", "x1", on_row("ep").alias("xp"), on_row("eq").alias("xq"))
    cells = rows.select(*KEYS, F.explode(F.sequence("x0", F.col("x1") - 1)).alias("i"), "xp", "xq")
    inside = lambda xs: (F.size(F.filter(xs, lambda x: x > F.col("i"))) % 2 == 1)
    return cells.select(*KEYS, inside("xp").alias("in_p"), inside("xq").alias("in_q"))


def pixel_areas(pairs: DataFrame) -> DataFrame:
    """Pixel-only counting of intersection and union in one pass over the joint box."""
    return _pixels(pairs).groupBy(*KEYS).agg(F.count_if(F.col("in_p") & F.col("in_q")).alias("inter"), F.count_if(F.col("in_p") | F.col("in_q")).alias("uni"))


def pixel_classes(pairs: DataFrame) -> DataFrame:
    """Pixels of the joint box in both rings, in one, in none."""
    both, one = F.col("in_p") & F.col("in_q"), F.col("in_p") != F.col("in_q")
    return _pixels(pairs).groupBy(*KEYS).agg(F.count_if(both).alias("n_both"), F.count_if(one).alias("n_one"), F.count_if(~F.col("in_p") & ~F.col("in_q")).alias("n_none"))


def pixel_span_areas(pairs: DataFrame) -> DataFrame:
    """Pixel counting by rows: the inside of a ring on a row is spans between its sorted crossings."""
    y0, y1 = F.greatest("p_miny", "q_miny"), F.least("p_maxy", "q_maxy")
    edged = pairs.select(*KEYS, "ring_p", "ring_q", g.vertical_edges(F.col("ring_p")).alias("ep"), g.vertical_edges(F.col("ring_q")).alias("eq"), F.when(y1 > y0, F.sequence(y0, y1 - 1)).otherwise(F.array().cast("array<bigint>")).alias("js"))
    rows = edged.select(*KEYS, "ep", "eq", F.explode("js").alias("j"))
    crossings = lambda e: F.array_sort(F.transform(F.filter(e, lambda s: (s["lo"] <= F.col("j")) & (F.col("j") < s["hi"])), lambda s: s["x"]))
    rows = rows.select(*KEYS, crossings("ep").alias("xp"), crossings("eq").alias("xq"))
    spans = lambda xs: F.transform(F.sequence(F.lit(0), F.floor(F.size(xs) / 2).cast("int") - 1), lambda k: F.struct(F.get(xs, 2 * k).alias("a"), F.get(xs, 2 * k + 1).alias("b")))
    rows = rows.filter((F.size("xp") > 0) & (F.size("xq") > 0)).select(*KEYS, spans("xp").alias("sp"), spans("xq").alias("sq"))
    zero = F.lit(0).cast("bigint")
    common = F.aggregate("sp", zero, lambda t, p: t + F.aggregate("sq", zero, lambda u, q: u + F.greatest(F.least(p["b"], q["b"]) - F.greatest(p["a"], q["a"]), zero)))
    inter = rows.groupBy(*KEYS).agg(F.sum(common).alias("inter"))
    return areas_only(_finish(pairs.join(inter, KEYS, "left"), F.coalesce("inter", zero)))
