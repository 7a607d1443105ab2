"""Ring geometry as Column expressions: areas, boxes, edges, pixel and box tests.

A ring is an array of integer vertices (x, y), not closed explicitly, with edges parallel to the axes. Pixel
(i, j) is the unit square from (i, j); it is inside where its centre is. All functions stay in the JVM.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schema import EDGES


def rotated(ring: Column) -> Column:
    """The ring from its second vertex on, so that entry k is the vertex after entry k of the ring."""
    return F.concat(F.slice(ring, F.lit(2), F.greatest(F.size(ring) - 1, F.lit(0))), F.slice(ring, 1, 1))


def signed_area2(ring: Column) -> Column:
    """Twice the signed area; coordinates are taken from the first vertex, which keeps products small."""
    ox, oy = ring[0]["x"], ring[0]["y"]
    cross = F.zip_with(ring, rotated(ring), lambda a, b: (a["x"] - ox) * (b["y"] - oy) - (b["x"] - ox) * (a["y"] - oy))
    return F.aggregate(cross, F.lit(0).cast("bigint"), lambda s, v: s + v)


def ring_area(ring: Column) -> Column:
    """Area by the vertex formula."""
    return F.shiftright(F.abs(signed_area2(ring)), 1)


def area_partials(df, id_cols: list[str], ring: str = "ring"):
    """One row per edge with its share of twice the area; sum and halve to get the area of each object."""
    r = F.col(ring)
    pairs = F.arrays_zip(r.alias("a"), rotated(r).alias("b"))
    return df.select(*id_cols, F.posexplode(pairs).alias("seq", "e")).select(*id_cols, "seq", (F.col("e.a.x") * F.col("e.b.y") - F.col("e.b.x") * F.col("e.a.y")).alias("part"))


def ring_mbr(ring: Column) -> dict[str, Column]:
    """The bounding box as four columns."""
    xs, ys = F.transform(ring, lambda v: v["x"]), F.transform(ring, lambda v: v["y"])
    return {"minx": F.array_min(xs), "miny": F.array_min(ys), "maxx": F.array_max(xs), "maxy": F.array_max(ys)}


def vertical_edges(ring: Column) -> Column:
    """Vertical edges (x, lo, hi, sgn); in a counter-clockwise ring sgn is 1 at a left border, -1 at a right one."""
    both = F.zip_with(ring, rotated(ring), lambda a, b: F.struct(a["x"].alias("x"), F.least(a["y"], b["y"]).alias("lo"), F.greatest(a["y"], b["y"]).alias("hi"), F.when(b["y"] < a["y"], 1).otherwise(-1).alias("sgn"), (a["x"] == b["x"]).alias("up")))
    return F.transform(F.filter(both, lambda e: e["up"]), lambda e: F.struct(e["x"].alias("x"), e["lo"].alias("lo"), e["hi"].alias("hi"), e["sgn"].alias("sgn"))).cast(EDGES)


def pixel_in_ring(ring: Column, i: Column, j: Column) -> Column:
    """Even-odd test of a pixel's centre with a ray to the right."""
    crossing = F.filter(vertical_edges(ring), lambda e: (e["x"] > i) & (e["lo"] <= j) & (j < e["hi"]))
    return F.size(crossing) % 2 == 1


def box_position(ring: Column, x0: Column, y0: Column, x1: Column, y1: Column) -> Column:
    """1 inside, 0 outside, -1 straddling: straddling where an edge meets the open box, else as its first pixel."""
    sides = F.zip_with(ring, rotated(ring), lambda a, b: F.struct(F.least(a["x"], b["x"]).alias("ax"), F.greatest(a["x"], b["x"]).alias("bx"), F.least(a["y"], b["y"]).alias("ay"), F.greatest(a["y"], b["y"]).alias("by")))
    upright = lambda e: (e["ax"] == e["bx"]) & (e["ax"] > x0) & (e["ax"] < x1) & (e["ay"] < y1) & (e["by"] > y0)
    level = lambda e: (e["ay"] == e["by"]) & (e["ay"] > y0) & (e["ay"] < y1) & (e["ax"] < x1) & (e["bx"] > x0)
    return F.when(F.exists(sides, lambda e: upright(e) | level(e)), -1).when(pixel_in_ring(ring, x0, y0), 1).otherwise(0)


def scale_ring(ring: Column, factor: int) -> Column:
    return F.transform(ring, lambda v: F.struct((v["x"] * factor).alias("x"), (v["y"] * factor).alias("y")))


def edge_form_inter(ring_p: Column, ring_q: Column) -> Column:
    """Exact intersection area from pairs of vertical edges: minus the sum of sign products times common height times the larger x."""
    eq = vertical_edges(ring_q)

    def with_q(a: Column, p: Column) -> Column:
        inner = F.aggregate(eq, F.lit(0).cast("bigint"), lambda s, q: s + p["sgn"] * q["sgn"] * F.greatest(F.least(p["hi"], q["hi"]) - F.greatest(p["lo"], q["lo"]), F.lit(0).cast("bigint")) * F.greatest(p["x"], q["x"]))
        return a - inner

    return F.aggregate(vertical_edges(ring_p), F.lit(0).cast("bigint"), with_q)


def _proper_or_touch(ring_p: Column, ring_q: Column, strict: bool) -> Column:
    """Whether some edge of p crosses (strict) or meets (not strict) some edge of q at right angles or along it."""
    sides = lambda r: F.zip_with(r, rotated(r), lambda a, b: F.struct(F.least(a["x"], b["x"]).alias("ax"), F.greatest(a["x"], b["x"]).alias("bx"), F.least(a["y"], b["y"]).alias("ay"), F.greatest(a["y"], b["y"]).alias("by")))

    def meet(e: Column, f: Column) -> Column:
        if strict:
            upright_level = (e["ax"] == e["bx"]) & (f["ay"] == f["by"]) & (f["ax"] < e["ax"]) & (e["ax"] < f["bx"]) & (e["ay"] < f["ay"]) & (f["ay"] < e["by"])
            level_upright = (e["ay"] == e["by"]) & (f["ax"] == f["bx"]) & (e["ax"] < f["ax"]) & (f["ax"] < e["bx"]) & (f["ay"] < e["ay"]) & (e["ay"] < f["by"])
            return upright_level | level_upright
        return (e["ax"] <= f["bx"]) & (f["ax"] <= e["bx"]) & (e["ay"] <= f["by"]) & (f["ay"] <= e["by"])

    return F.exists(sides(ring_p), lambda e: F.exists(sides(ring_q), lambda f: meet(e, f)))


def poly_intersects(ring_p: Column, ring_q: Column) -> Column:
    """Closed intersection: boundaries meet, or one ring contains the other."""
    inside = lambda a, b: pixel_in_ring(b, a[0]["x"], a[0]["y"])
    return _proper_or_touch(ring_p, ring_q, strict=False) | inside(ring_p, ring_q) | inside(ring_q, ring_p)


def crosses_properly(ring_p: Column, ring_q: Column) -> Column:
    return _proper_or_touch(ring_p, ring_q, strict=True)


def on_boundary(vertex: Column, ring: Column) -> Column:
    sides = F.zip_with(ring, rotated(ring), lambda a, b: F.struct(F.least(a["x"], b["x"]).alias("ax"), F.greatest(a["x"], b["x"]).alias("bx"), F.least(a["y"], b["y"]).alias("ay"), F.greatest(a["y"], b["y"]).alias("by")))
    return F.exists(sides, lambda e: (e["ax"] <= vertex["x"]) & (vertex["x"] <= e["bx"]) & (e["ay"] <= vertex["y"]) & (vertex["y"] <= e["by"]))


def strictly_inside(vertex: Column, ring: Column) -> Column:
    """A vertex off the boundary whose surroundings are inside."""
    return ~on_boundary(vertex, ring) & pixel_in_ring(ring, vertex["x"], vertex["y"])


def poly_touches(ring_p: Column, ring_q: Column, inter: Column) -> Column:
    """Common boundary without common area: no proper crossing, no vertex strictly inside the other, some vertex on the other's boundary."""
    some_inside = F.exists(ring_p, lambda v: strictly_inside(v, ring_q)) | F.exists(ring_q, lambda v: strictly_inside(v, ring_p))
    some_on = F.exists(ring_p, lambda v: on_boundary(v, ring_q)) | F.exists(ring_q, lambda v: on_boundary(v, ring_p))
    return (inter == 0) & ~crosses_properly(ring_p, ring_q) & ~some_inside & some_on


def sides(ring: Column) -> Column:
    """The edges as boxes (ax, ay, bx, by) without width or height."""
    return F.zip_with(ring, rotated(ring), lambda a, b: F.struct(F.least(a["x"], b["x"]).alias("ax"), F.least(a["y"], b["y"]).alias("ay"), F.greatest(a["x"], b["x"]).alias("bx"), F.greatest(a["y"], b["y"]).alias("by")))


def touching(pairs: DataFrame) -> DataFrame:
    """Of pairs without common area (ring_p, ring_q), those that poly_touches accepts: edges that meet.

    Edges of such rings cannot cross, and no vertex of one lies inside the other, as either would bring common area;
    so they touch where an edge of one meets an edge of the other.
    """
    edged = once(pairs, _sp=sides(F.col("ring_p")), _sq=sides(F.col("ring_q")))
    meet = lambda e, f: (e["ax"] <= f["bx"]) & (f["ax"] <= e["bx"]) & (e["ay"] <= f["by"]) & (f["ay"] <= e["by"])
    return edged.filter(F.exists("_sp", lambda e: F.exists("_sq", lambda f: meet(e, f)))).drop("_sp", "_sq")


def centroid(ring: Column) -> Column:
    """(x, y) of the centre of mass."""
    ox, oy = ring[0]["x"], ring[0]["y"]
    terms = F.zip_with(ring, rotated(ring), lambda a, b: F.struct((a["x"] - ox + b["x"] - ox).alias("sx"), (a["y"] - oy + b["y"] - oy).alias("sy"), ((a["x"] - ox) * (b["y"] - oy) - (b["x"] - ox) * (a["y"] - oy)).alias("c")))
    zero = F.lit(0).cast("bigint")
    total = lambda f: F.aggregate(terms, zero, lambda s, t: s + f(t))
    three = 3 * signed_area2(ring)
    return F.struct((ox + total(lambda t: t["sx"] * t["c"]) / three).alias("x"), (oy + total(lambda t: t["sy"] * t["c"]) / three).alias("y"))


def centroid_distance(ring_p: Column, ring_q: Column) -> Column:
    a, b = centroid(ring_p), centroid(ring_q)
    return F.sqrt((a["x"] - b["x"]) * (a["x"] - b["x"]) + (a["y"] - b["y"]) * (a["y"] - b["y"]))


def validity(ring: Column) -> Column:
    """NULL for a valid ring, else the reason it is rejected."""
    nexts = F.zip_with(ring, rotated(ring), lambda a, b: F.struct((a["x"] == b["x"]).alias("up"), (a["y"] == b["y"]).alias("flat")))
    return (
        F.when(ring.isNull(), "no ring")
        .when(F.size(ring) < 4, "too few vertices")
        .when(F.exists(nexts, lambda e: e["up"] & e["flat"]), "repeated vertex")
        .when(F.exists(nexts, lambda e: ~e["up"] & ~e["flat"]), "slanted edge")
        .when(signed_area2(ring) == 0, "no area")
        .when(crosses_itself(ring), "crosses itself")
    )


def assembled_rings(vertices: DataFrame, keys: list[str]) -> DataFrame:
    """Vertex rows (keys, seq, x, y) in any order -> keys, ring in order of seq."""
    v = F.struct("seq", F.col("x").cast("bigint").alias("x"), F.col("y").cast("bigint").alias("y"))
    rings = vertices.groupBy(*keys).agg(F.array_sort(F.collect_list(v)).alias("v"))
    return rings.select(*keys, F.transform("v", lambda p: F.struct(p["x"].alias("x"), p["y"].alias("y"))).alias("ring"))


def crosses_itself(ring: Column) -> Column:
    """Whether an upright edge meets a flat one of the same ring inside both."""
    sides = F.zip_with(ring, rotated(ring), lambda a, b: F.struct(F.least(a["x"], b["x"]).alias("ax"), F.greatest(a["x"], b["x"]).alias("bx"), F.least(a["y"], b["y"]).alias("ay"), F.greatest(a["y"], b["y"]).alias("by")))
    upright, flat = F.filter(sides, lambda e: e["ax"] == e["bx"]), F.filter(sides, lambda e: e["ay"] == e["by"])
    return F.exists(upright, lambda u: F.exists(flat, lambda f: (f["ax"] < u["ax"]) & (u["ax"] < f["bx"]) & (u["ay"] < f["ay"]) & (f["ay"] < u["by"])))


def once(df: DataFrame, **columns: Column) -> DataFrame:
    """df with further columns that are computed once: a generator of one row keeps the optimizer from
    copying an expression into each of its uses, which inside lambdas would repeat it for every element."""
    return df.select("*", F.inline(F.array(F.struct(*(c.alias(n) for n, c in columns.items())))))


def opened(ring: Column) -> Column:
    """The ring without an explicit closing vertex."""
    return F.when((F.size(ring) > 1) & (ring[0] == F.element_at(ring, -1)), F.slice(ring, F.lit(1), F.size(ring) - 1)).otherwise(ring)


def repaired(df: DataFrame, ring: str, out: str) -> DataFrame:
    """df with `out`: the ring without closing vertex and collinear vertices, counter-clockwise."""
    names = df.columns
    df = once(df, _opened=opened(F.col(ring)))
    r, n = F.col("_opened"), F.size("_opened")

    def straight(v: Column, k: Column, c: str) -> Column:
        return (F.get(r, (k + n - 1) % n)[c] == v[c]) & (F.get(r, (k + 1) % n)[c] == v[c])

    df = once(df, _corners=F.filter(r, lambda v, k: ~(straight(v, k, "x") | straight(v, k, "y"))))
    corners = F.col("_corners")
    return df.select(*(c for c in names if c != out), F.when(signed_area2(corners) < 0, F.reverse(corners)).otherwise(corners).alias(out))


# SQL-defined functions: Catalyst inlines them, no Python runs.
_R = "array<struct<x:bigint,y:bigint>>"
_NEXT = "concat(slice({0}, 2, size({0}) - 1), slice({0}, 1, 1))"
_EDGES = "filter(zip_with({0}, " + _NEXT + ", (a, b) -> named_struct('x', a.x, 'lo', least(a.y, b.y), 'hi', greatest(a.y, b.y), 'sgn', if(b.y < a.y, 1, -1), 'up', a.x = b.x)), e -> e.up)"
_SIDES = "zip_with({0}, " + _NEXT + ", (a, b) -> named_struct('ax', least(a.x, b.x), 'bx', greatest(a.x, b.x), 'ay', least(a.y, b.y), 'by', greatest(a.y, b.y)))"
SQL_FUNCTIONS = {
    "seg_area": (f"ring {_R}", "bigint", "shiftright(abs(aggregate(zip_with(ring, " + _NEXT.format("ring") + ", (a, b) -> (a.x - ring[0].x) * (b.y - ring[0].y) - (b.x - ring[0].x) * (a.y - ring[0].y)), 0L, (s, v) -> s + v)), 1)"),
    "seg_mbr": (f"ring {_R}", "struct<minx:bigint,miny:bigint,maxx:bigint,maxy:bigint>", "named_struct('minx', array_min(transform(ring, v -> v.x)), 'miny', array_min(transform(ring, v -> v.y)), 'maxx', array_max(transform(ring, v -> v.x)), 'maxy', array_max(transform(ring, v -> v.y)))"),
    "seg_pixel_inside": (f"ring {_R}, i bigint, j bigint", "boolean", "size(filter(" + _EDGES.format("ring") + ", e -> e.x > i AND e.lo <= j AND j < e.hi)) % 2 = 1"),
    "seg_inter_area": (f"p {_R}, q {_R}", "bigint", "aggregate(" + _EDGES.format("p") + ", 0L, (t, e) -> t - aggregate(" + _EDGES.format("q") + ", 0L, (s, f) -> s + e.sgn * f.sgn * greatest(least(e.hi, f.hi) - greatest(e.lo, f.lo), 0L) * greatest(e.x, f.x)))"),
    "seg_union_area": (f"p {_R}, q {_R}", "bigint", "seg_area(p) + seg_area(q) - seg_inter_area(p, q)"),
    "seg_ratio": (f"p {_R}, q {_R}", "double", "try_divide(seg_inter_area(p, q), seg_union_area(p, q))"),
    "seg_box_position": (f"ring {_R}, x0 bigint, y0 bigint, x1 bigint, y1 bigint", "int", "CASE WHEN exists(" + _SIDES.format("ring") + ", e -> (e.ax = e.bx AND e.ax > x0 AND e.ax < x1 AND e.ay < y1 AND e.by > y0) OR (e.ay = e.by AND e.ay > y0 AND e.ay < y1 AND e.ax < x1 AND e.bx > x0)) THEN -1 WHEN seg_pixel_inside(ring, x0, y0) THEN 1 ELSE 0 END"),
    "seg_touches": (f"p {_R}, q {_R}", "boolean", "seg_inter_area(p, q) = 0 AND exists(" + _SIDES.format("p") + ", e -> exists(" + _SIDES.format("q") + ", f -> e.ax <= f.bx AND f.ax <= e.bx AND e.ay <= f.by AND f.ay <= e.by))"),
    "seg_contains": (f"p {_R}, q {_R}", "boolean", "seg_inter_area(p, q) = seg_area(q)"),
}


def register_sql_functions(spark: SparkSession) -> None:
    """CREATE TEMPORARY FUNCTION for each of SQL_FUNCTIONS."""
    for name, (arguments, kind, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({arguments}) RETURNS {kind} RETURN {body}")
