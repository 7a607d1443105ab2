"""The adaptive kernel as a DataFrame program: one level of splitting per round."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as g
from .native import KEYS
from .vector import Options

_BOXES = "array<struct<x0:bigint,y0:bigint,x1:bigint,y1:bigint>>"


def hybrid_relational(pairs: DataFrame, options: Options = Options()) -> DataFrame:
    """inter and uni by rounds of split, judge and filter over the pair's open boxes, which stay in the pair's row.

    Rounds are at most the base-g logarithm of the longest side, plus one; the driver only asks for that side. Rings
    are turned into edges once, and no row moves.
    """
    corners = [*(F.greatest(f"p_{c}", f"q_{c}").alias(n) for c, n in (("minx", "x0"), ("miny", "y0"))), *(F.least(f"p_{c}", f"q_{c}").alias(n) for c, n in (("maxx", "x1"), ("maxy", "y1")))]
    longest = pairs.select(*corners).agg(F.max(F.greatest(F.col("x1") - F.col("x0"), F.col("y1") - F.col("y0")))).first()[0] or 0
    ring = lambda s: F.col(f"ring_{s}")
    rows = pairs.select(*KEYS, "ring_p", "ring_q", F.struct(*corners).alias("root"))
    root = F.when((F.col("root.x1") > F.col("root.x0")) & (F.col("root.y1") > F.col("root.y0")), F.array("root")).otherwise(F.array()).cast(_BOXES)
    zero = F.lit(0).cast("bigint")
    rows = g.once(rows, _p=g.sides(ring("p")), _q=g.sides(ring("q")), area_p=g.ring_area(ring("p")), area_q=g.ring_area(ring("q")), _open=root, _inter=zero).drop("ring_p", "ring_q", "root")
    size = lambda b: (b["x1"] - b["x0"]) * (b["y1"] - b["y0"])
    names = (*KEYS, "area_p", "area_q", "_p", "_q")
    while True:
        small = F.aggregate(F.filter("_open", lambda b: size(b) < options.limit), zero, lambda s, b: s + _pixels(b))
        judged = F.transform(F.flatten(F.transform(F.filter("_open", lambda b: size(b) >= options.limit), lambda b: _parts(b, options.side))), _judged)
        rows = g.once(rows.select(*names, "_open", "_inter"), _small=small, _judged=judged)
        covered = F.aggregate(F.filter("_judged", lambda b: (b["f1"] == 1) & (b["f2"] == 1)), zero, lambda s, b: s + size(b))
        open_ = F.filter("_judged", lambda b: ((b["f1"] == -1) | (b["f2"] == -1)) & (b["f1"] != 0) & (b["f2"] != 0))
        rows = rows.select(*names, open_.alias("_open"), (F.col("_inter") + F.col("_small") + covered).alias("_inter"))
        if longest * longest < options.limit or longest <= 1:
            break  # the boxes of this round were all small
        longest = -(-longest // options.side)
    inter = F.col("_inter")
    return rows.select(*KEYS, inter.alias("inter"), (F.col("area_p") + F.col("area_q") - inter).alias("uni"))


def _parts(b: Column, side: int) -> Column:
    """The non-empty parts of a side by side split."""
    cut = lambda lo, hi, k: b[lo] + F.floor(k * (b[hi] - b[lo]) / side).cast("bigint")
    steps = F.array(*(F.lit(k).cast("bigint") for k in range(side * side)))
    across, up = (lambda k: F.floor(k / side)), (lambda k: k % side)
    parts = F.transform(steps, lambda k: F.struct(cut("x0", "x1", across(k)).alias("x0"), cut("y0", "y1", up(k)).alias("y0"), cut("x0", "x1", across(k) + 1).alias("x1"), cut("y0", "y1", up(k) + 1).alias("y1")))
    return F.filter(parts, lambda c: (c["x1"] > c["x0"]) & (c["y1"] > c["y0"]))


def _position(edges: str, b: Column) -> Column:
    """-1 where an edge meets the open box, else 1 or 0 as its first pixel."""
    through = F.exists(edges, lambda e: (e["ax"] < b["x1"]) & (e["bx"] > b["x0"]) & (e["ay"] < b["y1"]) & (e["by"] > b["y0"]) & F.when(e["ax"] == e["bx"], e["ax"] > b["x0"]).otherwise(e["ay"] > b["y0"]))
    beyond = F.filter(edges, lambda e: (e["ax"] == e["bx"]) & (e["ax"] > b["x0"]) & (e["ay"] <= b["y0"]) & (b["y0"] < e["by"]))
    return F.when(through, -1).otherwise(F.size(beyond) % 2)


def _judged(b: Column) -> Column:
    return F.struct(*(b[c].alias(c) for c in ("x0", "y0", "x1", "y1")), _position("_p", b).alias("f1"), _position("_q", b).alias("f2"))


def _pixels(b: Column) -> Column:
    """Pixels of a box that lie in both rings, each by the even-odd test; a row's edges are looked up once."""
    zero = F.lit(0).cast("bigint")
    met = lambda edges, j: F.transform(F.filter(edges, lambda e: (e["ax"] == e["bx"]) & (e["ay"] <= j) & (j < e["by"])), lambda e: e["ax"])
    rows = F.transform(F.sequence(b["y0"], b["y1"] - 1), lambda j: F.struct(met("_p", j).alias("p"), met("_q", j).alias("q")))
    inside = lambda xs, i: F.size(F.filter(xs, lambda x: x > i)) % 2 == 1
    row = lambda r: F.size(F.filter(F.sequence(b["x0"], b["x1"] - 1), lambda i: inside(r["p"], i) & inside(r["q"], i)))
    return F.aggregate(rows, zero, lambda s, r: s + row(r))
