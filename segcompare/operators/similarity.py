"""Scores of two result sets: pairwise mean ratio, set level, missing objects, profiles and roll-ups."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry as g
from ..kernels import native, vector
from . import pairing


def pair_ratio(inter: Column, area_p: Column, area_q: Column) -> Column:
    """Intersection over union from areas alone; NULL where both are empty."""
    return F.try_divide(inter.cast("double"), area_p + area_q - inter)


def ratio_of(inter: str = "inter", uni: str = "uni") -> Column:
    return F.try_divide(F.col(inter).cast("double"), F.col(uni))


def mean_ratio(areas: DataFrame, by: tuple[str, ...] = ("image_id",), exact: bool = False) -> DataFrame:
    """Mean ratio over pairs that truly overlap; NULL for a group without such a pair (none is listed).

    exact: the average of ratios rounded to twelve decimals, the same in any order of summation.
    """
    hit = areas.filter("inter > 0")
    value = F.avg(F.round(F.col("inter").cast("decimal(20,0)") / F.col("uni").cast("decimal(20,0)"), 12).cast("decimal(18,12)")) if exact else F.avg(ratio_of())
    return hit.groupBy(*by).agg(F.count(F.lit(1)).alias("pairs"), value.alias("score"))


def partial_scores(areas: DataFrame, by: tuple[str, ...] = ("image_id",)) -> DataFrame:
    """(sum, count) of the ratios: mergeable parts of the mean."""
    return areas.filter("inter > 0").groupBy(*by).agg(F.sum(ratio_of()).alias("ratio_sum"), F.count(F.lit(1)).alias("pairs"))


def merged_scores(parts: DataFrame, by: tuple[str, ...] = ("image_id",)) -> DataFrame:
    return parts.groupBy(*by).agg(F.sum("pairs").alias("pairs"), (F.sum("ratio_sum") / F.sum("pairs")).alias("score"))


def row_spans(objects: DataFrame) -> DataFrame:
    """image_id, y, x0, x1: maximal runs of pixels of the union of all rings on each row."""
    edged = objects.select("image_id", g.vertical_edges(F.col("ring")).alias("e"), *(v.alias(k) for k, v in g.ring_mbr(F.col("ring")).items()))
    rows = edged.select("image_id", "e", F.explode(F.sequence("miny", F.col("maxy") - 1)).alias("y"))
    xs = F.array_sort(F.transform(F.filter("e", lambda s: (s["lo"] <= F.col("y")) & (F.col("y") < s["hi"])), lambda s: s["x"]))
    rows = rows.select("image_id", "y", xs.alias("xs"))
    spans = F.transform(F.sequence(F.lit(0), F.floor(F.size("xs") / 2).cast("int") - 1), lambda k: F.struct(F.get("xs", 2 * k).alias("x0"), F.get("xs", 2 * k + 1).alias("x1")))
    single = rows.filter(F.size("xs") > 0).select("image_id", "y", F.inline(spans))
    w = Window.partitionBy("image_id", "y").orderBy("x0", "x1")
    reach = F.max("x1").over(w.rowsBetween(Window.unboundedPreceding, -1))
    islands = single.withColumn("new", F.when(F.col("x0") <= reach, 0).otherwise(1)).withColumn("island", F.sum("new").over(w))
    return islands.groupBy("image_id", "y", "island").agg(F.min("x0").alias("x0"), F.max("x1").alias("x1")).drop("island")


def set_jaccard(p: DataFrame, q: DataFrame) -> DataFrame:
    """Set-level score per image from merged row spans: a sweep over span ends counts what one or both sets cover."""
    ends = None
    for side, objects in (("p", p), ("q", q)):
        spans = row_spans(objects)
        for column, step in (("x0", 1), ("x1", -1)):
            part = spans.select("image_id", "y", F.col(column).alias("x"), F.lit(step if side == "p" else 0).alias("dp"), F.lit(step if side == "q" else 0).alias("dq"))
            ends = part if ends is None else ends.unionByName(part)
    cuts = ends.groupBy("image_id", "y", "x").agg(F.sum("dp").alias("dp"), F.sum("dq").alias("dq"))
    w = Window.partitionBy("image_id", "y").orderBy("x")
    swept = cuts.select("image_id", F.sum("dp").over(w).alias("cp"), F.sum("dq").over(w).alias("cq"), (F.lead("x").over(w) - F.col("x")).alias("length")).filter("length > 0")
    total = lambda cond: F.coalesce(F.sum(F.when(cond, F.col("length"))), F.lit(0)).cast("bigint")
    in_p, in_q = F.col("cp") > 0, F.col("cq") > 0
    return _set_scores(swept.groupBy("image_id").agg(total(in_p).alias("px_p"), total(in_q).alias("px_q"), total(in_p & in_q).alias("px_both"), total(in_p | in_q).alias("px_any")))


def _set_scores(counts: DataFrame) -> DataFrame:
    return counts.select("image_id", "px_p", "px_q", "px_both", "px_any", F.round(F.try_divide(F.col("px_both"), F.col("px_any")), 6).alias("score"))


def _block_counts(side: int):
    """All rings that reach a square block of pixels -> how many of its pixels lie in P, in Q, in both, in any."""

    def run(key: tuple[pa.Scalar, ...], rows: pa.Table) -> pa.Table:
        left, low = key[1].as_py() * side, key[2].as_py() * side
        of = np.asarray(rows.column("of").to_numpy())
        rings = vector.Rings.of(rows.column("ring").combine_chunks())
        x0, y0, x1, y1 = np.maximum(rings.box[0], left), np.maximum(rings.box[1], low), np.minimum(rings.box[2], left + side), np.minimum(rings.box[3], low + side)
        size = (x1 - x0) * (y1 - y0)
        inside = np.zeros((2, side * side), bool)
        for part in np.split(np.arange(len(of)), np.flatnonzero(np.diff(np.cumsum(size) // 1_000_000)) + 1):
            base = np.cumsum(size[part]) - size[part]
            at = np.flatnonzero(rings.raster(part, x0[part], y0[part], x1[part], y1[part], base, int(size[part].sum())))
            k = np.searchsorted(base, at, "right") - 1
            cell, r = at - base[k], part[k]
            width = x1[r] - x0[r]
            inside[of[r], (y0[r] + cell // width - low) * side + x0[r] + cell % width - left] = True
        p, q = inside
        return pa.table({"image_id": pa.array([key[0].as_py()], pa.int32()), **{c: pa.array([int(v.sum())]) for c, v in (("px_p", p), ("px_q", q), ("px_both", p & q), ("px_any", p | q))}})

    return run


def set_jaccard_pixels(p: DataFrame, q: DataFrame, side: int = 256) -> DataFrame:
    """Set-level score per image from the pixels themselves: each block of pixels is marked ring by ring, where only rings move."""
    rings = p.select("image_id", "ring", F.lit(0).alias("of")).unionByName(q.select("image_id", "ring", F.lit(1).alias("of")))
    rings = rings.select("*", *(v.alias(k) for k, v in g.ring_mbr(F.col("ring")).items()))
    blocks = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / side), F.floor((F.col(hi) - 1) / side)))
    dealt = rings.withColumn("bx", blocks("minx", "maxx")).withColumn("by", blocks("miny", "maxy")).select("image_id", "bx", "by", "of", "ring")
    counts = dealt.groupBy("image_id", "bx", "by").applyInArrow(_block_counts(side), "image_id int, px_p long, px_q long, px_both long, px_any long")
    return _set_scores(counts.groupBy("image_id").agg(*(F.sum(c).alias(c) for c in ("px_p", "px_q", "px_both", "px_any"))))


def unmatched(areas: DataFrame, p: DataFrame, q: DataFrame) -> DataFrame:
    """image_id, side, obj_id of the objects that overlap nothing of the other set."""
    hit = areas.filter("inter > 0")
    sides = []
    for side, objects, key in (("P", p, "p_id"), ("Q", q, "q_id")):
        matched = hit.select("image_id", F.col(key).alias("obj_id")).distinct()
        sides.append(objects.select("image_id", "obj_id").join(matched, ["image_id", "obj_id"], "left_anti").select("image_id", F.lit(side).alias("side"), "obj_id"))
    return sides[0].unionByName(sides[1])


def missing_objects(areas: DataFrame, p: DataFrame, q: DataFrame) -> DataFrame:
    """Per image and side: objects, those with a partner, those without."""
    lost = unmatched(areas, p, q).groupBy("image_id", "side").agg(F.count(F.lit(1)).alias("missing"))
    totals = None
    for side, objects in (("P", p), ("Q", q)):
        part = objects.groupBy("image_id").agg(F.count(F.lit(1)).alias("total")).withColumn("side", F.lit(side))
        totals = part if totals is None else totals.unionByName(part)
    missing = F.coalesce("missing", F.lit(0).cast("bigint"))
    return totals.join(lost, ["image_id", "side"], "left").select("image_id", "side", "total", (F.col("total") - missing).alias("matched"), missing.alias("missing"))


def overlap_profile(areas: DataFrame) -> DataFrame:
    """Per image: sums of areas over overlapping pairs and the mean share of p that lies in q, and of q in p."""
    hit = areas.filter("inter > 0")
    return hit.groupBy("image_id").agg(F.sum("area_p").alias("sum_p"), F.sum("area_q").alias("sum_q"), F.sum("inter").alias("sum_inter"), F.round(F.avg(F.col("inter") / F.col("area_p")), 6).alias("share_p"), F.round(F.avg(F.col("inter") / F.col("area_q")), 6).alias("share_q"))


_RATIOS = "algo_a int, algo_b int, pairs long, ratio_sum double"


def _tile_ratios(tile: pa.Table) -> pa.Table:
    """All objects of a tile -> for each two result sets, overlapping pairs and the sum of their ratios."""
    tile = tile.sort_by("algo")
    algo = tile.column("algo").to_numpy()
    rings = vector.Rings.of(tile.column("ring").combine_chunks())
    x0, y0, x1, y1 = rings.box
    found: dict[tuple[int, int], list[float]] = {}
    step = max(1, 2_000_000 // len(algo))
    for lo in range(0, len(algo), step):
        some = slice(lo, lo + step)
        meet = (x0[some, None] <= x1) & (x0 <= x1[some, None]) & (y0[some, None] <= y1) & (y0 <= y1[some, None]) & (algo[some, None] < algo)
        a, b = np.nonzero(meet)
        a += lo
        inter = vector.edge_form_sums(rings, a, rings, b)
        hit = inter > 0
        a, b, inter = a[hit], b[hit], inter[hit]
        kinds, at = np.unique(np.stack([algo[a], algo[b]], 1), axis=0, return_inverse=True)
        at = at.reshape(-1)
        ratios = np.bincount(at, inter / (rings.area[a] + rings.area[b] - inter), len(kinds))
        for (i, j), n, r in zip(kinds.tolist(), np.bincount(at, minlength=len(kinds)).tolist(), ratios.tolist(), strict=True):
            had = found.setdefault((i, j), [0, 0.0])
            had[0], had[1] = had[0] + n, had[1] + r
    columns = list(zip(*((i, j, n, r) for (i, j), (n, r) in found.items()), strict=True)) or [[]] * 4
    return pa.table({c.split()[0]: pa.array(v, t) for c, v, t in zip(_RATIOS.split(", "), columns, (pa.int32(), pa.int32(), pa.int64(), pa.float64()), strict=True)})


def cross_matrix(objects: DataFrame) -> DataFrame:
    """Scores of all pairs of result sets (column algo): each tile's objects meet one another in one Arrow call."""
    own = objects.select("image_id", "tile_id", F.col("algo").cast("int").alias("algo"), "ring")
    parts = own.groupBy("image_id", "tile_id").applyInArrow(_tile_ratios, _RATIOS)
    return parts.groupBy("algo_a", "algo_b").agg(F.sum("pairs").alias("pairs"), F.round(F.sum("ratio_sum") / F.sum("pairs"), 6).alias("score"))


def matrix_table(matrix: DataFrame, algos: list[int]) -> DataFrame:
    """The matrix with one column per second result set."""
    return matrix.groupBy("algo_a").pivot("algo_b", algos).agg(F.first("score"))


def score_cube(areas: DataFrame, dims: DataFrame) -> DataFrame:
    """Roll-up over region and nation of the objects (dims: obj_id, region, nation); NULL is the level above."""
    hit = areas.filter("inter > 0").join(dims, F.col("p_id") == F.col("obj_id"))
    rolled = hit.rollup("region", "nation").agg(F.grouping_id().cast("int").alias("level"), F.count(F.lit(1)).alias("pairs"), F.round(F.avg(ratio_of()), 6).alias("score"))
    return rolled.select("region", "nation", "level", "pairs", "score")


def best_match(areas: DataFrame) -> DataFrame:
    """The best partner of each object of P; ties go to the smaller id."""
    hit = areas.filter("inter > 0")
    w = Window.partitionBy("image_id", "p_id").orderBy(F.desc(F.col("inter").cast("double") / F.col("uni")), "q_id")
    return hit.withColumn("rk", F.row_number().over(w)).filter("rk = 1").select("image_id", "p_id", "q_id", F.round(ratio_of(), 6).alias("ratio"))


def ratio_histogram(areas: DataFrame) -> DataFrame:
    return areas.filter("inter > 0").groupBy(F.expr("cast(10 * inter div uni as int)").alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def worst_pairs(areas: DataFrame, k: int = 3) -> DataFrame:
    """The k overlapping pairs of lowest ratio in each image."""
    w = Window.partitionBy("image_id").orderBy(F.col("inter").cast("double") / F.col("uni"), "p_id", "q_id")
    return areas.filter("inter > 0").withColumn("rk", F.row_number().over(w)).filter(F.col("rk") <= k).select("image_id", "rk", "p_id", "q_id", "inter", "uni")


def agreement(reference: DataFrame, **others: DataFrame) -> DataFrame:
    """Per method: pairs, and pairs whose areas differ from the reference's or are missing.

    All results meet in one exchange by pair, so each is computed once. Rows of equal ids each meet all of the other
    side's, as in a join; rows of null ids meet none.
    """
    counted = lambda k: F.col(f"n{k}")
    frames = [reference, *others.values()]
    tagged = None
    for at, df in enumerate(frames):
        rows = df.select(*native.KEYS, "inter", "uni", F.lit(at).alias("of"))
        tagged = rows if tagged is None else tagged.unionByName(rows)
    count = lambda k: F.count_if(F.col("of") == k).alias(f"n{k}")
    # rows with the same areas first, then all of a pair: the exchange by ids serves both
    equal = tagged.repartition(*native.KEYS).groupBy(*native.KEYS, "inter", "uni").agg(*(count(k) for k in range(len(frames))))
    met = [(F.sum(counted(k)).alias(f"n{k}"), F.sum(counted(0) * counted(k)).alias(f"same{k}")) for k in range(1, len(frames))]
    by_pair = equal.groupBy(*native.KEYS).agg(F.sum("n0").alias("n0"), *(c for both in met for c in both))
    named = F.lit(True)
    for c in native.KEYS:
        named = named & F.col(c).isNotNull()
    out = []
    for k, name in enumerate(others, 1):
        joined = named & (counted(0) > 0) & (counted(k) > 0)
        pairs = F.when(joined, counted(0) * counted(k)).otherwise(counted(0) + counted(k))
        out += [F.coalesce(F.sum(pairs), F.lit(0)).cast("long").alias(f"p{k}"), F.coalesce(F.sum(pairs - F.when(joined, F.col(f"same{k}")).otherwise(0)), F.lit(0)).cast("long").alias(f"m{k}")]
    rows = [F.struct(F.lit(name).alias("method"), F.col(f"p{k}").alias("pairs"), F.col(f"m{k}").alias("mismatches")) for k, name in enumerate(others, 1)]
    return by_pair.agg(*out).select(F.inline(F.array(*rows)))
