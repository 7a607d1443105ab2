"""Candidate pairs: objects of two result sets whose bounding boxes meet."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.geometry import once, ring_area
from ..sources.fixtures import with_boxes


def mbr_overlaps(closed: bool = True, p: str = "p_", q: str = "q_") -> Column:
    """Box test on prefixed columns; closed keeps boxes that only touch."""
    c = F.col
    if closed:
        return (c(f"{p}minx") <= c(f"{q}maxx")) & (c(f"{q}minx") <= c(f"{p}maxx")) & (c(f"{p}miny") <= c(f"{q}maxy")) & (c(f"{q}miny") <= c(f"{p}maxy"))
    return (c(f"{p}minx") < c(f"{q}maxx")) & (c(f"{q}minx") < c(f"{p}maxx")) & (c(f"{p}miny") < c(f"{q}maxy")) & (c(f"{q}miny") < c(f"{p}maxy"))


def _side(objects: DataFrame, prefix: str) -> DataFrame:
    boxed = objects if "minx" in objects.columns else with_boxes(objects)
    return boxed.select("image_id", F.col("tile_id").alias(f"{prefix}tile"), F.col("obj_id").alias(f"{prefix}id"), F.col("ring").alias(f"ring_{prefix[0]}"), *(F.col(c).alias(f"{prefix}{c}") for c in ("minx", "miny", "maxx", "maxy")))


def candidate_pairs(p: DataFrame, q: DataFrame, scope: str = "tile", closed: bool = True, cell: int = 64, hint: str | None = None) -> DataFrame:
    """Pairs with both rings and boxes.

    scope "tile": objects of the same tile, an equi-join on image and tile with the box test as residual.
    scope "image": objects anywhere in the image, an equi-join on the grid cells their boxes cover; a pair is kept
    only in the cell of the lower left corner of the boxes' intersection, so none comes twice.
    """
    left, right = _side(p, "p_"), _side(q, "q_")
    if hint:
        left = left.hint(hint)
    if scope == "tile":
        pairs = left.withColumnRenamed("p_tile", "tile_id").join(right.withColumnRenamed("q_tile", "tile_id"), ["image_id", "tile_id"])
        return pairs.filter(mbr_overlaps(closed))
    if scope != "image":
        raise ValueError(f"no scope {scope}")

    def covered(side: DataFrame, prefix: str) -> DataFrame:
        cells = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(prefix + lo) / cell), F.floor(F.col(prefix + hi) / cell)))
        return side.withColumn("cx", cells("minx", "maxx")).withColumn("cy", cells("miny", "maxy"))

    pairs = covered(left, "p_").join(covered(right, "q_"), ["image_id", "cx", "cy"]).filter(mbr_overlaps(closed))
    corner_x, corner_y = F.greatest("p_minx", "q_minx"), F.greatest("p_miny", "q_miny")
    return pairs.filter((F.floor(corner_x / cell) == F.col("cx")) & (F.floor(corner_y / cell) == F.col("cy"))).drop("cx", "cy")


def nested_pairs(p: DataFrame, q: DataFrame, closed: bool = True, band: int = 64) -> DataFrame:
    """Every box of an image against every other one that shares a band of rows with it: the check of the joins above.

    Boxes without a common band cannot meet; a pair is kept in the band of the lower edge of the boxes' intersection.
    """

    def banded(side: DataFrame, prefix: str) -> DataFrame:
        return side.withColumn("band", F.explode(F.sequence(F.floor(F.col(f"{prefix}miny") / band), F.floor(F.col(f"{prefix}maxy") / band))))

    pairs = banded(_side(p, "p_"), "p_").join(banded(_side(q, "q_"), "q_"), ["image_id", "band"]).filter(mbr_overlaps(closed))
    return pairs.filter(F.floor(F.greatest("p_miny", "q_miny") / band) == F.col("band")).drop("band")


def ids(pairs: DataFrame, with_tile: bool = True) -> DataFrame:
    return pairs.select("image_id", *(["tile_id"] if with_tile else []), "p_id", "q_id")


def pairing_stats(pairs: DataFrame, areas: DataFrame) -> DataFrame:
    """Per image: candidates, pairs that truly overlap, share of false candidates."""
    c = pairs.groupBy("image_id").agg(F.count(F.lit(1)).alias("candidates"))
    t = areas.filter("inter > 0").groupBy("image_id").agg(F.count(F.lit(1)).alias("positive"))
    joined = c.join(t, "image_id", "left").withColumn("positive", F.coalesce("positive", F.lit(0).cast("bigint")))
    return joined.select("image_id", "candidates", "positive", F.round(1 - F.col("positive") / F.col("candidates"), 6).alias("false_share"))


def size_filter(objects: DataFrame, least: int, most: int | None = None) -> DataFrame:
    """Objects whose area lies in [least, most], with the area: specks and merged blobs are left out before pairing."""
    sized = once(objects, area=ring_area(F.col("ring"))).filter(F.col("area") >= least)
    return sized if most is None else sized.filter(F.col("area") <= most)


def roi_filter(objects: DataFrame, minx: int, miny: int, maxx: int, maxy: int) -> DataFrame:
    """Objects whose boxes meet a region; on a stored layout the comparisons reach the Parquet statistics."""
    return objects.filter((F.col("minx") <= maxx) & (F.col("maxx") >= minx) & (F.col("miny") <= maxy) & (F.col("maxy") >= miny))
