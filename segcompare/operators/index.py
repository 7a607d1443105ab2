"""Hilbert order, packed box trees and the search of two trees against each other."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..sources.fixtures import with_boxes
from .pairing import mbr_overlaps

BOX = ("minx", "miny", "maxx", "maxy")


def hilbert_key(x: Column, y: Column, order: int = 16) -> Column:
    """Place of (x, y) on the Hilbert curve over a square of side 2 ** order; nested expressions, no UDF.

    The bit loop is a fold over the bits, from the highest, of (key, x, y).
    """
    start = F.struct(F.lit(0).cast("bigint").alias("d"), x.cast("bigint").alias("x"), y.cast("bigint").alias("y"))
    bits = F.transform(F.sequence(F.lit(order - 1), F.lit(0), F.lit(-1)), lambda b: F.call_function("shiftleft", F.lit(1).cast("bigint"), b))

    def step(a: Column, s: Column) -> Column:
        rx = (a["x"].bitwiseAND(s) > 0).cast("bigint")
        ry = (a["y"].bitwiseAND(s) > 0).cast("bigint")
        d = a["d"] + s * s * (3 * rx).bitwiseXOR(ry)
        turned = (ry == 0) & (rx == 1)
        fx, fy = F.when(turned, s - 1 - a["x"].bitwiseAND(s - 1)).otherwise(a["x"].bitwiseAND(s - 1)), F.when(turned, s - 1 - a["y"].bitwiseAND(s - 1)).otherwise(a["y"].bitwiseAND(s - 1))
        return F.struct(d.alias("d"), F.when(ry == 0, fy).otherwise(fx).alias("x"), F.when(ry == 0, fx).otherwise(fy).alias("y"))

    return F.aggregate(bits, start, step, lambda a: a["d"])


def hilbert_sorted(objects: DataFrame, order: int = 16) -> DataFrame:
    """objects with boxes and the key of the box centre."""
    boxed = with_boxes(objects)
    return boxed.withColumn("hilbert", hilbert_key(F.expr("(minx + maxx) div 2 + 4096"), F.expr("(miny + maxy) div 2 + 4096"), order))


def leaf_entries(objects: DataFrame) -> DataFrame:
    """Level 0: each object of a tile with its rank in Hilbert order."""
    w = Window.partitionBy("image_id", "tile_id").orderBy("hilbert", "obj_id")
    return hilbert_sorted(objects).withColumn("node", (F.row_number().over(w) - 1).cast("bigint")).select("image_id", "tile_id", "node", "obj_id", "ring", *BOX)


def build_tree(objects: DataFrame, fanout: int = 16, levels: int = 3) -> list[DataFrame]:
    """[leaves, level 1, ...]: node k of a level covers nodes k * fanout ... of the level below, box and all.

    `levels` bounds the height above the leaves; a tile of n objects needs the logarithm of n to the fan-out.
    """
    tree = [leaf_entries(objects)]
    for _ in range(levels):
        below = tree[-1]
        tree.append(below.groupBy("image_id", "tile_id", F.expr(f"node div {fanout}").alias("node")).agg(F.min("minx").alias("minx"), F.min("miny").alias("miny"), F.max("maxx").alias("maxx"), F.max("maxy").alias("maxy"), F.count(F.lit(1)).alias("children")))
    return tree


def tree_join(tree_p: list[DataFrame], tree_q: list[DataFrame], fanout: int = 16, closed: bool = True) -> DataFrame:
    """Both trees searched from the top, level by level: only the children of node pairs whose boxes meet are joined."""

    def level(df: DataFrame, s: str) -> DataFrame:
        more = [F.col("obj_id").alias(f"{s}_id"), F.col("ring").alias(f"ring_{s}")] if "obj_id" in df.columns else []
        return df.select("image_id", "tile_id", F.col("node").alias(f"{s}_node"), F.expr(f"node div {fanout}").alias(f"{s}_up"), *(F.col(c).alias(f"{s}_{c}") for c in BOX), *more)

    top_p, top_q = level(tree_p[-1], "p"), level(tree_q[-1], "q")
    alive = top_p.join(top_q, ["image_id", "tile_id"]).filter(mbr_overlaps(closed)).select("image_id", "tile_id", "p_node", "q_node")
    for k in range(len(tree_p) - 2, -1, -1):
        up = alive.select("image_id", "tile_id", F.col("p_node").alias("p_up"), F.col("q_node").alias("q_up"))
        down = up.join(level(tree_p[k], "p"), ["image_id", "tile_id", "p_up"]).join(level(tree_q[k], "q"), ["image_id", "tile_id", "q_up"]).filter(mbr_overlaps(closed))
        alive = down if k == 0 else down.select("image_id", "tile_id", "p_node", "q_node")
    return alive.drop("p_up", "q_up", "p_node", "q_node")


def tree_levels(tree: list[DataFrame]) -> DataFrame:
    """level, nodes."""
    out = None
    for k, df in enumerate(tree):
        part = df.agg(F.lit(k).alias("level"), F.count(F.lit(1)).alias("nodes"))
        out = part if out is None else out.unionByName(part)
    return out
