"""Segmentations derived from the given tables with integer arithmetic only.

cells: two segmentations of 18 images from orders; satellites: many small rectangles against the cells;
columns: skylines with many vertices from documents; raw_text: lines for the parser; tile_arrivals: files of
tiles reaching the pipeline; triangles: polygons with real coordinates.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import geometry
from ..schema import RING

IMAGES = 18
#: Outlines of the eight shapes on a grid of 0..6, counter-clockwise.
SHAPES = [
    [(0, 0), (6, 0), (6, 6), (0, 6)],
    [(0, 0), (6, 0), (6, 3), (3, 3), (3, 6), (0, 6)],
    [(0, 0), (6, 0), (6, 6), (4, 6), (4, 2), (2, 2), (2, 6), (0, 6)],
    [(0, 0), (6, 0), (6, 2), (2, 2), (2, 4), (6, 4), (6, 6), (0, 6)],
    [(2, 0), (4, 0), (4, 2), (6, 2), (6, 4), (4, 4), (4, 6), (2, 6), (2, 4), (0, 4), (0, 2), (2, 2)],
    [(0, 0), (4, 0), (4, 2), (6, 2), (6, 6), (2, 6), (2, 4), (0, 4)],
    [(0, 0), (6, 0), (6, 5), (5, 5), (5, 2), (4, 2), (4, 6), (2, 6), (2, 3), (1, 3), (1, 6), (0, 6)],
    [(1, 0), (5, 0), (5, 1), (6, 1), (6, 5), (5, 5), (5, 6), (1, 6), (1, 5), (0, 5), (0, 1), (1, 1)],
]


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _shape_array() -> Column:
    vertex = lambda x, y: F.struct(F.lit(x).cast("bigint").alias("x"), F.lit(y).cast("bigint").alias("y"))
    return F.array(*(F.array(*(vertex(x, y) for x, y in shape)) for shape in SHAPES))


def _placed(orders: DataFrame) -> DataFrame:
    """k, image_id, tile_id, x0, y0, shape, su, sv of each order's object."""
    k, c, t = F.col("o_orderkey"), F.col("o_custkey"), F.floor("o_totalprice").cast("bigint")
    rows = orders.select(k.alias("k"), c.alias("c"), t.alias("t"), (k % 324).alias("u"))
    rows = rows.withColumn("image_id", F.floor(F.sqrt("u")).cast("int"))
    rows = rows.withColumn("w", F.expr("k div 324 * (2 * image_id + 1) + (u - image_id * image_id)")).withColumn("tile_id", F.expr("w div 64"))
    return rows.select(
        "k", "image_id", "tile_id", "w",
        F.expr("(tile_id % 8) * 208 + (w % 8) * 26 + c % 9").alias("x0"),
        F.expr("(tile_id div 8) * 208 + ((w % 64) div 8) * 26 + t % 9").alias("y0"),
        F.expr("cast(c % 8 as int)").alias("shape"), F.expr("1 + (c div 8) % 4").alias("su"), F.expr("1 + t % 4").alias("sv"),
    )


def _ringed(placed: DataFrame, algo: str, obj_id: Column) -> DataFrame:
    ring = F.transform(F.element_at(_shape_array(), F.col("shape") + 1), lambda v: F.struct((F.col("x0") + F.col("su") * v["x"]).alias("x"), (F.col("y0") + F.col("sv") * v["y"]).alias("y")))
    rows = placed.select("image_id", "tile_id", F.lit(algo).alias("algo"), obj_id.cast("bigint").alias("obj_id"), "shape", "su", "sv", "x0", "y0")
    # filters on the ring would else make it anew for each of its vertices
    return geometry.once(rows, ring=ring).drop("shape", "su", "sv", "x0", "y0")


def places(spark: SparkSession, sf_dir: str) -> DataFrame:
    """image_id, tile_id, cell: where the orders' objects lie."""
    return _placed(load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_totalprice")).select("image_id", "tile_id", F.expr("w % 64").alias("cell"))


def cells(spark: SparkSession, sf_dir: str, side: str) -> DataFrame:
    """Result set P, or Q: the same objects with shifted borders, some reshaped, regrown, dropped or split."""
    placed = _placed(load(spark, sf_dir, "orders"))
    if side == "P":
        return _ringed(placed, "P", F.col("k") * 4)
    changed = placed.filter("k % 13 <> 0").select(
        "k", "image_id", "tile_id", F.expr("x0 + (7 * k) % 5 - 2").alias("x0"), F.expr("y0 + (3 * k) % 5 - 2").alias("y0"),
        F.expr("if(k % 10 = 3, (shape + 1) % 8, shape)").alias("shape"), F.expr("if(k % 9 = 4, 1 + su % 4, su)").alias("su"), "sv",
    )
    one = F.lit(1).cast("bigint")
    extra = placed.filter("k % 17 = 0").select("k", "image_id", "tile_id", (F.col("x0") + 13).alias("x0"), (F.col("y0") + 11).alias("y0"), F.lit(7).alias("shape"), one.alias("su"), one.alias("sv"))
    return _ringed(changed, "Q", F.col("k") * 4).unionByName(_ringed(extra, "Q", F.col("k") * 4 + 1))


def jittered(spark: SparkSession, sf_dir: str, algo: int) -> DataFrame:
    """The objects of P with borders shifted by `algo` times the jitter: results of other parameters."""
    placed = _placed(load(spark, sf_dir, "orders"))
    moved = placed.withColumns({"x0": F.expr(f"x0 + {algo} * ((7 * k) % 5 - 2)"), "y0": F.expr(f"y0 + {algo} * ((3 * k) % 5 - 2)")})
    return _ringed(moved, str(algo), F.col("k") * 4)


def with_boxes(objects: DataFrame) -> DataFrame:
    """objects with their bounding boxes as flat columns, which Parquet statistics can use."""
    return objects.withColumns(geometry.ring_mbr(F.col("ring")))


def scaled(objects: DataFrame, factor: int) -> DataFrame:
    return objects.withColumn("ring", geometry.scale_ring(F.col("ring"), factor))


def rectangle(minx: Column, miny: Column, maxx: Column, maxy: Column) -> Column:
    vertex = lambda x, y: F.struct(x.cast("bigint").alias("x"), y.cast("bigint").alias("y"))
    return F.array(vertex(minx, miny), vertex(maxx, miny), vertex(maxx, maxy), vertex(minx, maxy))


def satellites(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One small rectangle per order line next to the order's object."""
    lines = load(spark, sf_dir, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.sum("l_partkey").alias("sp"), F.sum("l_suppkey").alias("ss"), F.sum(F.col("l_quantity").cast("bigint")).alias("sq"))
    placed = _placed(load(spark, sf_dir, "orders"))
    rows = lines.join(placed, lines["l_orderkey"] == placed["k"])
    minx, miny = F.col("x0") + F.col("sp") % 18, F.col("y0") + F.col("ss") % 18
    ring = rectangle(minx, miny, minx + 2 + F.col("sq") % 5, miny + 2 + F.col("sp") % 5)
    return rows.select("image_id", "tile_id", F.lit("S").alias("algo"), (F.col("k") * 8 + F.col("l_linenumber")).cast("bigint").alias("obj_id"), ring.alias("ring"))


def vessels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One large C-shaped ring around each tile of P."""
    tiles = cells(spark, sf_dir, "P").select("image_id", "tile_id").distinct()
    x, y = F.expr("(tile_id % 8) * 208"), F.expr("(tile_id div 8) * 208")
    # The outline around a tile of side 208, open to the right.
    outline = [(0, 0), (208, 0), (208, 40), (40, 40), (40, 168), (208, 168), (208, 208), (0, 208)]
    ring = F.array(*(F.struct((x + a).cast("bigint").alias("x"), (y + b).cast("bigint").alias("y")) for a, b in outline))
    return tiles.select("image_id", "tile_id", F.lit("V").alias("algo"), (F.col("image_id") * 1000000 + F.col("tile_id")).cast("bigint").alias("obj_id"), ring.alias("ring"))


def column_heights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """obj_id, width, heights: the lengths of a document's words as skylines of 128 words each; obj_id is 65,536 * doc_id + part."""
    docs = load(spark, sf_dir, "documents")
    words = F.filter(F.split("text", r"[ \t\n\r\x0B\f]+"), lambda w: w != "")
    every = docs.select("doc_id", (1 + F.col("n_chars") % 3).alias("width"), F.transform(words, lambda w: (1 + F.length(w) % 16).cast("bigint")).alias("heights")).filter(F.size("heights") > 0)
    parts = every.select("doc_id", "width", "heights", F.explode(F.sequence(F.lit(0), F.floor((F.size("heights") - 1) / 128).cast("int"))).alias("part"))
    return parts.select((F.col("doc_id") * 65536 + F.col("part")).alias("obj_id"), "width", F.slice("heights", F.col("part") * 128 + 1, F.lit(128)).alias("heights"))


def skyline_rings(width: np.ndarray, heights: np.ndarray, counts: np.ndarray, shift: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(x and y of the rings' vertices, vertices of each): outlines of `counts` columns each, counter-clockwise, without collinear vertices."""
    n = 2 * counts + 2
    end = np.cumsum(n)
    owner = np.repeat(np.arange(len(n)), n)
    k = np.arange(len(owner)) - (end - n)[owner]
    # the base, left and right, then the right and left end of each top, from the last column to the first
    column = counts[owner] - 1 - (k - 2) // 2
    at = np.where(k < 2, np.where(k == 0, 0, counts[owner]), column + 1 - k % 2)
    x = width[owner] * (shift + at)
    y = np.zeros(len(owner), np.int64)
    tops = k >= 2
    y[tops] = heights[(np.cumsum(counts) - counts)[owner[tops]] + column[tops]]
    first, last = end - n, end - 1
    before, after = np.arange(len(owner)) - 1, np.arange(len(owner)) + 1
    before[first], after[last] = last, first
    corner = ~(((x[before] == x) & (x[after] == x)) | ((y[before] == y) & (y[after] == y)))
    x, y, owner = x[corner], y[corner], owner[corner]
    n = np.bincount(owner, minlength=len(n))
    end = np.cumsum(n)
    after = np.arange(len(owner)) + 1
    after[(end - 1)[n > 0]] = (end - n)[n > 0]
    turned = np.zeros(len(n), np.int64)
    np.add.at(turned, owner, x * y[after] - x[after] * y)
    k = np.arange(len(owner)) - (end - n)[owner]
    order = (end - n)[owner] + np.where(turned[owner] < 0, n[owner] - 1 - k, k)
    return x[order], y[order], n


def columns(spark: SparkSession, sf_dir: str, shift: int = 0) -> DataFrame:
    """Skyline polygons, moved to the right by `shift` columns; collinear vertices are removed. Made in Arrow batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, width, heights = batch.columns
            counts = np.diff(np.asarray(heights.offsets, np.int64))
            known = np.asarray(width.is_valid())  # columns without a width have no vertices
            flat = np.asarray(heights.flatten(), np.int64)[np.repeat(known, counts)]
            x, y, n = skyline_rings(np.asarray(width.drop_null(), np.int64), flat, counts[known], shift)
            size = np.zeros(len(batch), np.int64)
            size[known] = n
            rings = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(size)], pa.int32()), pa.StructArray.from_arrays([pa.array(x, pa.int64()), pa.array(y, pa.int64())], names=["x", "y"]))
            yield pa.RecordBatch.from_arrays([ids, rings], names=["obj_id", "ring"])

    rows = column_heights(spark, sf_dir).select("obj_id", F.col("width").cast("long"), "heights").mapInArrow(run, f"obj_id long, ring {RING}")
    return rows.select(F.lit(0).alias("image_id"), F.col("obj_id").alias("tile_id"), F.lit(f"C{shift}").alias("algo"), "obj_id", "ring")


def raw_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines for the parser: rings of P as text, some of them faulty or in need of repair, and lines that are no rings."""
    p = cells(spark, sf_dir, "P").withColumn("k", F.expr("obj_id div 4"))
    ring, n = F.col("ring"), F.size("ring")
    closed = F.concat(ring, F.slice(ring, 1, 1))
    doubled = F.concat(F.slice(ring, 1, 1), ring)
    shape = F.when(F.col("k") % 50 == 4, F.reverse(ring)).when(F.col("k") % 50 == 5, closed).when(F.col("k") % 50 == 3, doubled).when(F.col("k") % 50 == 2, F.slice(ring, 1, 3)).when(F.col("k") % 50 == 1, F.concat(F.slice(ring, F.lit(1), n - 1), F.array(F.struct((F.element_at(ring, -1)["x"] + 1).alias("x"), (F.element_at(ring, -1)["y"] + 1).alias("y")))))
    coords = F.transform(F.coalesce(shape, ring), lambda v: F.concat_ws(" ", v["x"].cast("string"), v["y"].cast("string")))
    line = F.concat_ws(" ", F.col("obj_id").cast("string"), F.array_join(coords, " "))
    text = F.when(F.col("k") % 50 == 0, F.concat(line, F.lit(".5"))).otherwise(line)
    rings = p.select("image_id", "algo", "tile_id", F.col("k").alias("line_no"), text.alias("text"))
    junk = load(spark, sf_dir, "documents").select(F.expr("cast(doc_id % 18 as int)").alias("image_id"), F.lit("P").alias("algo"), F.lit(0).cast("bigint").alias("tile_id"), (-1 - F.col("doc_id")).alias("line_no"), "text")
    return rings.unionByName(junk)


def tile_arrivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """event_id, side, image_id, tile_id, bytes, event_time, arrival."""
    e = load(spark, sf_dir, "events")
    return arrivals_from(e)


def arrivals_from(events: DataFrame) -> DataFrame:
    """The same from any frame with the events' columns, streaming ones included."""
    return events.select(
        "event_id", F.expr("if(event_id % 2 = 0, 'P', 'Q')").alias("side"), F.expr("cast((event_id div 2) % 18 as int)").alias("image_id"), F.expr("(event_id div 36) % 64").alias("tile_id"),
        F.round(F.col("value") * 1000).cast("bigint").alias("bytes"), F.col("ts").alias("event_time"), F.expr("ts + make_dt_interval(0, 0, cast(event_id * 37 % 50 as int), 0)").alias("arrival"),
    )


def triangles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, label, xs, ys: three vertices with real coordinates."""
    e = load(spark, sf_dir, "embeddings")
    at = lambda k: F.col("embedding")[k].cast("double")
    return e.select("vec_id", "label", F.array(at(0), at(2), at(4)).alias("xs"), F.array(at(1), at(3), at(5)).alias("ys"))
