"""Batch schemes of the comparison: staged, several streams, pipelined, database style; packing of small tasks."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import geometry as g
from ..kernels import native, vector
from ..operators import pairing, similarity
from ..sources import parse
from ..storage import materialised


def pixel_cost() -> Column:
    """Pixels of a pair's joint box."""
    side = lambda lo, hi: F.greatest(f"p_{hi}", f"q_{hi}") - F.least(f"p_{lo}", f"q_{lo}")
    return side("minx", "maxx") * side("miny", "maxy")


def tasks(p: DataFrame, q: DataFrame) -> DataFrame:
    """One row per tile with what its work costs: objects and vertices of both sets, pairs, pixels of the pairs' boxes."""
    both = p.select("image_id", "tile_id", "ring").unionByName(q.select("image_id", "tile_id", "ring"))
    sizes = both.groupBy("image_id", "tile_id").agg(F.count(F.lit(1)).alias("objects"), F.sum(F.size("ring")).cast("bigint").alias("vertices"))
    work = pairing.candidate_pairs(p, q).groupBy("image_id", "tile_id").agg(F.count(F.lit(1)).alias("pairs"), F.sum(pixel_cost()).cast("bigint").alias("pixels"))
    zero = F.lit(0).cast("bigint")
    return sizes.join(work, ["image_id", "tile_id"], "left").select("image_id", "tile_id", "objects", "vertices", F.coalesce("pairs", zero).alias("pairs"), F.coalesce("pixels", zero).alias("pixels"))


def pack_batches(task_rows: DataFrame, max_cost: int, cost: str = "pixels") -> DataFrame:
    """Neighbouring small tasks of an image share a batch: the running cost before a task, in steps of max_cost."""
    before = F.sum(cost).over(Window.partitionBy("image_id").orderBy("tile_id").rowsBetween(Window.unboundedPreceding, -1))
    batch = F.floor(F.coalesce(before, F.lit(0)) / max_cost).cast("bigint")
    return task_rows.select("image_id", "tile_id", cost, (F.col("image_id") * F.lit(1_000_000).cast("bigint") + batch).alias("batch_id"))


def _rounded(scores: DataFrame) -> DataFrame:
    return scores.select("image_id", "pairs", F.round("score", 6).alias("score"))


def aggregated(pairs: DataFrame, options: vector.Options = vector.Options()) -> DataFrame:
    """The aggregation stage of the schemes: the adaptive kernel on each pair."""
    return native.areas_only(vector.hybrid_areas(pairs, options))


def objects_of(rows: DataFrame) -> DataFrame:
    """Objects, parsed where the rows are lines of text."""
    return parse.parse_polygons(rows)[0] if "text" in rows.columns else rows


def run_staged(p: DataFrame, q: DataFrame, streams: int = 1) -> DataFrame:
    """Stages parse (of lines of text), index, pair, aggregate; each one's result is stored before the next begins.

    Several streams work on their own images side by side.
    """

    def one(k: int) -> DataFrame:
        own = lambda df: df.filter(F.col("image_id") % streams == k)
        parsed = (materialised(objects_of(own(df)), "parsed") if "text" in df.columns else own(df) for df in (p, q))
        a, b = (materialised(pairing.with_boxes(df), "boxed") for df in parsed)
        pairs = materialised(pairing.candidate_pairs(a, b), "pairs")
        areas = materialised(aggregated(pairs), "areas")
        return materialised(similarity.partial_scores(areas), "scores")

    with ThreadPoolExecutor(streams) as pool:
        parts = list(pool.map(one, range(streams)))
    every = parts[0]
    for part in parts[1:]:
        every = every.unionByName(part)
    return _rounded(similarity.merged_scores(every))


def run_pipelined(p: DataFrame, q: DataFrame) -> DataFrame:
    """One lazy plan from objects or lines of text: stages fuse into tasks, and only the tile join and the score move rows."""
    return _rounded(similarity.mean_ratio(aggregated(pairing.candidate_pairs(objects_of(p), objects_of(q)))))


def run_database_style(p: DataFrame, q: DataFrame, chunks: int = 16) -> DataFrame:
    """Full overlays over even chunks of P, each a query of its own; partial sums are merged."""
    numbered = p.withColumn("chunk", F.pmod(F.xxhash64("image_id", "obj_id"), F.lit(chunks)))

    def one(k: int) -> DataFrame:
        pairs = pairing.candidate_pairs(numbered.filter(F.col("chunk") == k).drop("chunk"), q)
        return materialised(similarity.partial_scores(vector.overlay_areas(pairs)), "chunk")

    with ThreadPoolExecutor(min(chunks, 16)) as pool:
        parts = list(pool.map(one, range(chunks)))
    every = parts[0]
    for part in parts[1:]:
        every = every.unionByName(part)
    return _rounded(similarity.merged_scores(every))


def route_lane(pairs: DataFrame, budget: int) -> DataFrame:
    """pairs with a lane: cheap ones native, those whose joint box has more than `budget` pixels vector."""
    return pairs.withColumn("lane", F.when(pixel_cost() <= budget, "native").otherwise("vector"))


def routed_areas(pairs: DataFrame, budget: int = 400, options: vector.Options = vector.Options()) -> DataFrame:
    routed = route_lane(pairs, budget)
    low = native.areas_only(native.edge_form_areas(routed.filter("lane = 'native'")))
    return low.unionByName(native.areas_only(vector.hybrid_areas(routed.filter("lane = 'vector'"), options)))


def plain_query(p: DataFrame, q: DataFrame) -> DataFrame:
    """The unrewritten comparison: exact intersects predicate in the join, union overlaid directly."""
    pairs = pairing.candidate_pairs(p, q).filter(g.poly_intersects(F.col("ring_p"), F.col("ring_q")))
    return _rounded(similarity.mean_ratio(vector.overlay_areas(pairs, union="direct")))


def rewritten_query(p: DataFrame, q: DataFrame) -> DataFrame:
    """Box test and positive area instead of the predicate, one overlay a pair, and the union from the areas."""
    return _rounded(similarity.mean_ratio(vector.overlay_areas(pairing.candidate_pairs(p, q))))
