"""The registry of driver queries of the comparison engine."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import geometry as g
from .kernels import native, relational, vector
from .operators import general, index, pairing, relate, similarity
from .plans import metrics, pipeline, rebalance
from .sources import fixtures as fx
from .sources import io, parse
from .storage import materialised
from .streaming import arrivals, backlog

Query = Callable[[SparkSession, str], DataFrame]
Options = vector.Options
REGISTRY: dict[str, Query] = {}


def query(f: Query) -> Query:
    REGISTRY[f.__name__] = f
    return f


def _sides(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return fx.cells(s, d, "P"), fx.cells(s, d, "Q")


def _pairs(s: SparkSession, d: str, **options) -> DataFrame:
    return pairing.candidate_pairs(*_sides(s, d), **options)


def _areas(s: SparkSession, d: str) -> DataFrame:
    return native.edge_form_areas(_pairs(s, d))


def _described(objects: DataFrame) -> DataFrame:
    return fx.with_boxes(objects).select("image_id", "tile_id", "obj_id", F.size("ring").alias("n_vertices"), *index.BOX, g.ring_area(F.col("ring")).alias("area"))


# fixtures


@query
def fx_objects_p(s, d):
    return _described(fx.cells(s, d, "P"))


@query
def fx_objects_q(s, d):
    return _described(fx.cells(s, d, "Q"))


@query
def fx_stats(s, d):
    p, q = _sides(s, d)
    named = lambda df, side: metrics.workload_stats(df).select(F.lit(side).alias("side"), "objects", "mean_area", "sd_area")
    return named(p, "P").unionByName(named(q, "Q"))


@query
def fx_satellites(s, d):
    return fx.with_boxes(fx.satellites(s, d)).select("image_id", "tile_id", "obj_id", *index.BOX)


@query
def fx_columns(s, d):
    return fx.columns(s, d).select("obj_id", F.size("ring").alias("n_vertices"), g.ring_area(F.col("ring")).alias("area"))


@query
def fx_scaled_area(s, d):
    p = fx.cells(s, d, "P")
    out = None
    for k in range(1, 6):
        row = fx.scaled(p, k).agg(F.lit(k).alias("factor"), F.sum(g.ring_area(F.col("ring"))).alias("area"))
        out = row if out is None else out.unionByName(row)
    return out


# parsing


@query
def parse_ok(s, d):
    objects, _ = parse.parse_polygons(fx.raw_text(s, d))
    return objects.groupBy("image_id").agg(F.count(F.lit(1)).alias("objects"), F.sum(g.ring_area(F.col("ring"))).alias("area_sum"))


@query
def parse_rejects(s, d):
    _, rejects = parse.parse_polygons(fx.raw_text(s, d))
    return rejects.groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


@query
def parse_vector_equals(s, d):
    """Lines, and lines whose result differs between the two parsers."""
    mark = lambda lane: parse.worked(fx.raw_text(s, d), lane).select("line_no", F.xxhash64("image_id", "tile_id", "ring", "reason", F.when(F.col("reason").isNull(), F.col("obj_id"))).alias(lane))
    both = mark("native").join(mark("vector"), "line_no")
    return both.agg(F.count(F.lit(1)).alias("lines"), F.count_if(F.col("native") != F.col("vector")).alias("mismatches"))


@query
def ring_repair(s, d):
    objects, _ = parse.parse_polygons(fx.raw_text(s, d))
    return objects.filter("(obj_id div 4) % 50 IN (4, 5)").select("obj_id", F.size("ring").alias("n_vertices"), g.ring_area(F.col("ring")).alias("area"))


# geometry


@query
def ring_area(s, d):
    return fx.cells(s, d, "P").select("obj_id", g.ring_area(F.col("ring")).alias("area"))


@query
def ring_area_partials(s, d):
    parts = g.area_partials(fx.cells(s, d, "P"), ["obj_id"])
    return parts.groupBy("obj_id").agg(F.expr("abs(sum(part)) div 2").alias("area"))


@query
def ring_mbr(s, d):
    return fx.with_boxes(fx.cells(s, d, "Q")).select("obj_id", *index.BOX)


@query
def ring_edges(s, d):
    rows = fx.cells(s, d, "P").select("obj_id", F.posexplode(g.vertical_edges(F.col("ring"))).alias("seq", "e"))
    return rows.select("obj_id", "seq", "e.x", "e.lo", "e.hi", "e.sgn")


@query
def centroid(s, d):
    c = fx.cells(s, d, "P").select("obj_id", g.centroid(F.col("ring")).alias("c"))
    return c.select("obj_id", F.round("c.x", 6).alias("cx"), F.round("c.y", 6).alias("cy"))


@query
def pixel_in_ring(s, d):
    """Pixels inside each object, by the test of one pixel: how many, and the sums of their places."""
    p = fx.with_boxes(fx.cells(s, d, "P"))
    rows = p.select("obj_id", g.vertical_edges(F.col("ring")).alias("e"), "minx", "maxx", F.explode(F.sequence("miny", F.col("maxy") - 1)).alias("y"))
    # an edge that the row's rays cannot meet is looked at once a row, the others for each pixel
    met = F.transform(F.filter("e", lambda e: (e["lo"] <= F.col("y")) & (F.col("y") < e["hi"])), lambda e: e["x"])
    cells = rows.select("obj_id", "y", met.alias("xs"), F.explode(F.sequence("minx", F.col("maxx") - 1)).alias("x"))
    inside = F.size(F.filter("xs", lambda x: x > F.col("x"))) % 2 == 1
    return general.pixel_sums(cells.filter(inside).select("obj_id", "x", "y"))


@query
def box_position_grid(s, d):
    """Positions of the grid boxes of 16 by 16 pixels that each object's bounding box meets."""
    p = fx.with_boxes(fx.cells(s, d, "P"))
    steps = lambda lo, hi: F.explode(F.sequence(F.floor(F.col(lo) / 16) * 16, F.floor((F.col(hi) - 1) / 16) * 16, F.lit(16).cast("bigint")))
    cells = p.select("obj_id", "ring", "miny", "maxy", steps("minx", "maxx").alias("bx")).withColumn("by", steps("miny", "maxy"))
    return cells.select("obj_id", "bx", "by", g.box_position(F.col("ring"), F.col("bx"), F.col("by"), F.col("bx") + 16, F.col("by") + 16).alias("pos"))


@query
def hilbert_keys(s, d):
    return index.hilbert_sorted(fx.cells(s, d, "P")).select("obj_id", "hilbert")


# pairing


@query
def pairs_tile_closed(s, d):
    return pairing.ids(_pairs(s, d))


@query
def pairs_tile_open(s, d):
    return pairing.ids(_pairs(s, d, closed=False))


@query
def pairs_image_grid(s, d):
    return pairing.ids(_pairs(s, d, scope="image"), with_tile=False)


@query
def pairs_tree(s, d):
    p, q = _sides(s, d)
    return pairing.ids(index.tree_join(index.build_tree(p), index.build_tree(q)))


@query
def pairs_nested(s, d):
    p, q = _sides(s, d)
    return pairing.ids(pairing.nested_pairs(p, q), with_tile=False)


@query
def pairs_intersecting(s, d):
    return pairing.ids(_pairs(s, d).filter(g.poly_intersects(F.col("ring_p"), F.col("ring_q"))))


@query
def tree_levels(s, d):
    return index.tree_levels(index.build_tree(fx.cells(s, d, "P")))


@query
def pairing_stats(s, d):
    pairs = _pairs(s, d)
    return pairing.pairing_stats(pairs, native.edge_form_areas(pairs))


@query
def pairs_roi(s, d):
    p, q = (pairing.roi_filter(fx.with_boxes(o), 0, 0, 100, 100) for o in _sides(s, d))
    return pairing.ids(pairing.candidate_pairs(p, q))


# kernels


@query
def area_edge_form(s, d):
    return native.areas_only(_areas(s, d))


@query
def area_edge_form_exploded(s, d):
    return native.edge_form_areas_exploded(_pairs(s, d))


@query
def area_pixel(s, d):
    return native.pixel_areas(_pairs(s, d))


@query
def area_pixel_vector(s, d):
    return native.areas_only(vector.pixel_areas(_pairs(s, d)))


@query
def area_pixel_spans(s, d):
    return native.pixel_span_areas(_pairs(s, d))


@query
def area_pixel_classes(s, d):
    return native.pixel_classes(_pairs(s, d))


def _hybrid(name: str, options: Options) -> None:
    REGISTRY[name] = lambda s, d: native.areas_only(vector.hybrid_areas(_pairs(s, d), options))


_hybrid("area_hybrid", Options())
_hybrid("area_hybrid_overlap_root", Options(root="overlap"))
_hybrid("area_hybrid_joint", Options(union="direct"))
_hybrid("area_boxes_only", Options(fan_out=4, threshold=2))
_hybrid("area_hybrid_stack", Options(frontier="stack", fan_out=4, threshold=8))


@query
def area_hybrid_relational(s, d):
    return relational.hybrid_relational(_pairs(s, d), Options(fan_out=4, threshold=16))


@query
def agreement_shapes(s, d):
    """Pairs whose areas differ between the adaptive kernel and the closed form, on vessels and on skylines."""
    out = None
    for name, p, q in (("vessels", fx.vessels(s, d), fx.cells(s, d, "P")), ("columns", fx.columns(s, d), fx.columns(s, d, shift=1))):
        pairs = _kept(pairing.candidate_pairs(p, q).select(*native.KEYS, "ring_p", "ring_q"), name)
        row = similarity.agreement(vector.pixel_areas(pairs), hybrid=vector.hybrid_areas(pairs), joint=vector.hybrid_areas(pairs, Options(union="direct")), overlay=vector.overlay_areas(pairs)).select(F.lit(name).alias("shape"), "method", "mismatches")
        out = row if out is None else out.unionByName(row)
    return out


@query
def rings_assembled(s, d):
    """Rings taken apart into vertex rows and put together again in order."""
    rows = fx.cells(s, d, "P").select("image_id", "tile_id", "obj_id", F.posexplode("ring").alias("seq", "v")).select("image_id", "tile_id", "obj_id", "seq", "v.x", "v.y")
    return g.assembled_rings(rows, ["image_id", "tile_id", "obj_id"]).select("obj_id", F.size("ring").alias("n_vertices"), g.ring_area(F.col("ring")).alias("area"))


@query
def objects_by_size(s, d):
    return pairing.size_filter(fx.cells(s, d, "P"), 100, 400).select("obj_id", "area")


@query
def area_overlay(s, d):
    return vector.overlay_areas(_pairs(s, d))


@query
def area_overlay_union(s, d):
    return vector.overlay_areas(_pairs(s, d), union="direct")


def _sums(named: list[tuple[object, str, DataFrame]]) -> DataFrame:
    out = None
    for value, column, areas in named:
        row = areas.agg(F.lit(value).alias(column), F.sum("inter").alias("inter_sum"), F.sum("uni").alias("uni_sum"))
        out = row if out is None else out.unionByName(row)
    return out


@query
def area_thresholds(s, d):
    pairs = _pairs(s, d)
    return _sums([(t, "threshold", vector.hybrid_areas(pairs, Options(threshold=t))) for t in (2, 16, 64, 128, 256)])


@query
def area_scaled(s, d):
    pairs = _kept_pairs(s, d)
    big = lambda k: pairs.select(*native.KEYS, g.scale_ring(F.col("ring_p"), k).alias("ring_p"), g.scale_ring(F.col("ring_q"), k).alias("ring_q"))
    return _sums([(k, "factor", vector.hybrid_areas(big(k))) for k in (1, 2, 3, 4, 5)])


#: The implementation variants, each with one more of: parallel arrays, edge blocks, cached edges.
LAYOUTS = {"records": Options(layout="records", edge_block=1, edge_cache=0, tables=False), "columns": Options(edge_block=1, edge_cache=0, tables=False), "blocks": Options(edge_block=8, edge_cache=0, tables=False), "cached": Options(edge_block=8, edge_cache=256, tables=False)}


@query
def area_layouts(s, d):
    pairs = _kept_pairs(s, d)
    return _sums([(name, "layout", vector.hybrid_areas(pairs, o)) for name, o in LAYOUTS.items()])


def _kept_pairs(s: SparkSession, d: str) -> DataFrame:
    """All pairs, joined once for a sweep's many settings and dealt over all cores, as a pair's work is large for its bytes."""
    return _kept(_pairs(s, d), "pairs")


def _kept(pairs: DataFrame, name: str) -> DataFrame:
    return materialised(pairs.repartition(4 * pairs.sparkSession.sparkContext.defaultParallelism), name)


METHODS = [Options(pixels_only=True, union="direct"), Options(union="direct"), Options()]


@query
def work_scale(s, d):
    return metrics.sweep(_kept_pairs(s, d), [1, 2, 3, 4, 5], METHODS)


@query
def work_threshold(s, d):
    settings = [Options(fan_out=n, threshold=t) for n in (16, 64, 256) for t in sorted({n // 4, n, n * n // 8, n * n // 2, n * n})]
    return metrics.sweep(_kept_pairs(s, d), [1, 3, 5], settings)


@query
def agreement(s, d):
    pairs = _pairs(s, d)
    return similarity.agreement(native.edge_form_areas(pairs), spans=native.pixel_span_areas(pairs), hybrid=vector.hybrid_areas(pairs), joint=vector.hybrid_areas(pairs, Options(union="direct")), overlay=vector.overlay_areas(pairs, union="direct"))


# scores


@query
def score_plain(s, d):
    return pipeline.plain_query(*_sides(s, d))


@query
def score_rewritten(s, d):
    return pipeline.rewritten_query(*_sides(s, d))


@query
def score_all(s, d):
    return similarity.mean_ratio(_areas(s, d), by=()).select("pairs", F.round("score", 6).alias("score"))


@query
def score_set_level(s, d):
    return similarity.set_jaccard(*_sides(s, d))


@query
def score_set_pixels(s, d):
    return similarity.set_jaccard_pixels(*_sides(s, d))


@query
def missing_objects(s, d):
    return similarity.missing_objects(_areas(s, d), *_sides(s, d))


@query
def unmatched_objects(s, d):
    return similarity.unmatched(_areas(s, d), *_sides(s, d))


@query
def overlap_profile(s, d):
    return similarity.overlap_profile(_areas(s, d))


def _five(s: SparkSession, d: str) -> DataFrame:
    out = fx.jittered(s, d, 0)
    for k in range(1, 5):
        out = out.unionByName(fx.jittered(s, d, k))
    return out


@query
def cross_matrix(s, d):
    return similarity.cross_matrix(_five(s, d))


@query
def cross_matrix_pivot(s, d):
    table = similarity.matrix_table(similarity.cross_matrix(_five(s, d)), [1, 2, 3, 4])
    return table.select("algo_a", *(F.col(str(k)).alias(f"with_{k}") for k in range(1, 5)))


@query
def score_cube(s, d):
    n, r = fx.load(s, d, "nation"), fx.load(s, d, "region")
    o, c = fx.load(s, d, "orders"), fx.load(s, d, "customer")
    where = F.broadcast(n.join(r, n["n_regionkey"] == r["r_regionkey"]))  # 25 rows at every scale
    dims = o.join(c, o["o_custkey"] == c["c_custkey"]).join(where, F.col("c_nationkey") == F.col("n_nationkey")).select((F.col("o_orderkey") * 4).alias("obj_id"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"))
    return similarity.score_cube(_areas(s, d), dims)


@query
def score_decimal(s, d):
    return similarity.mean_ratio(_areas(s, d), exact=True).select("image_id", "pairs", F.round("score", 9).cast("decimal(18,9)").alias("score"))


@query
def centroid_distance(s, d):
    same = _pairs(s, d).filter("p_id = q_id")
    return same.select("image_id", "p_id", F.round(g.centroid_distance(F.col("ring_p"), F.col("ring_q")), 6).alias("distance"))


@query
def best_match(s, d):
    return similarity.best_match(_areas(s, d))


@query
def ratio_histogram(s, d):
    return similarity.ratio_histogram(_areas(s, d))


@query
def worst_pairs_topk(s, d):
    return similarity.worst_pairs(_areas(s, d))


# relations


@query
def contains_pairs(s, d):
    return relate.contains_pairs(_pairs(s, d))


@query
def touches_pairs(s, d):
    return relate.touches_pairs(_pairs(s, d))


@query
def relation_counts(s, d):
    return relate.relations(_pairs(s, d)).groupBy("relation").agg(F.count(F.lit(1)).alias("n"))


@query
def vessel_pairs(s, d):
    pairs = pairing.candidate_pairs(fx.vessels(s, d), fx.cells(s, d, "P"))
    return native.areas_only(vector.hybrid_areas(pairs)).filter("inter > 0")


@query
def satellite_pairs(s, d):
    pairs = pairing.candidate_pairs(fx.satellites(s, d), fx.cells(s, d, "P"))
    return native.edge_form_areas(pairs).groupBy("image_id").agg(F.count(F.lit(1)).alias("pairs"), F.sum("inter").alias("inter_sum"))


@query
def column_pairs(s, d):
    pairs = pairing.candidate_pairs(fx.columns(s, d), fx.columns(s, d, shift=1)).repartition(4 * s.sparkContext.defaultParallelism)
    return vector.hybrid_areas(pairs).select("p_id", "inter")


# pipeline


@query
def tasks(s, d):
    return pipeline.tasks(*_sides(s, d))


@query
def batches(s, d):
    packed = pipeline.pack_batches(pipeline.tasks(*_sides(s, d)), 100_000)
    return packed.groupBy("batch_id").agg(F.count(F.lit(1)).alias("tasks"), F.sum("pixels").alias("cost"))


@query
def scheme_staged(s, d):
    return pipeline.run_staged(*_sides(s, d), streams=1)


@query
def scheme_streams(s, d):
    return pipeline.run_staged(*_sides(s, d), streams=4)


@query
def scheme_pipelined(s, d):
    return pipeline.run_pipelined(*_sides(s, d))


@query
def scheme_chunked16(s, d):
    return pipeline.run_database_style(*_sides(s, d), chunks=16)


@query
def scheme_database(s, d):
    return pipeline.run_database_style(*_sides(s, d), chunks=1)


@query
def routed_lanes(s, d):
    scores = similarity.mean_ratio(pipeline.routed_areas(_pairs(s, d)))
    return scores.select("image_id", "pairs", F.round("score", 6).alias("score"))


@query
def rebalance_sim(s, d):
    return rebalance.simulate_pipeline(s, pipeline.tasks(*_sides(s, d)))


@query
def geo_mean(s, d):
    counts = fx.cells(s, d, "P").groupBy("image_id").agg(F.count(F.lit(1)).alias("n"))
    return counts.agg(F.round(metrics.geo_mean(F.col("n").cast("double")), 6).alias("geo_mean"))


# streaming


@query
def arrivals_tumbling(s, d):
    return arrivals.tumbling(s, d)


@query
def arrivals_sliding(s, d):
    return arrivals.sliding(s, d)


@query
def arrivals_session(s, d):
    return arrivals.sessions(s, d)


@query
def arrivals_asof(s, d):
    return arrivals.asof(s, d)


@query
def arrivals_interval(s, d):
    return arrivals.interval_join(s, d)


@query
def tile_assembler(s, d):
    return arrivals.assemble_tiles(s, d).filter("p_event >= 0 AND q_event >= 0")


@query
def stream_score(s, d):
    return arrivals.stream_scores(s, d)


@query
def routed_stream(s, d):
    """Scores of pairs that arrive as a stream, with the lanes' cut moved by the backlog between batches."""
    return backlog.routed_scores(_pairs(s, d))


@query
def arrivals_outer(s, d):
    return arrivals.unanswered(s, d)


@query
def late_rows(s, d):
    return arrivals.late_rows(s, d)


# accuracy


@query
def pixel_resolution(s, d):
    t = fx.triangles(s, d)
    out = None
    for k in (4, 16, 64, 256):
        row = metrics.pixel_error(t, k).agg(F.lit(k).alias("g"), F.count(F.lit(1)).alias("n"), F.round(F.avg("rel_error"), 6).alias("mean_rel_error"))
        out = row if out is None else out.unionByName(row)
    return out


@query
def pixel_error_by_label(s, d):
    t = fx.triangles(s, d)
    return metrics.pixel_error(t, 64).groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("rel_error"), 6).alias("mean_rel_error"))


# sources and sinks


@query
def io_json_round_trip(s, d):
    back = io.read_rings_json(io.rings_json(fx.cells(s, d, "P")))
    return back.filter("corrupt IS NULL").select("obj_id", g.ring_area(F.col("ring")).alias("area"))


@query
def io_text_round_trip(s, d):
    objects, _ = parse.parse_polygons(parse.render(fx.cells(s, d, "Q")))
    return objects.select("obj_id", g.ring_area(F.col("ring")).alias("area"))


@query
def io_stored_layout(s, d):
    """Objects stored by image and Hilbert order, read again with a region filter that reaches the files' statistics."""
    from .storage import new_path

    path = new_path(s, "objects")
    io.write_objects(fx.cells(s, d, "P"), path)
    return pairing.roi_filter(s.read.parquet(path).filter("image_id = 17"), 0, 0, 300, 300).select("obj_id")


@query
def io_generated(s, d):
    """Objects that the generator makes in the places of the given orders."""
    made = io.generated_at(fx.places(s, d))
    return made.groupBy("image_id").agg(F.count(F.lit(1)).alias("n"), F.sum(g.ring_area(F.col("ring"))).alias("area"))


@query
def io_wkb(s, d):
    return fx.cells(s, d, "P").select("obj_id", F.hex(io.ring_to_wkb(F.col("ring"))).alias("wkb"))


def queries() -> dict[str, Query]:
    return REGISTRY | general.queries()
