"""Measures of runs: time, shares, speed-up, throughput, geometric mean, utilisation, accuracy."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as g
from ..kernels import native, vector
from ..operators import pairing


def timed(df: DataFrame) -> float:
    """Seconds to compute df, written nowhere."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def best_of(make: Callable[[], DataFrame], runs: int = 3) -> float:
    """Median seconds after one warm-up run."""
    timed(make())
    return sorted(timed(make()) for _ in range(runs))[runs // 2]


def speedup(base: float, other: float) -> float:
    return base / other if other else math.inf


def reduction(base: float, other: float) -> float:
    """Share of the time saved."""
    return 1 - other / base if base else 0.0


def throughput(size: float, seconds: float) -> float:
    return size / seconds if seconds else math.inf


def utilisation(task_seconds: float, wall: float, cores: int) -> float:
    return task_seconds / (wall * cores) if wall and cores else 0.0


def cost_effectiveness(speed: float, price: float) -> float:
    return speed / price if price else math.inf


def geo_mean(column: Column) -> Column:
    """Geometric mean of a column of ratios, as an aggregate."""
    return F.exp(F.avg(F.ln(column)))


def run_seconds(make: Callable[[], DataFrame], runs: int = 1) -> float:
    """Median seconds of making and computing a frame; what a scheme does before it returns counts."""
    taken = []
    for _ in range(runs):
        began = time.perf_counter()
        timed(make())
        taken.append(time.perf_counter() - began)
    return sorted(taken)[runs // 2]


def image_speedups(p: DataFrame, q: DataFrame, base: Callable[[DataFrame, DataFrame], DataFrame], other: Callable[[DataFrame, DataFrame], DataFrame]) -> Iterator[tuple[int, float, float, float]]:
    """(image, seconds of base, seconds of other, speed-up) of each image's two sets, one after another."""
    for (image,) in p.select("image_id").distinct().orderBy("image_id").collect():  # as many rows as images
        own = [df.filter(F.col("image_id") == image) for df in (p, q)]
        a, b = (run_seconds(lambda f=f: f(*own)) for f in (base, other))
        yield image, a, b, speedup(a, b)


def profile_query(p: DataFrame, q: DataFrame, variant: str = "rewritten", runs: int = 3) -> list[tuple[str, float, float]]:
    """(component, seconds, share) of a comparison query: prefixes of the plan are timed and subtracted."""
    pairs = lambda: pairing.candidate_pairs(p, q)
    steps: list[tuple[str, DataFrame]] = [("index", pairing.with_boxes(p).unionByName(pairing.with_boxes(q))), ("search", pairs())]
    if variant == "plain":
        steps.append(("intersects", pairs().filter(g.poly_intersects(F.col("ring_p"), F.col("ring_q")))))
        steps.append(("intersection area", vector.overlay_areas(steps[-1][1])))
        steps.append(("union area", vector.overlay_areas(steps[-2][1], union="direct")))
    else:
        steps.append(("polygon areas", pairs().withColumns({"a": g.ring_area(F.col("ring_p")), "b": g.ring_area(F.col("ring_q"))})))
        steps.append(("intersection area", vector.overlay_areas(pairs())))
    seconds = [best_of(lambda df=df: df, runs) for _, df in steps]
    own = [seconds[0], *(max(0.0, b - a) for a, b in zip(seconds, seconds[1:], strict=False))]
    if variant != "plain":
        own[-1] = max(0.0, seconds[-1] - seconds[1])
    total = sum(own) or 1.0
    return [(name, s, s / total) for (name, _), s in zip(steps, own, strict=True)]


def sweep(pairs: DataFrame, factors: list[int], settings: list[vector.Options]) -> DataFrame:
    """Work counters for each enlargement and setting of the adaptive kernel, from one pass over the pairs."""
    spark = pairs.sparkSession
    named = [(k, f, "pixel" if o.pixels_only else "hybrid_joint" if o.union == "direct" else "hybrid", o.fan_out, o.limit) for f in factors for k, o in enumerate(settings)]
    told = spark.createDataFrame(named, "setting int, factor int, method string, fanout int, threshold bigint")
    # without a pair the counters are empty
    return told.join(vector.sweep_work(pairs, factors, settings), ["factor", "setting"], "left").select("factor", "method", "fanout", "threshold", "pixels", "boxes", "partitions", "max_level")


def workload_stats(objects: DataFrame) -> DataFrame:
    """Objects, mean and sample deviation of the area (see pair_stats for pairs)."""
    area = g.ring_area(F.col("ring"))
    return objects.select(area.alias("a")).agg(F.count(F.lit(1)).alias("objects"), F.round(F.avg("a"), 6).alias("mean_area"), F.round(F.stddev_samp("a"), 6).alias("sd_area"))


def pair_stats(objects: DataFrame, pairs: DataFrame) -> DataFrame:
    """Pairs, pairs an object, mean and sample deviation of the pairs in a tile."""
    by_tile = pairs.groupBy("image_id", "tile_id").agg(F.count(F.lit(1)).alias("n"))
    tiles = objects.groupBy("image_id", "tile_id").agg(F.count(F.lit(1)).alias("objects")).join(by_tile, ["image_id", "tile_id"], "left").withColumn("n", F.coalesce("n", F.lit(0)))
    return tiles.agg(F.sum("n").alias("pairs"), F.round(F.sum("n") / F.sum("objects"), 6).alias("pairs_per_object"), F.round(F.avg("n"), 6).alias("mean_pairs"), F.round(F.stddev_samp("n"), 6).alias("sd_pairs"))


def pixel_area_float(triangles: DataFrame, resolution: int) -> DataFrame:
    """Polygons with real coordinates, enlarged by `resolution`: exact area and count of pixel centres inside (any edge direction)."""
    g_ = float(resolution)
    t = triangles.select("*", F.transform("xs", lambda v: v * g_).alias("X"), F.transform("ys", lambda v: v * g_).alias("Y"))
    n = F.size("X")
    idx = F.sequence(F.lit(0), n - 1)
    nxt = lambda a, k: F.get(a, (k + 1) % n)
    exact = F.abs(F.aggregate(F.transform(idx, lambda k: F.get("X", k) * nxt("Y", k) - nxt("X", k) * F.get("Y", k)), F.lit(0.0), lambda s, v: s + v)) / 2
    rows = t.select(*triangles.columns, "X", "Y", exact.alias("exact"), F.explode(F.sequence(F.floor(F.array_min("Y")), F.floor(F.array_max("Y")))).alias("j"))
    cy = F.col("j") + 0.5
    cuts = F.filter(F.transform(idx, lambda k: F.when((F.get("Y", k) > cy) != (nxt("Y", k) > cy), F.get("X", k) + (cy - F.get("Y", k)) * (nxt("X", k) - F.get("X", k)) / (nxt("Y", k) - F.get("Y", k)))), lambda x: x.isNotNull())
    rows = rows.withColumn("cuts", F.array_sort(cuts))
    # centres i + 0.5 with cut_2m <= i + 0.5 < cut_2m+1
    upto = lambda x: F.ceil(x - 0.5)
    per_row = F.aggregate(F.transform(F.sequence(F.lit(0), F.floor(F.size("cuts") / 2).cast("int") - 1), lambda m: upto(F.get("cuts", 2 * m + 1)) - upto(F.get("cuts", 2 * m))), F.lit(0).cast("bigint"), lambda s, v: s + v)
    counted = rows.select(*triangles.columns, "exact", F.when(F.size("cuts") > 1, per_row).otherwise(0).alias("c"))
    return counted.groupBy(*[c for c in triangles.columns if c not in ("xs", "ys")]).agg(F.first("exact").alias("exact"), F.sum("c").alias("pixels"))


def pixel_error(triangles: DataFrame, resolution: int) -> DataFrame:
    counted = pixel_area_float(triangles, resolution)
    return counted.withColumn("rel_error", F.abs(F.col("pixels") - F.col("exact")) / F.col("exact"))
