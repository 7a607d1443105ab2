"""General relational operators around the comparison, each as a query on the given tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import geometry as g
from ..kernels import native, vector
from ..sources.fixtures import cells, load
from . import pairing


def salt_join(big: DataFrame, small: DataFrame, keys: list[str], salts: int = 8) -> DataFrame:
    """Equi-join whose hot keys are spread: the big side gets a salt, the small side one row per salt."""
    a = big.withColumn("_salt", F.pmod(F.xxhash64(*big.columns), F.lit(salts)).cast("int"))
    b = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [*keys, "_salt"]).drop("_salt")


def sample_by_key(df: DataFrame, key: str, modulus: int, remainder: int = 0) -> DataFrame:
    """A repeatable share of the rows by key."""
    return df.filter(F.col(key) % modulus == remainder)


def op_scan_prune(spark: SparkSession, d: str) -> DataFrame:
    o = load(spark, d, "orders")
    return o.filter((F.col("o_orderdate") >= F.lit("1996-01-01").cast("timestamp_ntz")) & (F.col("o_orderdate") < F.lit("1997-01-01").cast("timestamp_ntz")) & (F.col("o_totalprice") > 400000)).select("o_orderkey", "o_custkey", "o_orderdate")


def op_filters(spark: SparkSession, d: str) -> DataFrame:
    p = load(spark, d, "part")
    return p.filter(F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#23", "Brand#34") & F.col("p_name").like("%a%")).select("p_partkey", "p_name", "p_size")


def op_join_broadcast(spark: SparkSession, d: str) -> DataFrame:
    n, r = load(spark, d, "nation"), load(spark, d, "region")  # 25 and 5 rows at every scale
    names = n.join(F.broadcast(r), n["n_regionkey"] == r["r_regionkey"])
    c = load(spark, d, "customer")
    return c.join(F.broadcast(names), c["c_nationkey"] == names["n_nationkey"]).select("c_custkey", "n_name", "r_name")


def op_join_merge(spark: SparkSession, d: str) -> DataFrame:
    li, o = load(spark, d, "lineitem"), load(spark, d, "orders")
    j = li.hint("merge").join(o, li["l_orderkey"] == o["o_orderkey"])
    return j.groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("qty"))


def op_join_hash(spark: SparkSession, d: str) -> DataFrame:
    li, p = load(spark, d, "lineitem"), load(spark, d, "part")
    return li.join(p.hint("shuffle_hash"), li["l_partkey"] == p["p_partkey"]).groupBy("p_type").agg(F.count(F.lit(1)).alias("n"))


def op_join_nested(spark: SparkSession, d: str) -> DataFrame:
    s = load(spark, d, "supplier")
    a, b = s.alias("a"), s.alias("b")
    return a.join(b, (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_acctbal") < F.col("b.s_acctbal"))).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))


def op_join_range(spark: SparkSession, d: str) -> DataFrame:
    c, s = load(spark, d, "customer"), load(spark, d, "supplier")
    band = (c["c_nationkey"] == s["s_nationkey"]) & c["c_acctbal"].between(s["s_acctbal"] - 50, s["s_acctbal"] + 50)
    return c.join(s, band).select("c_custkey", "s_suppkey")


def op_join_theta(spark: SparkSession, d: str) -> DataFrame:
    """Pairs of a brand's parts of which the first is dearer: parts of one price stand together, and a running sum counts the cheaper ones."""
    prices = load(spark, d, "part").filter("p_brand IS NOT NULL AND p_retailprice IS NOT NULL").groupBy("p_brand", "p_retailprice").agg(F.count(F.lit(1)).alias("parts"))
    below = F.sum("parts").over(Window.partitionBy("p_brand").orderBy("p_retailprice").rowsBetween(Window.unboundedPreceding, -1))
    return prices.withColumn("below", below).filter("below > 0").groupBy("p_brand").agg(F.sum(F.col("parts") * F.col("below")).alias("n"))


def op_join_outer(spark: SparkSession, d: str) -> DataFrame:
    c, o = load(spark, d, "customer"), load(spark, d, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("n_orders"))


def op_join_full(spark: SparkSession, d: str) -> DataFrame:
    p, q = (cells(spark, d, s).select("image_id", "obj_id", F.lit(True).alias(s)) for s in "PQ")
    return p.join(q, ["image_id", "obj_id"], "full_outer").groupBy("image_id").agg(F.count_if(F.col("P") & F.col("Q")).alias("n_both"), F.count_if(F.col("Q").isNull()).alias("only_p"), F.count_if(F.col("P").isNull()).alias("only_q"))


def op_join_semi(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").select("doc_id").join(load(spark, d, "labels"), "doc_id", "left_semi")


def op_join_anti(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").select("doc_id").join(load(spark, d, "labels"), "doc_id", "left_anti")


def op_join_self(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "conversations").select("conv_id", "turn", "role")
    following = c.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("role").alias("next_role"))
    return c.join(following, ["conv_id", "turn"]).select("conv_id", "turn", "next_role")


def op_join_asof(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events").filter(F.col("event_type").isin("view", "purchase"))
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("prev_event_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.filter("event_type = 'purchase'").select("event_id", "prev_event_id")


def op_join_lateral(spark: SparkSession, d: str) -> DataFrame:
    docs = load(spark, d, "documents").select("doc_id", F.split("text", " ").alias("parts"))
    words = docs.lateralJoin(spark.tvf.explode(F.col("parts").outer()).toDF("word"))
    return words.filter("word <> ''").groupBy("doc_id").agg(F.count(F.lit(1)).alias("n_words"))


def op_join_salted(spark: SparkSession, d: str) -> DataFrame:
    li, s = load(spark, d, "lineitem").select("l_suppkey", "l_orderkey"), load(spark, d, "supplier").select(F.col("s_suppkey").alias("l_suppkey"))
    return salt_join(li, s, ["l_suppkey"]).groupBy("l_suppkey").agg(F.count(F.lit(1)).alias("n"))


def op_agg_hash(spark: SparkSession, d: str) -> DataFrame:
    li = load(spark, d, "lineitem")
    return li.groupBy(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast("bigint")).alias("qty"), F.round(F.avg("l_discount"), 6).alias("avg_disc"))


def op_agg_distinct(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "lineitem").groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("n"))


def op_agg_approx(spark: SparkSession, d: str) -> DataFrame:
    """Whether the sketch's distinct count is within five standard errors of the exact one."""
    x = load(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("a"), F.count_distinct("l_partkey").alias("b"))
    return x.select((F.abs(F.col("a") - F.col("b")) <= 0.1 * F.col("b")).alias("within"))


def op_agg_sketch(spark: SparkSession, d: str) -> DataFrame:
    """Distinct counts from sketches that are made per flag and merged: whether they are near the exact count."""
    lines = load(spark, d, "lineitem")
    parts = lines.groupBy("l_returnflag").agg(F.hll_sketch_agg("l_orderkey", 14).alias("sketch"))
    merged = parts.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("a"))
    exact = lines.agg(F.count_distinct("l_orderkey").alias("b"))
    return merged.join(exact).select((F.abs(F.col("a") - F.col("b")) <= 0.05 * F.col("b")).alias("within"))


def op_agg_rollup(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "part").rollup("p_brand", "p_size").agg(F.grouping_id().cast("int").alias("level"), F.count(F.lit(1)).alias("n")).select("p_brand", "p_size", "level", "n")


def op_agg_cube(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars"))


def op_agg_gsets(spark: SparkSession, d: str) -> DataFrame:
    li = load(spark, d, "lineitem")
    return li.groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n")).select("l_returnflag", "l_linestatus", "n")




def op_agg_pivot(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events").select(F.date_trunc("day", "ts").cast("date").alias("day"), "event_type")
    counts = e.groupBy("day").pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1)))
    return counts.select("day", *(F.coalesce(k, F.lit(0).cast("bigint")).alias(f"n_{k}") for k in ("click", "purchase", "view")))


def op_agg_percentile(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "orders").groupBy("o_orderpriority").agg(F.round(F.percentile("o_totalprice", 0.5), 6).alias("med"))


def op_agg_maxby(spark: SparkSession, d: str) -> DataFrame:
    o = load(spark, d, "orders")
    return o.groupBy(F.col("o_custkey").alias("c")).agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("o_orderkey"))


def op_agg_stats(spark: SparkSession, d: str) -> DataFrame:
    """Deviation, correlation and slope of object areas in P and Q over same objects."""
    areas = native.edge_form_areas(pairing.candidate_pairs(cells(spark, d, "P"), cells(spark, d, "Q"))).filter("p_id = q_id")
    return areas.agg(F.round(F.stddev_samp("area_p"), 6).alias("sd"), F.round(F.corr("area_p", "area_q"), 6).alias("corr"), F.round(F.regr_slope("area_q", "area_p"), 6).alias("slope"))


def op_win_rank(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("s_nationkey").orderBy(F.desc("s_acctbal"))
    return load(spark, d, "supplier").select("s_suppkey", F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("drk"), F.row_number().over(w.orderBy(F.desc("s_acctbal"), "s_suppkey")).cast("bigint").alias("rn"))


def op_win_frame(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(-4, 0)
    return load(spark, d, "orders").select("o_orderkey", F.sum(F.floor("o_totalprice")).over(w).cast("bigint").alias("s"))


def _micros():
    """Microseconds of ts since 1970, whatever the session's time zone."""
    return F.expr("timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01 00:00:00', ts)")


def op_win_range(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events").select("event_id", "user_id", _micros().alias("us"))
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return e.select("event_id", F.count(F.lit(1)).over(w).alias("n"))


def op_win_leadlag(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events").select("event_id", "user_id", _micros().alias("us"))
    w = Window.partitionBy("user_id").orderBy("us", "event_id")
    return e.select("event_id", (F.lead("us").over(w) - F.col("us")).alias("gap"))


def op_win_ntile(spark: SparkSession, d: str) -> DataFrame:
    """16 even chunks of each image's objects."""
    p = cells(spark, d, "P").select("image_id", "obj_id")
    return p.select("image_id", F.ntile(16).over(Window.partitionBy("image_id").orderBy("obj_id")).cast("int").alias("chunk")).groupBy("chunk").agg(F.count(F.lit(1)).alias("n"))


def op_win_dist(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, d, "customer").select("c_custkey", F.round(F.cume_dist().over(w), 6).alias("cd"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.nth_value("c_custkey", 2).over(whole).alias("second"))


def op_topk(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


def op_topk_group(spark: SparkSession, d: str) -> DataFrame:
    w = Window.partitionBy("o_orderpriority").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return load(spark, d, "orders").withColumn("rk", F.row_number().over(w)).filter("rk <= 3").select("o_orderpriority", "rk", "o_orderkey")


def op_page(spark: SparkSession, d: str) -> DataFrame:
    """The second page of ten by order key."""
    return load(spark, d, "orders").orderBy("o_orderkey").offset(10).limit(10).select("o_orderkey")


def _keys(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return load(spark, d, "customer").select(F.col("c_nationkey").alias("nationkey")), load(spark, d, "supplier").select(F.col("s_nationkey").alias("nationkey"))


def op_union(spark: SparkSession, d: str) -> DataFrame:
    c, s = _keys(spark, d)
    return c.unionByName(s).groupBy("nationkey").agg(F.count(F.lit(1)).alias("n"))


def op_intersect(spark: SparkSession, d: str) -> DataFrame:
    c, s = _keys(spark, d)
    return c.intersectAll(s)


def op_except(spark: SparkSession, d: str) -> DataFrame:
    c, s = _keys(spark, d)
    return c.exceptAll(s)


def op_distinct(spark: SparkSession, d: str) -> DataFrame:
    c, s = _keys(spark, d)
    return c.intersect(s).unionByName(c.subtract(s)).dropDuplicates(["nationkey"])


def op_string(spark: SparkSession, d: str) -> DataFrame:
    p = load(spark, d, "pages")
    host = F.regexp_extract("url", r"^[a-z]+://([^/]+)", 1)
    return p.select("page_id", host.alias("host"), (F.size(F.split("url", "/")) - 3).cast("int").alias("depth"), F.trim(F.substring("url", 1, 8)).alias("head"), F.length("html").cast("bigint").alias("chars"), F.translate("url", "/:", "__").alias("flat"))


def op_date(spark: SparkSession, d: str) -> DataFrame:
    li, o = load(spark, d, "lineitem"), load(spark, d, "orders")
    j = li.join(o, li["l_orderkey"] == o["o_orderkey"])
    return j.groupBy(F.date_trunc("quarter", "o_orderdate").cast("date").alias("q")).agg(F.count(F.lit(1)).alias("n"), F.sum(F.datediff(F.col("l_shipdate").cast("date"), F.col("o_orderdate").cast("date"))).cast("bigint").alias("days"))


def op_math(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "customer")
    bucket = F.width_bucket("c_acctbal", F.lit(-1000.0), F.lit(10000.0), F.lit(11))
    signed = F.signum("c_acctbal") * F.ln(1 + F.abs("c_acctbal"))
    return c.groupBy(bucket.cast("bigint").alias("bucket")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(signed), 4).alias("logs"))


def op_array(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("v"))
    norm = F.sqrt(F.aggregate("v", F.lit(0.0), lambda s, x: s + x * x))
    return e.select("vec_id", F.round(norm, 6).alias("norm"), F.array_position("v", F.array_max("v")).cast("int").alias("arg"))


def op_map(spark: SparkSession, d: str) -> DataFrame:
    e = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = e.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.element_at("m", "click"), F.lit(0).cast("bigint")).alias("clicks"))


def op_json(spark: SparkSession, d: str) -> DataFrame:
    return load(spark, d, "events").select("event_id", F.from_json("props", "k string")["k"].alias("k"))


def op_sqludf(spark: SparkSession, d: str) -> DataFrame:
    g.register_sql_functions(spark)
    return cells(spark, d, "P").selectExpr("obj_id", "seg_area(ring) AS area")


def _ring_areas(rings: pa.Array) -> pa.Array:
    return pa.array(vector.Rings.of(rings).area)


def op_arrowudf(spark: SparkSession, d: str) -> DataFrame:
    from pyspark.sql.functions import arrow_udf

    return cells(spark, d, "P").select("obj_id", arrow_udf(_ring_areas, "bigint")("ring").alias("area"))


def op_udaf(spark: SparkSession, d: str) -> DataFrame:
    """Mean ratio by a grouped Arrow aggregate."""
    from pyspark.sql.functions import arrow_udf

    def mean(inter: pa.Array, uni: pa.Array) -> float:
        return float(np.mean(np.asarray(inter, np.float64) / np.asarray(uni, np.float64)))

    mean.__annotations__ = {"inter": pa.Array, "uni": pa.Array, "return": float}
    areas = native.edge_form_areas(pairing.candidate_pairs(cells(spark, d, "P"), cells(spark, d, "Q"))).filter("inter > 0")
    return areas.groupBy("image_id").agg(arrow_udf(mean, "double")("inter", "uni").alias("s")).select("image_id", F.round("s", 6).alias("score"))


class _Pixels:
    """The pixels of each ring of a table's Arrow batches."""

    def eval(self, batch: pa.RecordBatch) -> Iterator[pa.Table]:
        rings, ids = vector.Rings.of(batch.column("ring")), batch.column("obj_id").to_numpy()
        x0, y0, x1, y1 = rings.box
        boxes = vector.strips((np.arange(len(ids)), x0, y0, x1, y1), 1_000_000)
        pair, x0, y0, x1, y1 = boxes
        size = (x1 - x0) * (y1 - y0)
        for part in np.split(np.arange(len(pair)), np.flatnonzero(np.diff(np.cumsum(size) // 1_000_000)) + 1) if len(pair) else ():
            base = np.cumsum(size[part]) - size[part]
            at = np.flatnonzero(rings.raster(*(v[part] for v in boxes), base, int(size[part].sum())))
            k = np.searchsorted(base, at, "right") - 1
            cell, r = at - base[k], part[k]
            width = x1[r] - x0[r]
            yield pa.table({"obj_id": ids[pair[r]], "x": x0[r] + cell % width, "y": y0[r] + cell // width})


class _Boxes:
    """Boxes that the adaptive kernel tests for a pair, with level and positions."""

    def eval(self, p, q, fan_out: int, threshold: int):
        make = lambda r: vector.Rings(np.array([v.x for v in r], np.int64), np.array([v.y for v in r], np.int64), np.array([0, len(r)]))
        a, b = make(p), make(q)
        options = vector.Options(fan_out=fan_out, threshold=threshold)
        root = tuple(np.atleast_1d(f(x, y)) for f, x, y in zip((np.minimum, np.minimum, np.maximum, np.maximum), a.box, b.box, strict=True))
        level = 0
        while len(root[0]):
            size = (root[2] - root[0]) * (root[3] - root[1])
            _, *part = vector.split(*(v[size >= options.limit] for v in root), options.side)
            zero = np.zeros(len(part[0]), np.int64)
            f1, f2 = a.positions(zero, *part, options), b.positions(zero, *part, options)
            for k in range(len(zero)):
                yield level, *(int(v[k]) for v in part), int(f1[k]), int(f2[k])
            go_on = vector.needs_split(f1, f2)
            root, level = tuple(v[go_on] for v in part), level + 1


def register_table_functions(spark: SparkSession) -> None:
    """seg_pixels(TABLE(obj_id, ring)), seg_boxes(ring, ring, fan_out, threshold)."""
    spark.udtf.register("seg_pixels", F.arrow_udtf(_Pixels, returnType="obj_id bigint, x bigint, y bigint"))
    spark.udtf.register("seg_boxes", F.udtf(_Boxes, returnType="level int, x0 bigint, y0 bigint, x1 bigint, y1 bigint, f1 int, f2 int"))


def pixel_sums(pixels: DataFrame) -> DataFrame:
    """obj_id, x, y rows -> obj_id, n, sum_x, sum_y."""
    return pixels.groupBy("obj_id").agg(F.count(F.lit(1)).alias("n"), F.sum("x").alias("sum_x"), F.sum("y").alias("sum_y"))


def op_udtf(spark: SparkSession, d: str) -> DataFrame:
    register_table_functions(spark)
    cells(spark, d, "P").select("obj_id", "ring").createOrReplaceTempView("_seg_rings")
    return pixel_sums(spark.sql("SELECT obj_id, x, y FROM seg_pixels(TABLE(_seg_rings))"))


def op_cogroup(spark: SparkSession, d: str) -> DataFrame:
    """Both sides of a tile in one Arrow call: overlapping pairs of each tile."""

    def tile(p: pa.Table, q: pa.Table) -> pa.Table:
        key = p if len(p) else q
        a, b = (vector.Rings.of(t.column("ring").combine_chunks()) if len(t) else None for t in (p, q))
        n = 0
        if a is not None and b is not None:
            meet = (a.box[0][:, None] <= b.box[2]) & (b.box[0] <= a.box[2][:, None]) & (a.box[1][:, None] <= b.box[3]) & (b.box[1] <= a.box[3][:, None])
            n = int(meet.sum())
        return pa.table({"image_id": pa.array([key.column("image_id")[0].as_py()], pa.int32()), "tile_id": pa.array([key.column("tile_id")[0].as_py()], pa.int64()), "n": pa.array([n], pa.int64())})

    p, q = (cells(spark, d, s).select("image_id", "tile_id", "ring").groupBy("image_id", "tile_id") for s in "PQ")
    return p.cogroup(q).applyInArrow(tile, "image_id int, tile_id bigint, n bigint")


def queries() -> dict:
    return {name: f for name, f in globals().items() if name.startswith("op_")}


