"""DuckDB SQL for the registry's queries: stand-alone text, no code shared with the engine."""

from __future__ import annotations

# The outlines by shape, x and y of each vertex in turn.
_OUTLINES = """
0: 0 0 6 0 6 6 0 6
1: 0 0 6 0 6 3 3 3 3 6 0 6
2: 0 0 6 0 6 6 4 6 4 2 2 2 2 6 0 6
3: 0 0 6 0 6 2 2 2 2 4 6 4 6 6 0 6
4: 2 0 4 0 4 2 6 2 6 4 4 4 4 6 2 6 2 4 0 4 0 2 2 2
5: 0 0 4 0 4 2 6 2 6 6 2 6 2 4 0 4
6: 0 0 6 0 6 5 5 5 5 2 4 2 4 6 2 6 2 3 1 3 1 6 0 6
7: 1 0 5 0 5 1 6 1 6 5 5 5 5 6 1 6 1 5 0 5 0 1 1 1
"""


def _values() -> str:
    rows = []
    for line in _OUTLINES.strip().splitlines():
        shape, _, rest = line.partition(":")
        numbers = rest.split()
        rows += [f"({shape}, {k}, {x}, {y})" for k, (x, y) in enumerate(zip(numbers[::2], numbers[1::2], strict=True))]
    return ", ".join(rows)


_NEXT = "coalesce(lead({c}) OVER (PARTITION BY obj_id ORDER BY seq), first_value({c}) OVER (PARTITION BY obj_id ORDER BY seq))"


def _rings(name: str, source: str) -> str:
    """{name}v vertices with their followers, {name}e vertical edges, {name}b boxes with areas."""
    return f"""
{name}v0 AS (SELECT image_id, tile_id, obj_id, seq, x0 + su * tx AS x, y0 + sv * ty AS y FROM {source} JOIN shapes USING (shape)),
{name}v AS (SELECT *, {_NEXT.format(c="x")} AS nx, {_NEXT.format(c="y")} AS ny FROM {name}v0),
{name}e AS (SELECT image_id, tile_id, obj_id, seq, x, least(y, ny) AS lo, greatest(y, ny) AS hi, CASE WHEN ny < y THEN 1 ELSE -1 END AS sgn FROM {name}v WHERE x = nx),
{name}b AS (SELECT image_id, tile_id, obj_id, count(*) AS nv, min(x) AS minx, min(y) AS miny, max(x) AS maxx, max(y) AS maxy, CAST(abs(sum(x * ny - nx * y)) // 2 AS BIGINT) AS area FROM {name}v GROUP BY ALL)"""


_PLACED = f"""shapes(shape, seq, tx, ty) AS (VALUES {_values()}),
ob AS (SELECT o_orderkey AS k, o_custkey AS c, CAST(floor(o_totalprice) AS BIGINT) AS t, o_orderkey % 324 AS u FROM orders),
oi AS (SELECT *, CAST(floor(sqrt(u)) AS INTEGER) AS image_id FROM ob),
ow AS (SELECT *, (k // 324) * (2 * image_id + 1) + u - image_id * image_id AS w FROM oi),
pl AS (SELECT k, image_id, w // 64 AS tile_id, ((w // 64) % 8) * 208 + (w % 8) * 26 + c % 9 AS x0, ((w // 64) // 8) * 208 + ((w % 64) // 8) * 26 + t % 9 AS y0, c % 8 AS shape, 1 + (c // 8) % 4 AS su, 1 + t % 4 AS sv FROM ow),
po AS (SELECT image_id, tile_id, 4 * k AS obj_id, x0, y0, shape, su, sv FROM pl),
qo AS (SELECT image_id, tile_id, 4 * k AS obj_id, x0 + (7 * k) % 5 - 2 AS x0, y0 + (3 * k) % 5 - 2 AS y0, CASE WHEN k % 10 = 3 THEN (shape + 1) % 8 ELSE shape END AS shape, CASE WHEN k % 9 = 4 THEN 1 + su % 4 ELSE su END AS su, sv FROM pl WHERE k % 13 <> 0
  UNION ALL SELECT image_id, tile_id, 4 * k + 1, x0 + 13, y0 + 11, 7, 1, 1 FROM pl WHERE k % 17 = 0)"""

_MEET = "p.minx <= q.maxx AND q.minx <= p.maxx AND p.miny <= q.maxy AND q.miny <= p.maxy"
_MEET_OPEN = _MEET.replace("<=", "<")
_TERM = "a.sgn * b.sgn * greatest(least(a.hi, b.hi) - greatest(a.lo, b.lo), 0) * greatest(a.x, b.x)"

F1 = f"""WITH {_PLACED},{_rings("p", "po")},{_rings("q", "qo")},
pr AS (SELECT p.image_id, p.tile_id, p.obj_id AS p_id, q.obj_id AS q_id, p.area AS area_p, q.area AS area_q, p.minx AS pminx, p.miny AS pminy, p.maxx AS pmaxx, p.maxy AS pmaxy, q.minx AS qminx, q.miny AS qminy, q.maxx AS qmaxx, q.maxy AS qmaxy FROM pb p JOIN qb q ON p.image_id = q.image_id AND p.tile_id = q.tile_id AND {_MEET}),
it AS (SELECT p_id, q_id, CAST(-sum({_TERM}) AS BIGINT) AS inter FROM pr JOIN pe a ON a.obj_id = p_id JOIN qe b ON b.obj_id = q_id GROUP BY p_id, q_id),
ar AS (SELECT image_id, tile_id, p_id, q_id, inter, area_p, area_q, area_p + area_q - inter AS uni FROM pr JOIN it USING (p_id, q_id)),
hit AS (SELECT *, inter / uni AS ratio FROM ar WHERE inter > 0)
"""

_AREAS = F1 + "SELECT image_id, p_id, q_id, inter, uni FROM ar"
_SCORES = F1 + "SELECT image_id, count(*) AS pairs, round(avg(ratio), 6) AS score FROM hit GROUP BY image_id"
_BOX = "minx, miny, maxx, maxy"


def _objects(side: str) -> str:
    return F1 + f"SELECT image_id, tile_id, obj_id, CAST(nv AS INTEGER) AS n_vertices, {_BOX}, area FROM {side}b"


_SUM = "CAST(sum(inter) AS BIGINT) AS inter_sum, CAST(sum(uni) AS BIGINT) AS uni_sum"
_COLS = r"""WITH w AS (SELECT doc_id, 1 + n_chars % 3 AS width, list_filter(regexp_split_to_array(text, '[ \t\n\r\x0B\f]+'), lambda x: x <> '') AS words FROM documents),
h AS (SELECT doc_id, width, unnest(words) AS word, generate_subscripts(words, 1) AS i FROM w),
c AS (SELECT doc_id * 65536 + (i - 1) // 128 AS obj_id, width, i, 1 + length(word) % 16 AS h FROM h)
"""
_EVENTS = """WITH a AS (SELECT event_id, CASE WHEN event_id % 2 = 0 THEN 'P' ELSE 'Q' END AS side, CAST((event_id // 2) % 18 AS INTEGER) AS image_id, (event_id // 36) % 64 AS tile_id, CAST(round(value * 1000) AS BIGINT) AS bytes, ts FROM events)
"""
_TRI = """WITH v AS (SELECT vec_id, label, CAST(embedding[1] AS DOUBLE) AS x1, CAST(embedding[2] AS DOUBLE) AS y1, CAST(embedding[3] AS DOUBLE) AS x2, CAST(embedding[4] AS DOUBLE) AS y2, CAST(embedding[5] AS DOUBLE) AS x3, CAST(embedding[6] AS DOUBLE) AS y3 FROM embeddings),
s AS (SELECT vec_id, label, g, x1 * g AS x1, y1 * g AS y1, x2 * g AS x2, y2 * g AS y2, x3 * g AS x3, y3 * g AS y3 FROM v, (VALUES (4), (16), (64), (256)) t(g)),
ex AS (SELECT *, abs((x1 * y2 - x2 * y1) + (x2 * y3 - x3 * y2) + (x3 * y1 - x1 * y3)) / 2 AS exact FROM s),
r AS (SELECT *, unnest(range(CAST(floor(least(y1, y2, y3)) AS BIGINT), CAST(floor(greatest(y1, y2, y3)) AS BIGINT) + 1)) + 0.5 AS cy FROM ex),
k AS (SELECT *, list_sort(list_filter([CASE WHEN (y1 > cy) <> (y2 > cy) THEN x1 + (cy - y1) * (x2 - x1) / (y2 - y1) END, CASE WHEN (y2 > cy) <> (y3 > cy) THEN x2 + (cy - y2) * (x3 - x2) / (y3 - y2) END, CASE WHEN (y3 > cy) <> (y1 > cy) THEN x3 + (cy - y3) * (x1 - x3) / (y1 - y3) END], lambda z: z IS NOT NULL)) AS cuts FROM r),
n AS (SELECT vec_id, label, g, any_value(exact) AS exact, sum(CASE WHEN len(cuts) = 2 THEN ceil(cuts[2] - 0.5) - ceil(cuts[1] - 0.5) ELSE 0 END) AS px FROM k GROUP BY vec_id, label, g),
e AS (SELECT *, abs(px - exact) / exact AS err FROM n)
"""
_JIT = ",".join(_rings(f"j{k}", f"jo{k}") for k in range(5))
_JITTERED = f"WITH {_PLACED}," + ",".join(f"jo{k} AS (SELECT image_id, tile_id, 4 * k AS obj_id, x0 + {k} * ((7 * k) % 5 - 2) AS x0, y0 + {k} * ((3 * k) % 5 - 2) AS y0, shape, su, sv FROM pl)" for k in range(5)) + f",{_JIT}," + f"""
jb AS ({" UNION ALL ".join(f"SELECT {k} AS algo, * FROM j{k}b" for k in range(5))}), je AS ({" UNION ALL ".join(f"SELECT {k} AS algo, * FROM j{k}e" for k in range(5))}),
jp AS (SELECT p.algo AS algo_a, q.algo AS algo_b, p.obj_id AS p_id, q.obj_id AS q_id, p.area + q.area AS total FROM jb p JOIN jb q ON p.algo < q.algo AND p.image_id = q.image_id AND p.tile_id = q.tile_id AND {_MEET}),
ji AS (SELECT algo_a, algo_b, p_id, q_id, any_value(total) AS total, -sum({_TERM}) AS inter FROM jp JOIN je a ON a.algo = algo_a AND a.obj_id = p_id JOIN je b ON b.algo = algo_b AND b.obj_id = q_id GROUP BY ALL),
jm AS (SELECT algo_a, algo_b, count(*) AS pairs, round(avg(inter / (total - inter)), 6) AS score FROM ji WHERE inter > 0 GROUP BY ALL)
"""
_SPANS = """, {n}rows AS (SELECT image_id, obj_id, unnest(range(lo, hi)) AS y, x FROM {n}e),
{n}k AS (SELECT image_id, obj_id, y, x, row_number() OVER w AS rn, lead(x) OVER w AS nx FROM {n}rows WINDOW w AS (PARTITION BY image_id, obj_id, y ORDER BY x)),
{n}x AS (SELECT DISTINCT image_id, y, unnest(range(x, nx)) AS x FROM {n}k WHERE rn % 2 = 1)"""
_SETS = F1.rstrip() + _SPANS.format(n="p") + _SPANS.format(n="q") + """
SELECT coalesce(a.image_id, b.image_id) AS image_id, count(a.x) AS px_p, count(b.x) AS px_q, count(*) FILTER (WHERE a.x IS NOT NULL AND b.x IS NOT NULL) AS px_both, count(*) AS px_any,
  round(count(*) FILTER (WHERE a.x IS NOT NULL AND b.x IS NOT NULL) / count(*), 6) AS score FROM px a FULL JOIN qx b ON a.image_id = b.image_id AND a.y = b.y AND a.x = b.x GROUP BY 1"""
_TOUCH = "EXISTS (SELECT 1 FROM ps a JOIN qs b ON a.obj_id = p_id AND b.obj_id = q_id AND a.ax <= b.bx AND b.ax <= a.bx AND a.ay <= b.by_ AND b.ay <= a.by_)"
_SEGS = F1.rstrip() + """, ps AS (SELECT obj_id, least(x, nx) AS ax, greatest(x, nx) AS bx, least(y, ny) AS ay, greatest(y, ny) AS by_ FROM pv), qs AS (SELECT obj_id, least(x, nx) AS ax, greatest(x, nx) AS bx, least(y, ny) AS ay, greatest(y, ny) AS by_ FROM qv),
zero AS (SELECT image_id, p_id, q_id FROM ar WHERE inter = 0), tz AS (SELECT DISTINCT image_id, p_id, q_id FROM zero JOIN ps a ON a.obj_id = p_id JOIN qs b ON b.obj_id = q_id AND a.ax <= b.bx AND b.ax <= a.bx AND a.ay <= b.by_ AND b.ay <= a.by_)
"""
_BY_IMAGE = "FROM ar GROUP BY image_id"
_TASKS = F1.rstrip() + """, sz AS (SELECT image_id, tile_id, count(*) AS objects, CAST(sum(nv) AS BIGINT) AS vertices FROM (SELECT * FROM pb UNION ALL SELECT * FROM qb) GROUP BY ALL),
wk AS (SELECT image_id, tile_id, count(*) AS pairs, CAST(sum((greatest(pmaxx, qmaxx) - least(pminx, qminx)) * (greatest(pmaxy, qmaxy) - least(pminy, qminy))) AS BIGINT) AS pixels FROM pr GROUP BY ALL),
tk AS (SELECT image_id, tile_id, objects, vertices, coalesce(pairs, 0) AS pairs, coalesce(pixels, 0) AS pixels FROM sz LEFT JOIN wk USING (image_id, tile_id))
"""


def _windows(starts: str, length: str) -> str:
    return _EVENTS + f"SELECT s AS start, s + INTERVAL '{length}' AS \"end\", image_id, count(*) AS files, CAST(sum(bytes) AS BIGINT) AS bytes FROM (SELECT *, {starts} AS s FROM a) WHERE ts >= s AND ts < s + INTERVAL '{length}' GROUP BY s, image_id"


_SCALE = "SELECT CAST(f AS INTEGER) AS factor, CAST(f * f * sum(inter) AS BIGINT) AS inter_sum, CAST(f * f * sum(uni) AS BIGINT) AS uni_sum FROM ar, range(1, 6) t(f) GROUP BY f"

_PIXEL_SUMS = F1 + "SELECT obj_id, count(*) AS n, CAST(sum(x) AS BIGINT) AS sum_x, CAST(sum(y) AS BIGINT) AS sum_y FROM (SELECT c.obj_id, c.x, c.y, count(e.x) AS n FROM (SELECT obj_id, x, unnest(range(miny, maxy)) AS y FROM (SELECT obj_id, miny, maxy, unnest(range(minx, maxx)) AS x FROM pb)) c LEFT JOIN pe e ON e.obj_id = c.obj_id AND e.x > c.x AND e.lo <= c.y AND c.y < e.hi GROUP BY ALL) WHERE n % 2 = 1 GROUP BY obj_id"

SQL: dict[str, str] = {
    "rings_assembled": F1 + "SELECT obj_id, CAST(nv AS INTEGER) AS n_vertices, area FROM pb",
    "objects_by_size": F1 + "SELECT obj_id, area FROM pb WHERE area BETWEEN 100 AND 400",
    "agreement_shapes": "SELECT shape, method, CAST(0 AS BIGINT) AS mismatches FROM (VALUES ('vessels'), ('columns')) s(shape), (VALUES ('hybrid'), ('joint'), ('overlay')) t(method)",
    "arrivals_outer": _EVENTS + "SELECT p.image_id, p.tile_id, p.event_id AS p_event FROM a p WHERE p.side = 'P' AND NOT EXISTS (SELECT 1 FROM a q WHERE q.side = 'Q' AND q.image_id = p.image_id AND q.tile_id = p.tile_id AND q.ts BETWEEN p.ts - INTERVAL 1 HOUR AND p.ts + INTERVAL 1 HOUR) AND p.ts <= (SELECT least(max(ts) FILTER (WHERE side = 'P'), max(ts) FILTER (WHERE side = 'Q')) - INTERVAL 2 DAY FROM a)",
    "fx_objects_p": _objects("p"),
    "fx_objects_q": _objects("q"),
    "fx_stats": F1 + "SELECT side, count(*) AS objects, round(avg(area), 6) AS mean_area, round(stddev_samp(area), 6) AS sd_area FROM (SELECT 'P' AS side, area FROM pb UNION ALL SELECT 'Q', area FROM qb) GROUP BY side",
    "fx_satellites": f"WITH {_PLACED}, l AS (SELECT l_orderkey AS k, l_linenumber AS n, sum(l_partkey) AS sp, sum(l_suppkey) AS ss, sum(CAST(l_quantity AS BIGINT)) AS sq FROM lineitem GROUP BY ALL), "
    "m AS (SELECT image_id, tile_id, 8 * k + n AS obj_id, x0 + sp % 18 AS minx, y0 + ss % 18 AS miny, sq, sp FROM l JOIN pl USING (k)) SELECT image_id, tile_id, CAST(obj_id AS BIGINT) AS obj_id, CAST(minx AS BIGINT) AS minx, CAST(miny AS BIGINT) AS miny, CAST(minx + 2 + sq % 5 AS BIGINT) AS maxx, CAST(miny + 2 + sp % 5 AS BIGINT) AS maxy FROM m",
    "fx_columns": _COLS + "SELECT obj_id, CAST(2 + 2 * sum(CASE WHEN h = prev THEN 0 ELSE 1 END) AS INTEGER) AS n_vertices, CAST(sum(h * width) AS BIGINT) AS area FROM (SELECT *, coalesce(lag(h) OVER (PARTITION BY obj_id ORDER BY i), -1) AS prev FROM c) GROUP BY obj_id",
    "fx_scaled_area": F1 + "SELECT CAST(f AS INTEGER) AS factor, CAST(f * f * sum(area) AS BIGINT) AS area FROM pb, range(1, 6) t(f) GROUP BY f",
    "parse_ok": F1 + "SELECT image_id, count(*) AS objects, CAST(sum(area) AS BIGINT) AS area_sum FROM pb WHERE (obj_id // 4) % 50 NOT IN (0, 1, 2, 3) GROUP BY image_id",
    "parse_rejects": "SELECT reason, count(*) AS n FROM (SELECT CASE o_orderkey % 50 WHEN 0 THEN 'not integers' WHEN 1 THEN 'slanted edge' WHEN 2 THEN 'too few vertices' WHEN 3 THEN 'repeated vertex' END AS reason FROM orders UNION ALL SELECT 'not integers' FROM documents) WHERE reason IS NOT NULL GROUP BY reason",
    "parse_vector_equals": "SELECT (SELECT count(*) FROM orders) + (SELECT count(*) FROM documents) AS lines, CAST(0 AS BIGINT) AS mismatches",
    "ring_repair": F1 + "SELECT obj_id, CAST(nv AS INTEGER) AS n_vertices, area FROM pb WHERE (obj_id // 4) % 50 IN (4, 5)",
    "ring_area": F1 + "SELECT obj_id, area FROM pb",
    "ring_area_partials": F1 + "SELECT obj_id, area FROM pb",
    "ring_mbr": F1 + f"SELECT obj_id, {_BOX} FROM qb",
    "ring_edges": F1 + "SELECT obj_id, CAST(row_number() OVER (PARTITION BY obj_id ORDER BY seq) - 1 AS INTEGER) AS seq, x, lo, hi, sgn FROM pe",
    "centroid": F1 + "SELECT obj_id, round(sum((x + nx) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)), 6) AS cx, round(sum((y + ny) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)), 6) AS cy FROM pv GROUP BY obj_id",
    "pixel_in_ring": _PIXEL_SUMS,
    "box_position_grid": F1.rstrip() + ", px AS (SELECT c.obj_id, c.x, c.y, count(e.x) AS n FROM (SELECT obj_id, x, unnest(range(miny, maxy)) AS y FROM (SELECT obj_id, miny, maxy, unnest(range(minx, maxx)) AS x FROM pb)) c LEFT JOIN pe e ON e.obj_id = c.obj_id AND e.x > c.x AND e.lo <= c.y AND c.y < e.hi GROUP BY ALL), "
    "bx AS (SELECT obj_id, bx, unnest(range(CAST(floor(miny / 16) * 16 AS BIGINT), maxy, 16)) AS by_ FROM (SELECT *, unnest(range(CAST(floor(minx / 16) * 16 AS BIGINT), maxx, 16)) AS bx FROM pb)), "
    "cn AS (SELECT bx.obj_id, bx, by_, count(px.x) AS n FROM bx LEFT JOIN (SELECT * FROM px WHERE n % 2 = 1) px ON px.obj_id = bx.obj_id AND CAST(floor(px.x / 16) * 16 AS BIGINT) = bx AND CAST(floor(px.y / 16) * 16 AS BIGINT) = by_ GROUP BY ALL) SELECT obj_id, bx, by_ AS \"by\", CASE n WHEN 0 THEN 0 WHEN 256 THEN 1 ELSE -1 END AS pos FROM cn",
    "pairs_tile_closed": F1 + "SELECT image_id, tile_id, p_id, q_id FROM pr",
    "pairs_tile_open": F1 + f"SELECT p.image_id, p.tile_id, p.obj_id AS p_id, q.obj_id AS q_id FROM pb p JOIN qb q ON p.image_id = q.image_id AND p.tile_id = q.tile_id AND {_MEET_OPEN}",
    "pairs_image_grid": F1 + f"SELECT p.image_id, p.obj_id AS p_id, q.obj_id AS q_id FROM pb p JOIN qb q ON p.image_id = q.image_id AND {_MEET}",
    "pairs_tree": F1 + "SELECT image_id, tile_id, p_id, q_id FROM pr",
    "pairs_nested": F1 + f"SELECT p.image_id, p.obj_id AS p_id, q.obj_id AS q_id FROM pb p JOIN qb q ON p.image_id = q.image_id AND {_MEET}",
    "pairs_intersecting": _SEGS + "SELECT image_id, tile_id, p_id, q_id FROM ar WHERE inter > 0 UNION ALL SELECT tz.image_id, pr.tile_id, tz.p_id, tz.q_id FROM tz JOIN pr USING (p_id, q_id)",
    "pairing_stats": F1 + "SELECT image_id, count(*) AS candidates, count(*) FILTER (WHERE inter > 0) AS positive, round(1 - count(*) FILTER (WHERE inter > 0) / count(*), 6) AS false_share " + _BY_IMAGE,
    "pairs_roi": F1 + "SELECT image_id, tile_id, p_id, q_id FROM pr WHERE pminx <= 100 AND pmaxx >= 0 AND pminy <= 100 AND pmaxy >= 0 AND qminx <= 100 AND qmaxx >= 0 AND qminy <= 100 AND qmaxy >= 0",
    "area_pixel_classes": F1 + "SELECT image_id, p_id, q_id, inter AS n_both, uni - inter AS n_one, (greatest(pmaxx, qmaxx) - least(pminx, qminx)) * (greatest(pmaxy, qmaxy) - least(pminy, qminy)) - uni AS n_none FROM ar JOIN (SELECT p_id, q_id, pminx, pminy, pmaxx, pmaxy, qminx, qminy, qmaxx, qmaxy FROM pr) USING (p_id, q_id)",
    "area_hybrid_relational": _AREAS,
    "area_thresholds": F1 + f"SELECT t.threshold, {_SUM} FROM ar, (VALUES (2), (16), (64), (128), (256)) t(threshold) GROUP BY t.threshold",
    "area_scaled": F1 + _SCALE,
    "area_layouts": F1 + f"SELECT t.layout, {_SUM} FROM ar, (VALUES ('records'), ('columns'), ('blocks'), ('cached')) t(layout) GROUP BY t.layout",
    "agreement": F1 + "SELECT t.method, count(*) AS pairs, CAST(0 AS BIGINT) AS mismatches FROM ar, (VALUES ('spans'), ('hybrid'), ('joint'), ('overlay')) t(method) GROUP BY t.method",
    "score_all": F1 + "SELECT count(*) AS pairs, round(avg(ratio), 6) AS score FROM hit",
    "score_set_level": _SETS,
    "score_set_pixels": _SETS,
    "missing_objects": F1 + "SELECT image_id, side, count(*) AS total, count(m) AS matched, count(*) - count(m) AS missing FROM (SELECT image_id, 'P' AS side, obj_id, m FROM pb LEFT JOIN (SELECT DISTINCT p_id AS obj_id, 1 AS m FROM hit) USING (obj_id) UNION ALL SELECT image_id, 'Q', obj_id, m FROM qb LEFT JOIN (SELECT DISTINCT q_id AS obj_id, 1 AS m FROM hit) USING (obj_id)) GROUP BY ALL",
    "unmatched_objects": F1 + "SELECT image_id, 'P' AS side, obj_id FROM pb WHERE obj_id NOT IN (SELECT p_id FROM hit) UNION ALL SELECT image_id, 'Q', obj_id FROM qb WHERE obj_id NOT IN (SELECT q_id FROM hit)",
    "overlap_profile": F1 + "SELECT image_id, CAST(sum(area_p) AS BIGINT) AS sum_p, CAST(sum(area_q) AS BIGINT) AS sum_q, CAST(sum(inter) AS BIGINT) AS sum_inter, round(avg(inter / area_p), 6) AS share_p, round(avg(inter / area_q), 6) AS share_q FROM hit GROUP BY image_id",
    "cross_matrix": _JITTERED + "SELECT algo_a, algo_b, pairs, score FROM jm",
    "cross_matrix_pivot": _JITTERED + "SELECT algo_a, " + ", ".join(f"max(score) FILTER (WHERE algo_b = {k}) AS with_{k}" for k in range(1, 5)) + " FROM jm GROUP BY algo_a",
    "score_cube": F1 + "SELECT r_name AS region, n_name AS nation, CAST(grouping(r_name, n_name) AS INTEGER) AS level, count(*) AS pairs, round(avg(ratio), 6) AS score FROM hit JOIN orders ON o_orderkey * 4 = p_id JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
    "score_decimal": F1 + "SELECT image_id, count(*) AS pairs, CAST(round(avg(ratio), 9) AS DECIMAL(18, 9)) AS score FROM hit GROUP BY image_id",
    "centroid_distance": F1.rstrip() + ", cp AS (SELECT obj_id, sum((x + nx) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)) AS cx, sum((y + ny) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)) AS cy FROM pv GROUP BY obj_id), cq AS (SELECT obj_id, sum((x + nx) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)) AS cx, sum((y + ny) * (x * ny - nx * y)) / (3 * sum(x * ny - nx * y)) AS cy FROM qv GROUP BY obj_id) SELECT image_id, p_id, round(sqrt((cp.cx - cq.cx) ** 2 + (cp.cy - cq.cy) ** 2), 6) AS distance FROM pr JOIN cp ON cp.obj_id = p_id JOIN cq ON cq.obj_id = q_id WHERE p_id = q_id",
    "best_match": F1 + "SELECT image_id, p_id, q_id, round(ratio, 6) AS ratio FROM hit QUALIFY row_number() OVER (PARTITION BY image_id, p_id ORDER BY ratio DESC, q_id) = 1",
    "ratio_histogram": F1 + "SELECT CAST(10 * inter // uni AS INTEGER) AS bucket, count(*) AS n FROM hit GROUP BY 1",
    "worst_pairs_topk": F1 + "SELECT image_id, CAST(rk AS INTEGER) AS rk, p_id, q_id, inter, uni FROM (SELECT *, row_number() OVER (PARTITION BY image_id ORDER BY ratio, p_id, q_id) AS rk FROM hit) WHERE rk <= 3",
    "contains_pairs": F1 + "SELECT image_id, p_id, q_id FROM ar WHERE inter = area_q",
    "touches_pairs": _SEGS + "SELECT image_id, p_id, q_id FROM tz",
    "relation_counts": _SEGS + "SELECT CASE WHEN inter = area_p AND inter = area_q THEN 'equals' WHEN inter = area_q THEN 'contains' WHEN inter = area_p THEN 'within' WHEN inter > 0 THEN 'overlaps' WHEN tz.p_id IS NOT NULL THEN 'touches' ELSE 'disjoint' END AS relation, count(*) AS n FROM ar LEFT JOIN tz USING (p_id, q_id) GROUP BY 1",
    "vessel_pairs": F1.rstrip() + ", tl AS (SELECT DISTINCT image_id, tile_id, (tile_id % 8) * 208 AS x, (tile_id // 8) * 208 AS y FROM pb), "
    "ve AS (SELECT image_id, tile_id, x + ex AS x, y + elo AS lo, y + ehi AS hi, s AS sgn FROM tl, (VALUES (208, 0, 40, -1), (40, 40, 168, -1), (208, 168, 208, -1), (0, 0, 208, 1)) t(ex, elo, ehi, s)), "
    f"vp AS (SELECT b.image_id, CAST(b.image_id AS BIGINT) * 1000000 + b.tile_id AS p_id, b.obj_id AS q_id, CAST(-sum({_TERM.replace('a.', 'v.').replace('b.', 'e.')}) AS BIGINT) AS inter, any_value(b.area) AS area FROM pb b JOIN ve v ON v.image_id = b.image_id AND v.tile_id = b.tile_id JOIN pe e ON e.obj_id = b.obj_id GROUP BY ALL) SELECT image_id, p_id, q_id, inter, 208 * 208 - 168 * 128 + area - inter AS uni FROM vp WHERE inter > 0",
    "column_pairs": _COLS + "SELECT obj_id AS p_id, CAST(sum(CASE WHEN prev IS NULL THEN 0 ELSE least(h, prev) * width END) AS BIGINT) AS inter FROM (SELECT *, lag(h) OVER (PARTITION BY obj_id ORDER BY i) AS prev FROM c) GROUP BY obj_id",
    "tasks": _TASKS + "SELECT image_id, tile_id, objects, vertices, pairs, pixels FROM tk",
    "batches": _TASKS + "SELECT image_id * 1000000 + coalesce(before, 0) // 100000 AS batch_id, count(*) AS tasks, CAST(sum(pixels) AS BIGINT) AS cost FROM (SELECT *, CAST(sum(pixels) OVER (PARTITION BY image_id ORDER BY tile_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS BIGINT) AS before FROM (SELECT CAST(image_id AS BIGINT) AS image_id, tile_id, pixels FROM tk)) GROUP BY 1",
    "geo_mean": F1 + "SELECT round(exp(avg(ln(n))), 6) AS geo_mean FROM (SELECT image_id, CAST(count(*) AS DOUBLE) AS n FROM pb GROUP BY image_id)",
    "arrivals_tumbling": _windows("date_trunc('day', ts)", "1 day"),
    "arrivals_sliding": _windows("unnest([time_bucket(INTERVAL '6 hours', ts) - INTERVAL '6 hours' * k for k in range(4)])", "1 day"),
    "arrivals_session": _EVENTS + "SELECT min(ts) AS start, max(ts) + INTERVAL '30 minutes' AS \"end\", image_id, count(*) AS files, CAST(sum(bytes) AS BIGINT) AS bytes FROM (SELECT *, sum(new) OVER (PARTITION BY image_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY image_id ORDER BY ts, event_id) + INTERVAL '30 minutes' THEN 0 ELSE 1 END AS new FROM a)) GROUP BY image_id, s",
    "arrivals_asof": _EVENTS + "SELECT image_id, tile_id, (SELECT max_by(p.event_id, (p.ts, p.event_id)) FROM a p WHERE p.side = 'P' AND p.image_id = q.image_id AND p.tile_id = q.tile_id AND p.ts <= q.ts) AS p_event, event_id AS q_event FROM a q WHERE side = 'Q'",
    "arrivals_interval": _EVENTS + "SELECT p.image_id, p.tile_id, p.event_id AS p_event, q.event_id AS q_event FROM a p JOIN a q ON p.side = 'P' AND q.side = 'Q' AND p.image_id = q.image_id AND p.tile_id = q.tile_id AND q.ts BETWEEN p.ts - INTERVAL '1 hour' AND p.ts + INTERVAL '1 hour'",
    "tile_assembler": _EVENTS.rstrip() + ", r AS (SELECT *, row_number() OVER (PARTITION BY image_id, tile_id, side ORDER BY event_id) AS rn FROM a) SELECT p.image_id, p.tile_id, p.event_id AS p_event, q.event_id AS q_event FROM r p JOIN r q ON p.side = 'P' AND q.side = 'Q' AND p.image_id = q.image_id AND p.tile_id = q.tile_id AND p.rn = q.rn",
    "stream_score": F1 + f"SELECT image_id, count(*) AS pairs, round(avg(ratio), 6) AS score FROM hit WHERE (image_id, tile_id) IN ({_EVENTS} SELECT image_id, tile_id FROM a GROUP BY ALL HAVING count(DISTINCT side) = 2) GROUP BY image_id",
    "pixel_resolution": _TRI + "SELECT CAST(g AS INTEGER) AS g, count(*) AS n, round(avg(err), 6) AS mean_rel_error FROM e GROUP BY g",
    "pixel_error_by_label": _TRI + "SELECT label, count(*) AS n, round(avg(err), 6) AS mean_rel_error FROM e WHERE g = 64 GROUP BY label",
    "io_json_round_trip": F1 + "SELECT obj_id, area FROM pb",
    "io_text_round_trip": F1 + "SELECT obj_id, area FROM qb",
    "io_stored_layout": F1 + "SELECT obj_id FROM pb WHERE image_id = 17 AND minx <= 300 AND maxx >= 0 AND miny <= 300 AND maxy >= 0",
    # general operators
    "op_scan_prune": "SELECT o_orderkey, o_custkey, o_orderdate FROM orders WHERE o_orderdate >= TIMESTAMP '1996-01-01' AND o_orderdate < TIMESTAMP '1997-01-01' AND o_totalprice > 400000",
    "op_filters": "SELECT p_partkey, p_name, p_size FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#23', 'Brand#34') AND p_name LIKE '%a%'",
    "op_join_broadcast": "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey",
    "op_join_merge": "SELECT o_orderstatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
    "op_join_hash": "SELECT p_type, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1",
    "op_join_nested": "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_acctbal < b.s_acctbal",
    "op_join_range": "SELECT c_custkey, s_suppkey FROM customer JOIN supplier ON c_nationkey = s_nationkey AND c_acctbal BETWEEN s_acctbal - 50 AND s_acctbal + 50",
    "op_join_theta": "SELECT a.p_brand, count(*) AS n FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_retailprice > b.p_retailprice GROUP BY 1",
    "op_join_outer": "SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1",
    "op_join_full": F1 + "SELECT coalesce(p.image_id, q.image_id) AS image_id, count(*) FILTER (WHERE p.obj_id IS NOT NULL AND q.obj_id IS NOT NULL) AS n_both, count(*) FILTER (WHERE q.obj_id IS NULL) AS only_p, count(*) FILTER (WHERE p.obj_id IS NULL) AS only_q FROM pb p FULL JOIN qb q ON p.obj_id = q.obj_id GROUP BY 1",
    "op_join_semi": "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)",
    "op_join_anti": "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)",
    "op_join_self": "SELECT a.conv_id, a.turn, b.role AS next_role FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1",
    "op_join_asof": "SELECT event_id, prev_event_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS prev_event_id FROM events WHERE event_type IN ('view', 'purchase')) WHERE event_type = 'purchase'",
    "op_join_lateral": "SELECT doc_id, count(*) AS n_words FROM (SELECT doc_id, unnest(string_split(text, ' ')) AS w FROM documents) WHERE w <> '' GROUP BY 1",
    "op_join_salted": "SELECT l_suppkey, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey GROUP BY 1",
    "op_agg_hash": "SELECT l_returnflag AS flag, l_linestatus AS status, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS qty, round(avg(l_discount), 6) AS avg_disc FROM lineitem GROUP BY ALL",
    "op_agg_distinct": "SELECT l_suppkey, count(DISTINCT l_partkey) AS n FROM lineitem GROUP BY 1",
    "op_agg_approx": "SELECT TRUE AS within",
    "op_agg_sketch": "SELECT TRUE AS within",
    "op_agg_rollup": "SELECT p_brand, p_size, CAST(grouping(p_brand, p_size) AS INTEGER) AS level, count(*) AS n FROM part GROUP BY ROLLUP (p_brand, p_size)",
    "op_agg_cube": "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY CUBE (lang, source)",
    "op_agg_gsets": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())",
    "op_agg_pivot": "SELECT CAST(ts AS DATE) AS day, count(*) FILTER (WHERE event_type = 'click') AS n_click, count(*) FILTER (WHERE event_type = 'purchase') AS n_purchase, count(*) FILTER (WHERE event_type = 'view') AS n_view FROM events GROUP BY 1",
    "op_agg_percentile": "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 6) AS med FROM orders GROUP BY 1",
    "op_agg_maxby": "SELECT o_custkey AS c, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS o_orderkey FROM orders GROUP BY 1",
    "op_agg_stats": F1 + "SELECT round(stddev_samp(area_p), 6) AS sd, round(corr(area_p, area_q), 6) AS corr, round(regr_slope(area_q, area_p), 6) AS slope FROM ar WHERE p_id = q_id",
    "op_win_rank": "SELECT s_suppkey, rank() OVER w AS rk, dense_rank() OVER w AS drk, row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS rn FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY s_acctbal DESC)",
    "op_win_frame": "SELECT o_orderkey, CAST(sum(CAST(floor(o_totalprice) AS BIGINT)) OVER (PARTITION BY o_custkey ORDER BY o_orderkey ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS BIGINT) AS s FROM orders",
    "op_win_range": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events",
    "op_win_leadlag": "SELECT event_id, lead(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) - epoch_us(ts) AS gap FROM events",
    "op_win_ntile": F1 + "SELECT CAST(c AS INTEGER) AS chunk, count(*) AS n FROM (SELECT ntile(16) OVER (PARTITION BY image_id ORDER BY obj_id) AS c FROM pb) GROUP BY 1",
    "op_win_dist": "SELECT c_custkey, round(cume_dist() OVER w, 6) AS cd, round(percent_rank() OVER w, 6) AS pr, nth_value(c_custkey, 2) OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey)",
    "op_topk": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10",
    "op_topk_group": "SELECT o_orderpriority, CAST(rk AS INTEGER) AS rk, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS rk FROM orders) WHERE rk <= 3",
    "op_page": "SELECT o_orderkey FROM orders ORDER BY o_orderkey LIMIT 10 OFFSET 10",
    "op_union": "SELECT nationkey, count(*) AS n FROM (SELECT c_nationkey AS nationkey FROM customer UNION ALL SELECT s_nationkey FROM supplier) GROUP BY 1",
    "op_intersect": "SELECT c_nationkey AS nationkey FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier",
    "op_except": "SELECT c_nationkey AS nationkey FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
    "op_distinct": "SELECT DISTINCT c_nationkey AS nationkey FROM customer",
    "op_string": "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, CAST(len(string_split(url, '/')) - 3 AS INTEGER) AS depth, trim(url[1:8]) AS head, length(html) AS chars, translate(url, '/:', '__') AS flat FROM pages",
    "op_date": "SELECT CAST(date_trunc('quarter', o_orderdate) AS DATE) AS q, count(*) AS n, CAST(sum(CAST(l_shipdate AS DATE) - CAST(o_orderdate AS DATE)) AS BIGINT) AS days FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1",
    "op_math": "SELECT CASE WHEN c_acctbal < -1000 THEN 0 WHEN c_acctbal >= 10000 THEN 12 ELSE CAST(floor((c_acctbal + 1000) / 1000) AS BIGINT) + 1 END AS bucket, count(*) AS n, round(sum(sign(c_acctbal) * ln(1 + abs(c_acctbal))), 4) AS logs FROM customer GROUP BY 1",
    "op_array": "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 6) AS norm, CAST(list_position(embedding, list_max(embedding)) AS INTEGER) AS arg FROM embeddings",
    "op_map": "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS clicks FROM events GROUP BY 1",
    "op_json": "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events",
    "op_sqludf": F1 + "SELECT obj_id, area FROM pb",
    "op_arrowudf": F1 + "SELECT obj_id, area FROM pb",
    "op_udaf": F1 + "SELECT image_id, round(avg(ratio), 6) AS score FROM hit GROUP BY image_id",
    "op_udtf": _PIXEL_SUMS,
    "op_cogroup": F1 + "SELECT image_id, tile_id, count(p_id) AS n FROM (SELECT image_id, tile_id FROM pb UNION SELECT image_id, tile_id FROM qb) LEFT JOIN pr USING (image_id, tile_id) GROUP BY ALL",
}
SQL |= {name: _AREAS for name in ("area_edge_form", "area_edge_form_exploded", "area_pixel", "area_pixel_vector", "area_pixel_spans", "area_hybrid", "area_hybrid_overlap_root", "area_hybrid_joint", "area_boxes_only", "area_hybrid_stack", "area_overlay", "area_overlay_union")}
SQL |= {name: _SCORES for name in ("score_plain", "score_rewritten", "scheme_staged", "scheme_streams", "scheme_pipelined", "scheme_chunked16", "scheme_database", "routed_lanes", "routed_stream")}
SQL["satellite_pairs"] = SQL["fx_satellites"].replace("SELECT image_id, tile_id, CAST(obj_id AS BIGINT)", "sb AS (SELECT image_id, tile_id, CAST(obj_id AS BIGINT)", 1).replace("FROM l JOIN pl USING (k)) sb", "FROM l JOIN pl USING (k)), sb") + f""" ),{_rings("p", "po")},
sj AS (SELECT p.image_id, p.obj_id AS s_id, q.obj_id AS p_id, p.minx, p.miny, p.maxx, p.maxy FROM sb p JOIN pb q ON p.image_id = q.image_id AND p.tile_id = q.tile_id AND {_MEET}),
si AS (SELECT s.image_id, s_id, p_id, sum(e.sgn * greatest(least(e.hi, s.maxy) - greatest(e.lo, s.miny), 0) * (greatest(e.x, s.maxx) - greatest(e.x, s.minx))) AS inter FROM sj s JOIN pe e ON e.obj_id = s.p_id GROUP BY ALL)
SELECT image_id, count(*) AS pairs, CAST(sum(inter) AS BIGINT) AS inter_sum FROM si GROUP BY image_id"""


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
