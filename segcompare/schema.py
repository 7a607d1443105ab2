"""Declared schemas; nothing is inferred."""

from __future__ import annotations

VERTEX = "struct<x:bigint,y:bigint>"
RING = f"array<{VERTEX}>"
EDGES = "array<struct<x:bigint,lo:bigint,hi:bigint,sgn:int>>"
BOXES = "array<struct<x0:bigint,y0:bigint,x1:bigint,y1:bigint>>"
#: One segmented object of one result set.
OBJECTS = f"image_id int, tile_id bigint, algo string, obj_id bigint, ring {RING}"
RAW = "image_id int, algo string, tile_id bigint, line_no bigint, text string"
REJECTS = RAW + ", reason string"
#: A pair whose boxes meet, with both rings, so that an area kernel needs no further shuffle.
PAIRS = f"image_id int, p_id bigint, q_id bigint, ring_p {RING}, ring_q {RING}"
AREAS = "image_id int, p_id bigint, q_id bigint, inter bigint, uni bigint"
COUNTERS = "pixels bigint, boxes bigint, partitions bigint, max_level int"
