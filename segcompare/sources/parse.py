"""Text of one polygon per line -> rings; faulty lines go to a side table with the reason.

A line is an id and the coordinates x y x y ..., all integers. Repairs: a closing vertex and collinear
vertices are dropped, clockwise rings are turned. Two implementations give the same rows: column expressions
(lane "native") and Arrow kernels (lane "vector").
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import geometry as g
from ..schema import RAW, RING

_WORKED = f"image_id int, algo string, tile_id bigint, line_no bigint, text string, obj_id bigint, ring {RING}, reason string"


def _native(raw: DataFrame) -> DataFrame:
    names = ["image_id", "algo", "tile_id", "line_no", "text"]
    tokens = F.split(F.trim(F.regexp_replace(F.coalesce("text", F.lit("")), r"[ \t\n\r\x0B\f]+", " ")), " ")
    rows = g.once(raw.select(*names), tokens=tokens)
    rows = g.once(rows, plain=F.forall("tokens", lambda t: t.rlike(r"^-?[0-9]{1,15}$")))
    rows = g.once(rows, n=F.when(F.col("plain"), F.transform("tokens", lambda t: t.try_cast("bigint"))))
    count = F.size("n")
    even = (count >= 3) & (count % 2 == 1)
    given = F.transform(F.sequence(F.lit(1), count - 2, F.lit(2)), lambda k: F.struct(F.get("n", k).alias("x"), F.get("n", k + 1).alias("y")))
    rows = g.once(rows, given=F.when(F.col("plain") & even, given))
    rows = g.once(rows, bare=F.when(F.col("given").isNotNull(), g.opened(F.col("given"))))
    early = F.when(~F.col("plain"), "not integers").when(~even, "odd count")
    rows = g.once(rows, reason=F.coalesce(early, g.validity(F.col("bare"))))
    rows = g.once(rows, obj_id=F.get("n", F.lit(0)), valid=F.when(F.col("reason").isNull(), F.col("bare")))
    return g.repaired(rows, "valid", "ring").select(*names, "obj_id", "ring", "reason")


def _ring_of(text: str | None) -> tuple[int | None, list[tuple[int, int]] | None, str | None]:
    """(id, repaired ring, reason) of a line by a state machine over its tokens."""
    tokens = (text or "").split(" ") if not any(c in (text or "") for c in "\t\n\r\x0b\x0c") else (text or "").translate({9: " ", 10: " ", 11: " ", 12: " ", 13: " "}).split(" ")
    tokens = [t for t in tokens if t] or [""]
    numbers = []
    for t in tokens:
        digits = t[1:] if t[:1] == "-" else t
        if not (1 <= len(digits) <= 15 and digits.isascii() and digits.isdigit()):
            return None, None, "not integers"
        numbers.append(int(t))
    if len(numbers) < 3 or len(numbers) % 2 == 0:
        return numbers[0], None, "odd count"
    ring = list(zip(numbers[1::2], numbers[2::2], strict=True))
    if len(ring) > 1 and ring[0] == ring[-1]:
        ring.pop()
    if len(ring) < 4:
        return numbers[0], None, "too few vertices"
    steps = [(b[0] - a[0], b[1] - a[1]) for a, b in zip(ring, ring[1:] + ring[:1], strict=True)]
    if (0, 0) in steps:
        return numbers[0], None, "repeated vertex"
    if any(x and y for x, y in steps):
        return numbers[0], None, "slanted edge"
    twice = sum(a[0] * b[1] - b[0] * a[1] for a, b in zip(ring, ring[1:] + ring[:1], strict=True))
    if not twice:
        return numbers[0], None, "no area"
    if _crosses_itself(ring):
        return numbers[0], None, "crosses itself"
    corners = [v for v, before, after in zip(ring, steps[-1:] + steps[:-1], steps, strict=True) if bool(before[0]) != bool(after[0])]
    return numbers[0], corners[::-1] if twice < 0 else corners, None


def _crosses_itself(ring: list[tuple[int, int]]) -> bool:
    v = np.array(ring, np.int64)
    lo, hi = np.minimum(v, np.roll(v, -1, 0)), np.maximum(v, np.roll(v, -1, 0))
    up = lo[:, 0] == hi[:, 0]
    flat_lo, flat_hi = lo[~up], hi[~up]
    return any(((flat_lo[:, 0] < x) & (x < flat_hi[:, 0]) & (a < flat_lo[:, 1]) & (flat_lo[:, 1] < b)).any() for x, a, b in zip(lo[up, 0], lo[up, 1], hi[up, 1], strict=True))


def _vector(raw: DataFrame) -> DataFrame:
    kind = pa.list_(pa.struct([("x", pa.int64()), ("y", pa.int64())]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [_ring_of(t) for t in batch.column(4).to_pylist()]
            sizes = np.array([len(r) if r is not None else 0 for _, r, _ in found], np.int64)
            flat = np.array([v for _, r, _ in found if r is not None for v in r], np.int64).reshape(-1, 2)
            offsets = pa.array(np.r_[0, np.cumsum(sizes)].astype(np.int32), mask=np.r_[np.array([r is None for _, r, _ in found], bool), False])
            rings = pa.ListArray.from_arrays(offsets, pa.StructArray.from_arrays([pa.array(flat[:, 0]), pa.array(flat[:, 1])], ["x", "y"])).cast(kind)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array([i for i, _, _ in found], pa.int64()), rings, pa.array([w for _, _, w in found], pa.string())], names=[*batch.schema.names, "obj_id", "ring", "reason"])

    return raw.select(*(c.split()[0] for c in RAW.split(", "))).mapInArrow(run, _WORKED)


def worked(raw: DataFrame, lane: str = "native") -> DataFrame:
    """Every line with its id, ring or reason."""
    return _native(raw) if lane == "native" else _vector(raw)


def parse_polygons(raw: DataFrame, lane: str = "native") -> tuple[DataFrame, DataFrame]:
    """(objects, rejects)."""
    rows = worked(raw, lane)
    objects = rows.filter("reason IS NULL").select("image_id", "tile_id", "algo", "obj_id", "ring")
    rejects = rows.filter("reason IS NOT NULL").select("image_id", "algo", "tile_id", "line_no", "text", "reason")
    return objects, rejects


def render(objects: DataFrame) -> DataFrame:
    """Objects as lines of text, the parser's inverse."""
    coords = F.transform("ring", lambda v: F.concat_ws(" ", v["x"].cast("string"), v["y"].cast("string")))
    return objects.select("image_id", "algo", "tile_id", F.col("obj_id").alias("line_no"), F.concat_ws(" ", F.col("obj_id").cast("string"), F.array_join(coords, " ")).alias("text"))
