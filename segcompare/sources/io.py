"""Readers and sinks: polygon text files, JSON rings, a generated source, stored layout, scores, WKB."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions import geometry as g
from ..operators.index import hilbert_sorted
from ..schema import RING
from .fixtures import SHAPES


def read_polygon_text(spark: SparkSession, path: str) -> DataFrame:
    """Lines of text files image_algo_tile.txt in the parser's input form; the file's name is the tile's provenance."""
    lines = spark.read.text(path).withColumn("file", F.input_file_name())
    part = lambda k: F.regexp_extract("file", r"(\d+)_(\w+?)_(\d+)\.txt", k)
    return lines.select(part(1).try_cast("int").alias("image_id"), part(2).alias("algo"), part(3).try_cast("bigint").alias("tile_id"), F.monotonically_increasing_id().alias("line_no"), F.col("value").alias("text"))


def read_rings_json(lines: DataFrame, column: str = "value") -> DataFrame:
    """JSON objects with image_id, tile_id, obj_id and ring, by the declared schema; unreadable ones keep their text in `corrupt`."""
    schema = f"image_id int, tile_id bigint, algo string, obj_id bigint, ring {RING}, corrupt string"
    read = F.from_json(F.col(column), schema, {"columnNameOfCorruptRecord": "corrupt"})
    return lines.select(read.alias("r")).select("r.*")


def rings_json(objects: DataFrame) -> DataFrame:
    return objects.select(F.to_json(F.struct("image_id", "tile_id", "algo", "obj_id", "ring")).alias("value"))


def write_objects(objects: DataFrame, path: str) -> None:
    """Partitioned by image, sorted by tile and Hilbert key, so that row groups can be skipped by box and tile."""
    hilbert_sorted(objects).repartition("image_id", F.col("tile_id") % 64).sortWithinPartitions("image_id", "tile_id", "hilbert").write.mode("overwrite").partitionBy("image_id").parquet(path)


def write_scores(scores: DataFrame, path: str, batch_id: int = 0, format: str = "parquet") -> None:  # noqa: A002
    """Idempotent by batch: a batch that is written again replaces its own folder."""
    scores.write.mode("overwrite").format(format).save(f"{path}/batch={batch_id}")


def ring_to_wkb(ring):
    """Little-endian well-known binary of a closed ring."""
    closed = F.concat(ring, F.slice(ring, 1, 1))

    def little(i, size: int):
        digits = F.lpad(F.hex(i), size * 2, "0")
        return F.concat(*(F.substring(digits, 2 * k - 1, 2) for k in range(size, 0, -1)))

    def double(v):
        """Hex of a non-negative whole number below 2 ** 52 as an IEEE double, low byte first."""
        e = F.floor(F.log2(F.greatest(v, F.lit(1)).cast("double"))).cast("int")
        exponent = F.when(F.call_function("shiftleft", F.lit(1).cast("bigint"), e) > v, e - 1).otherwise(e)
        fraction = F.call_function("shiftleft", v - F.call_function("shiftleft", F.lit(1).cast("bigint"), exponent), 52 - exponent)
        bits = F.when(v == 0, F.lit(0).cast("bigint")).otherwise(F.call_function("shiftleft", (exponent + 1023).cast("bigint"), F.lit(52)) + fraction)
        return little(bits, 8)

    points = F.array_join(F.transform(closed, lambda p: F.concat(double(p["x"]), double(p["y"]))), "")
    head = F.concat(F.lit("01"), F.lit("03000000"), F.lit("01000000"), little(F.size(closed).cast("bigint"), 4))
    return F.unhex(F.concat(head, points))


class _Tile(InputPartition):
    def __init__(self, image: int, tile: int):
        super().__init__((image, tile))
        self.image, self.tile = image, tile


def _cell(tile: int, k: int) -> list[dict[str, int]]:
    """The ring in place k of a tile."""
    x0, y0, s = (tile % 8) * 208 + (k % 8) * 26, (tile // 8) * 208 + (k // 8 % 8) * 26, 1 + k % 3
    return [{"x": x0 + s * x, "y": y0 + s * y} for x, y in SHAPES[(k + tile) % len(SHAPES)]]


class _CellReader(DataSourceReader):
    def __init__(self, options):
        self.images, self.tiles, self.cells = (int(options.get(k, v)) for k, v in (("images", 1), ("tiles", 4), ("cells", 64)))

    def partitions(self):
        return [_Tile(i, t) for i in range(self.images) for t in range(self.tiles)]

    def read(self, partition: _Tile) -> Iterator[tuple]:
        for k in range(self.cells):
            yield partition.image, partition.tile, "gen", partition.tile * self.cells + k, _cell(partition.tile, k)


class CellSource(DataSource):
    """spark.read.format("segcells").option("images", ...): generated objects, one partition per tile."""

    @classmethod
    def name(cls):
        return "segcells"

    def schema(self):
        return f"image_id int, tile_id bigint, algo string, obj_id bigint, ring {RING}"

    def reader(self, schema):
        return _CellReader(self.options)


def generated(spark: SparkSession, images: int = 1, tiles: int = 4, cells: int = 64) -> DataFrame:
    spark.dataSource.register(CellSource)
    return spark.read.format("segcells").option("images", images).option("tiles", tiles).option("cells", cells).load()


def generated_at(places: DataFrame, cells: int = 64) -> DataFrame:
    """Places (image_id, tile_id, cell) -> the objects that the source generates there, the rows read by Spark."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("x", pa.int64()), ("y", pa.int64())]))
        for batch in batches:
            image, tile, cell = (c.to_pylist() for c in batch.columns)
            rings = pa.array([_cell(t, k) for t, k in zip(tile, cell, strict=True)], kind)
            ids = pa.array([t * cells + k for t, k in zip(tile, cell, strict=True)], pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(image, pa.int32()), pa.array(tile, pa.int64()), pa.array(["gen"] * len(tile)), ids, rings], names=["image_id", "tile_id", "algo", "obj_id", "ring"])

    return places.select("image_id", "tile_id", "cell").mapInArrow(run, f"image_id int, tile_id bigint, algo string, obj_id bigint, ring {RING}")


def valid_only(objects: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(valid, rejected with reason)."""
    judged = objects.withColumn("reason", g.validity(F.col("ring")))
    return judged.filter("reason IS NULL").drop("reason"), judged.filter("reason IS NOT NULL")
