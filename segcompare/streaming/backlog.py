"""Live routing between two lanes: after each micro-batch the cut moves towards the lane that has less to do.

Pairs whose joint box is cheap go to the native lane, the others to the vector lane. A lane's backlog is the time
its share of the last batch took; where the vector lane's is the larger one by a margin the cut rises, so that more
pairs go native, and the other way round. `Backlog` listens to a query's progress and tells whether input waits.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.listener import QueryProgressEvent, QueryStartedEvent, QueryTerminatedEvent, StreamingQueryListener

from ..kernels import native, vector
from ..operators import similarity
from ..plans.pipeline import route_lane
from ..storage import new_path


@dataclass
class Cut:
    """The pixels up to which a pair goes native; `margin` keeps it from moving to and fro."""

    pixels: int = 400
    least: int = 16
    most: int = 1 << 20
    step: float = 2.0
    margin: float = 1.25
    moves: list[tuple[int, int]] = field(default_factory=list)

    def move(self, batch_id: int, native_seconds: float, vector_seconds: float) -> None:
        if vector_seconds > self.margin * native_seconds:
            self.pixels = min(self.most, int(self.pixels * self.step))
        elif native_seconds > self.margin * vector_seconds:
            self.pixels = max(self.least, int(self.pixels / self.step))
        self.moves.append((batch_id, self.pixels))


class Backlog(StreamingQueryListener):
    """Rows that came and were worked off per second, batch by batch; `full` where more comes than is worked off."""

    def __init__(self) -> None:
        self.rates: list[tuple[int, float, float]] = []

    def onQueryStarted(self, event: QueryStartedEvent) -> None:
        pass

    def onQueryProgress(self, event: QueryProgressEvent) -> None:
        p = event.progress
        self.rates.append((p.numInputRows, float(p.inputRowsPerSecond or 0), float(p.processedRowsPerSecond or 0)))

    def onQueryTerminated(self, event: QueryTerminatedEvent) -> None:
        pass

    @property
    def full(self) -> bool:
        return bool(self.rates) and self.rates[-1][1] > self.rates[-1][2] > 0

    @property
    def empty(self) -> bool:
        return not self.rates or self.rates[-1][0] == 0


def routed_scores(pairs: DataFrame, cut: Cut | None = None, files: int = 4) -> DataFrame:
    """Scores per image of pairs that arrive in `files` micro-batches; the cut moves between them."""
    spark = pairs.sparkSession
    cut = cut or Cut()
    source, out, checkpoint = (new_path(spark, n) for n in ("pairs", "routed", "progress"))
    pairs.repartition(files).write.parquet(source)
    schema = spark.read.parquet(source).schema
    seen: list[int] = []

    def lane(df: DataFrame, name: str, batch_id: int) -> float:
        own = route_lane(df, cut.pixels).filter(F.col("lane") == name)
        areas = native.areas_only(native.edge_form_areas(own) if name == "native" else vector.hybrid_areas(own))
        began = time.perf_counter()
        similarity.partial_scores(areas).write.mode("overwrite").parquet(f"{out}/batch={batch_id}/lane={name}")
        return time.perf_counter() - began

    def sink(df: DataFrame, batch_id: int) -> None:
        taken = {name: lane(df, name, batch_id) for name in ("native", "vector")}
        cut.move(batch_id, taken["native"], taken["vector"])
        seen.append(batch_id)

    listener = Backlog()
    spark.streams.addListener(listener)
    try:
        stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(source)
        stream.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.streams.removeListener(listener)
    kind = "image_id int, ratio_sum double, pairs bigint"
    paths = [f"{out}/batch={b}/lane={name}" for b in sorted(set(seen)) for name in ("native", "vector")]
    parts = spark.read.schema(kind).parquet(*paths) if paths else spark.createDataFrame([], kind)
    return similarity.merged_scores(parts).select("image_id", "pairs", F.round("score", 6).alias("score"))
