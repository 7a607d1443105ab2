"""The comparison as tiles arrive: windows, stream joins, a stateful assembler and running scores.

Timestamps without zone become UTC timestamps for the watermark and are cast back on output.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..kernels import native
from ..operators import pairing, similarity
from ..sources.fixtures import cells, tile_arrivals
from ..storage import new_path

def stage_arrivals(spark: SparkSession, sf_dir: str, files: int = 4) -> str:
    """Arrival records written as `files` files, one after another in order of arrival; returns their folder.

    A file stream takes files by their time of change, so the order of writing bounds how late a record comes.
    """
    path = new_path(spark, "arrivals")
    arrivals = tile_arrivals(spark, sf_dir).withColumns({c: F.col(c).cast("timestamp") for c in ("event_time", "arrival")})
    at = F.unix_micros("arrival")
    cuts = arrivals.agg(F.percentile_approx(at, [k / files for k in range(1, files)])).first()[0] or []
    bounds = [None, *sorted(set(cuts)), None]
    for lo, hi in zip(bounds, bounds[1:], strict=False):
        part = arrivals if lo is None else arrivals.filter(at > lo)
        part = part if hi is None else part.filter(at <= hi)
        part.coalesce(1).sortWithinPartitions("arrival", "event_id").write.mode("append").parquet(path)
    return path


def read_arrivals(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """The file stream; files per trigger bound the input buffer."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def run_to_end(stream: DataFrame, mode: str) -> DataFrame:
    """Runs a stream over all that has arrived and returns its result as a batch frame.

    Complete mode keeps the last batch; append keeps all batches, each in a folder of its own, so a batch that
    is written again replaces itself.
    """
    spark = stream.sparkSession
    out, checkpoint = new_path(spark, "stream"), new_path(spark, "progress")
    last = []

    def sink(df: DataFrame, batch_id: int) -> None:
        df.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")
        last.append(batch_id)

    query = stream.writeStream.foreachBatch(sink).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    if not last:
        return spark.createDataFrame([], stream.schema)
    if mode == "complete":
        return spark.read.schema(stream.schema).parquet(f"{out}/batch={last[-1]}")
    return spark.read.schema(stream.schema).parquet(*(f"{out}/batch={b}" for b in sorted(set(last))))


def _plain(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c, t in df.dtypes if t == "timestamp"})


def _windowed(make: Callable) -> Callable[[SparkSession, str], DataFrame]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        stream = read_arrivals(spark, stage_arrivals(spark, sf_dir)).withWatermark("event_time", "60 minutes")
        counted = stream.groupBy(make().alias("w"), "image_id").agg(F.count(F.lit(1)).alias("files"), F.sum("bytes").alias("bytes"))
        return _plain(run_to_end(counted.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "image_id", "files", "bytes"), "complete"))

    return run


tumbling = _windowed(lambda: F.window("event_time", "1 day"))
sliding = _windowed(lambda: F.window("event_time", "1 day", "6 hours"))
sessions = _windowed(lambda: F.session_window("event_time", "30 minutes"))


def interval_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """P and Q files of one tile within an hour of each other, joined stream to stream."""
    stream = lambda side, prefix: read_arrivals(spark, path).filter(F.col("side") == side).select(F.col("image_id").alias(f"{prefix}_image"), F.col("tile_id").alias(f"{prefix}_tile"), F.col("event_id").alias(f"{prefix}_event"), F.col("event_time").alias(f"{prefix}_time")).withWatermark(f"{prefix}_time", "60 minutes")
    path = stage_arrivals(spark, sf_dir)
    p, q = stream("P", "p"), stream("Q", "q")
    near = (F.col("p_image") == F.col("q_image")) & (F.col("p_tile") == F.col("q_tile")) & F.expr("q_time BETWEEN p_time - INTERVAL 1 HOUR AND p_time + INTERVAL 1 HOUR")
    return run_to_end(p.join(q, near).select(F.col("p_image").alias("image_id"), F.col("p_tile").alias("tile_id"), "p_event", "q_event"), "append")


def unanswered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """P files without a Q file of their tile within an hour, by a left outer stream join.

    A row is certain once the watermark has passed its hour, so only files two days older than the last ones of both
    sides are given out; those after that may still be waiting when the input ends.
    """
    path = stage_arrivals(spark, sf_dir)
    stream = lambda side, prefix: read_arrivals(spark, path).filter(F.col("side") == side).select(F.col("image_id").alias(f"{prefix}_image"), F.col("tile_id").alias(f"{prefix}_tile"), F.col("event_id").alias(f"{prefix}_event"), F.col("event_time").alias(f"{prefix}_time")).withWatermark(f"{prefix}_time", "60 minutes")
    p, q = stream("P", "p"), stream("Q", "q")
    near = (F.col("p_image") == F.col("q_image")) & (F.col("p_tile") == F.col("q_tile")) & F.expr("q_time BETWEEN p_time - INTERVAL 1 HOUR AND p_time + INTERVAL 1 HOUR")
    alone = run_to_end(p.join(q, near, "left_outer").select(F.col("p_image").alias("image_id"), F.col("p_tile").alias("tile_id"), "p_event", "p_time", "q_event"), "append").filter("q_event IS NULL")
    ends = tile_arrivals(spark, sf_dir).agg(F.least(F.max(F.when(F.col("side") == "P", F.col("event_time"))), F.max(F.when(F.col("side") == "Q", F.col("event_time")))).alias("last"))
    return alone.join(F.broadcast(ends), F.col("p_time").cast("timestamp_ntz") <= F.col("last") - F.expr("INTERVAL 2 DAYS")).select("image_id", "tile_id", "p_event")


def asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each Q file, the last P file of its tile at or before it: union, then the last non-null value."""
    a = tile_arrivals(spark, sf_dir)
    w = Window.partitionBy("image_id", "tile_id").orderBy("event_time", F.col("side"), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("side") == "P", F.col("event_id")), ignorenulls=True).over(w)
    return a.withColumn("p_event", last).filter("side = 'Q'").select("image_id", "tile_id", "p_event", F.col("event_id").alias("q_event"))


class TileAssembler:
    """Holds the files of a tile until both sides are there; emits them in order of event time as pairs.

    What waits longer than the state's timeout is given out as one side only, with -1 for the other.
    """

    OUTPUT = "image_id int, tile_id bigint, p_event bigint, q_event bigint"
    STATE = "p array<bigint>, q array<bigint>"

    def __call__(self, key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        p, q = (list(x) for x in state.get) if state.exists else ([], [])
        if state.hasTimedOut:
            state.remove()
            rows = [(*key, int(e), -1) for e in p] + [(*key, -1, int(e)) for e in q]
            yield pd.DataFrame(rows, columns=["image_id", "tile_id", "p_event", "q_event"])
            return
        for frame in frames:
            for side, event in zip(frame["side"], frame["event_id"], strict=True):
                (p if side == "P" else q).append(int(event))
        p, q = sorted(p), sorted(q)
        k = min(len(p), len(q))
        rows = [(*key, a, b) for a, b in zip(p[:k], q[:k], strict=True)]
        if not (p[k:] or q[k:]):
            if state.exists:
                state.remove()
        else:
            state.update((p[k:], q[k:]))
            state.setTimeoutTimestamp(state.getCurrentWatermarkMs() + 24 * 3600 * 1000)
        yield pd.DataFrame(rows, columns=["image_id", "tile_id", "p_event", "q_event"])


def assemble_tiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    stream = read_arrivals(spark, stage_arrivals(spark, sf_dir)).withWatermark("event_time", "60 minutes")
    made = stream.groupBy("image_id", "tile_id").applyInPandasWithState(TileAssembler(), TileAssembler.OUTPUT, TileAssembler.STATE, "append", GroupStateTimeout.EventTimeTimeout)
    return run_to_end(made, "append")


class BothSides:
    """Gives a tile out once, when files of both sides have arrived; the state is three flags a tile, whatever is sent again."""

    OUTPUT = "image_id int, tile_id bigint"
    STATE = "p boolean, q boolean, done boolean"

    def __call__(self, key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        p, q, done = state.get if state.exists else (False, False, False)
        for frame in frames:
            sides = set(frame["side"])
            p, q = p or "P" in sides, q or "Q" in sides
        ready = bool(p and q and not done)
        state.update((bool(p), bool(q), bool(done or ready)))
        yield pd.DataFrame([key] if ready else [], columns=["image_id", "tile_id"])


def stream_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Running score per image over the tiles whose P and Q files have arrived (re-sent files count once): sums are mergeable.

    Each micro-batch compares its own new tiles with the batch kernel; the running state is (sum, count).
    """
    arrivals = read_arrivals(spark, stage_arrivals(spark, sf_dir))
    fresh = arrivals.groupBy("image_id", "tile_id").applyInPandasWithState(BothSides(), BothSides.OUTPUT, BothSides.STATE, "append", GroupStateTimeout.NoTimeout)
    p, q = cells(spark, sf_dir, "P"), cells(spark, sf_dir, "Q")
    out, checkpoint = new_path(spark, "scores"), new_path(spark, "progress")
    seen = []

    def sink(df: DataFrame, batch_id: int) -> None:
        own = p.join(df, ["image_id", "tile_id"], "left_semi")
        parts = similarity.partial_scores(native.edge_form_areas(pairing.candidate_pairs(own, q)))
        parts.write.mode("overwrite").parquet(f"{out}/batch={batch_id}")
        seen.append(batch_id)

    fresh.writeStream.foreachBatch(sink).outputMode("append").option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()
    schema = "image_id int, ratio_sum double, pairs bigint"
    parts = spark.read.schema(schema).parquet(*(f"{out}/batch={b}" for b in sorted(set(seen)))) if seen else spark.createDataFrame([], schema)
    return similarity.merged_scores(parts).select("image_id", "pairs", F.round("score", 6).alias("score"))


def late_rows(spark: SparkSession, sf_dir: str, delay: str = "10 minutes") -> DataFrame:
    """Rows that a short watermark drops, one file per trigger: delay, rows dropped."""
    stream = read_arrivals(spark, stage_arrivals(spark, sf_dir, files=8)).withWatermark("event_time", delay)
    counted = stream.groupBy(F.window("event_time", "10 minutes"), "image_id").count()
    query = counted.writeStream.format("noop").outputMode("update").option("checkpointLocation", new_path(spark, "progress")).trigger(availableNow=True).start()
    query.awaitTermination()
    dropped = sum(o.numRowsDroppedByWatermark for x in query.recentProgress for o in x.stateOperators)
    return spark.createDataFrame([(delay, int(dropped))], "delay string, dropped bigint")
