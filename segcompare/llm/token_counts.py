"""Token counts of documents in flat token files that have no index, by a vectorised scan for separators.

A file is ids of fixed width, each document closed by the separator id. It is cut into blocks; each block is
searched in one vector comparison. A block knows its own separators only, so the documents that cross blocks
are stitched by an exclusive prefix scan over the blocks' summaries (separators before, place of the last one).

A file without any separator has one open document (`closed` false); an empty file has none. Blocks are read
with range reads through pyarrow.fs, so a file may be larger than any worker's memory.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import fresh, saved
from .tokens import SPECIAL_ID, tokenizer
from .words import chunks

WRITTEN = "file string, ordinal long, doc_id long, bytes long"


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


def write_token_files(docs: DataFrame, folder: str, separator: int = SPECIAL_ID, width: int = 2, tokenizer_path: str | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Writes one flat file per task; rows: a document's place in its file, and per file one row of ordinal -1 with its bytes.

    A file's name has the attempt's number, so that of a task that ran twice only the listed file counts.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, context = tokenizer(tokenizer_path), TaskContext.get()
        file = f"{folder}/tokens-{context.partitionId():06d}-{context.taskAttemptId()}.bin"
        out, ordinal, written = None, 0, 0
        pack = lambda n, ids: pa.RecordBatch.from_arrays([pa.array([file] * len(ids), pa.string()), pa.array(n, pa.int64()), ids, pa.array([written] * len(ids), pa.int64())], names=["file", "ordinal", "doc_id", "bytes"])
        for batch in chunks(batches):
            if out is None:
                store, path = _open(file)
                store.create_dir(path.rpartition("/")[0], recursive=True)
                out = store.open_output_stream(path)
            parts = []
            for text in batch.column(1).to_pylist():
                ids = tok.encode(text or "", ordinary=True)
                ids.append(separator)
                parts.append(np.array(ids, f"<u{width}"))
            block = np.concatenate(parts)
            out.write(block.tobytes())
            written += block.nbytes
            yield pack(range(ordinal, ordinal + len(batch)), batch.column(0))
            ordinal += len(batch)
        if out is not None:
            out.close()
            yield pack([-1], pa.array([None], pa.int64()))

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, WRITTEN)


def scan_blocks(files: DataFrame, separator: int = SPECIAL_ID, width: int = 2, block_tokens: int = 1 << 21) -> DataFrame:
    """files (file, bytes) -> one row per block: first token, tokens, places of separators in the block."""
    size = block_tokens * width
    blocks = files.filter("bytes > 0").select("file", "bytes", F.explode(F.expr(f"sequence(0L, (bytes - 1) div {size})")).alias("block"))
    blocks = blocks.repartition("file", "block")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, total, block in zip(*(batch.column(c).to_pylist() for c in range(3)), strict=True):
                store, path = _open(file)
                with store.open_input_file(path) as f:
                    data = np.frombuffer(f.read_at(min(size, total - block * size), block * size), f"<u{width}")
                places = np.flatnonzero(data == separator)
                yield pa.RecordBatch.from_arrays([pa.array([file]), pa.array([block], pa.int64()), pa.array([len(data)], pa.int64()), pa.array([places.astype(np.int64)], pa.list_(pa.int64()))], names=["file", "block", "n", "places"])

    return blocks.mapInArrow(run, "file string, block long, n long, places array<long>").select("file", "block", (F.col("block") * block_tokens).alias("first"), "n", "places")


def stitch(blocks: DataFrame) -> DataFrame:
    """Blocks -> one row per document: file, ordinal, first token, tokens without the separator, closed."""
    before = Window.partitionBy("file").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    summary = blocks.select("file", "block", "first", "n", F.size("places").alias("k"), F.expr("first + try_element_at(places, -1)").alias("last"))
    carry = summary.select("file", "block", F.coalesce(F.sum("k").over(before), F.lit(0)).alias("docs_before"), (F.coalesce(F.max("last").over(before), F.lit(-1)) + 1).alias("open_at"))
    closed = (
        blocks.join(carry, ["file", "block"])
        .select("file", "first", "docs_before", "open_at", "places", F.posexplode("places").alias("i", "place"))
        .select("file", (F.col("docs_before") + F.col("i")).alias("ordinal"), F.expr("CASE WHEN i = 0 THEN open_at ELSE first + places[i - 1] + 1 END").alias("start"), (F.col("first") + F.col("place")).alias("stop"))
    )
    tail = summary.groupBy("file").agg(F.sum("k").alias("ordinal"), (F.coalesce(F.max("last"), F.lit(-1)) + 1).alias("start"), F.max(F.col("first") + F.col("n")).alias("stop")).filter("stop > start")
    return closed.select("file", "ordinal", "start", (F.col("stop") - F.col("start")).alias("n_tokens"), F.lit(True).alias("closed")).unionByName(tail.select("file", "ordinal", "start", (F.col("stop") - F.col("start")).alias("n_tokens"), F.lit(False).alias("closed")))


def count_tokens(spark: SparkSession, files: DataFrame, separator: int = SPECIAL_ID, width: int = 2, block_tokens: int = 1 << 21) -> DataFrame:
    """Documents of flat token files (file, bytes); the blocks' separators are kept in the shared folder."""
    return stitch(saved(scan_blocks(files, separator, width, block_tokens), "blocks"))


def document_token_counts(docs: DataFrame, **options) -> DataFrame:
    """Writes docs as flat token files, scans them, and names each counted document: doc_id, n_tokens, file part, ordinal."""
    spark = docs.sparkSession
    listed = saved(write_token_files(docs, fresh(spark, "tokens"), **options), "listed")
    counted = count_tokens(spark, listed.filter("ordinal = -1").select("file", "bytes"))
    named = listed.filter("ordinal >= 0").select("file", "ordinal", "doc_id")
    return named.join(counted, ["file", "ordinal"], "left").select("doc_id", F.coalesce("n_tokens", F.lit(0)).alias("n_tokens"), "ordinal", F.regexp_extract("file", r"tokens-(\d+)-", 1).cast("long").alias("part"), "start")
