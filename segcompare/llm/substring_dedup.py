"""Removal of long repeated word sequences with prefix-partitioned suffix trees.

The suffixes that matter start a window of `span` words (35) that starts elsewhere too.

1. Pruning. Each window has an anchor: the least hash among its word sequences of `anchor` words. Equal
   windows have equal anchors, so a window whose anchor occurs once in the corpus is a leaf of the tree and
   is left out. Anchors are about a tenth of the words; only these are counted.
2. Groups. A remaining suffix goes to a group by a prefix of variable length: by its anchor, which reaches
   from somewhere in its window over `anchor` words, so that adjoining suffixes mostly go to one group and their
   words are sent once a run; where an anchor is frequent, by its own first words, more of them the more
   frequent the anchor is. Equal windows meet in one group. Groups are dealt to parts of a size that one task
   sorts; equal runs of a bucket of documents are one row with a count.
3. Subtrees. Each part's suffixes are sorted word by word (a suffix array with the longest common prefixes
   of neighbours, which is the depth-first order of its subtrees); a prefix of `span` words or more that two
   suffixes share is an internal node that deep. Its suffixes go back to their buckets, where adjoining ones
   make the maximal repeats, whose words are removed.

Words are compared by 64-bit hashes. Windows are judged on the input only.
Defined results: null or blank texts have no words; a text shorter than a window loses nothing; repeated
rows (same id or not) are separate documents, so they remove each other; an empty table gives no rows; ties do
not matter, as all suffixes of a node are repeats; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .shared import saved
from .words import U64, byte_texts, chunks, covered, hashed_words, mix, shared_prefixes, sliding_min, windows

RESULT = "doc_id long, n_words long, n_removed long, kept_sha256 string, kept string"


@dataclass(frozen=True)
class Plan:
    """span: words of a window; anchor: words of an anchor; prefixes: words of a suffix's own prefix where its anchor is frequent, and very frequent."""

    span: int = 35
    anchor: int = 18
    prefixes: tuple[int, int] = (9, 18)
    frequent: int = 10_000
    bucket_bytes: int = 8 << 20

    def __post_init__(self):
        if not (1 <= self.anchor <= self.span and all(1 <= p <= self.span for p in self.prefixes)):
            raise ValueError("anchors and prefixes are parts of a window")


def text_bytes(docs: DataFrame, text_col: str) -> int:
    """Bytes of all texts."""
    return docs.agg(F.sum(F.octet_length(docs[text_col]).cast("long"))).first()[0] or 0


def bucketed(docs: DataFrame, bucket_bytes: int, id_col: str, text_col: str) -> DataFrame:
    """doc_id, text, bucket; a bucket has about bucket_bytes of text."""
    buckets = max(1, min(-(-text_bytes(docs, text_col) // bucket_bytes), 1 << 30))
    own = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    return own.withColumn("bucket", F.pmod(F.xxhash64("doc_id", F.length("text")), F.lit(buckets)).cast("int"))


class _Words:
    """The word sequence of some documents, with the windows that lie within one of them."""

    def __init__(self, texts: list[bytes], plan: Plan):
        self.hashes, self.sizes = hashed_words(texts)
        self.n, self.plan = len(self.hashes), plan
        ends = np.cumsum(self.sizes)
        self.left = np.repeat(ends, self.sizes) - np.arange(self.n)  # words from here to the document's end

    def labels(self, length: int) -> np.ndarray:
        """A hash for each place with so many words to come; what crosses documents is not to be used."""
        out = np.zeros(self.n, U64)
        found = windows(self.hashes, length)
        out[: len(found)] = found
        return out

    def anchors(self) -> tuple[np.ndarray, np.ndarray]:
        """(each window's anchor, 0 where no window starts; which places are an anchor of some window)."""
        plan, top = self.plan, np.iinfo(U64).max
        grams = self.labels(plan.anchor)
        grams[self.left < plan.anchor] = top
        width = plan.span - plan.anchor + 1
        own = np.zeros(self.n, U64)
        least = sliding_min(grams, width)
        own[: len(least)] = least
        own[self.left < plan.span] = 0
        padded = np.concatenate([np.zeros(width - 1, U64), own])
        reached = ~sliding_min(~padded, width) if self.n else own
        return own, (reached == grams) & (self.left >= plan.anchor) & (reached > 0)


def _count_anchors(docs: DataFrame, plan: Plan) -> DataFrame:
    """Anchors by bucket: key, bucket, n."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches, room=2 << 20):
            words = _Words(byte_texts(batch), plan)
            own, mark = words.anchors()
            grams = words.labels(plan.anchor)
            bucket = np.repeat(batch.column(2).to_numpy(), words.sizes)[mark]
            pairs = np.stack([grams[mark].view(np.int64), bucket.astype(np.int64)], 1)
            order = np.lexsort((pairs[:, 1], pairs[:, 0]))
            pairs = pairs[order]
            first = np.flatnonzero(np.r_[True, (pairs[1:] != pairs[:-1]).any(1)]) if len(pairs) else np.empty(0, np.int64)
            count = np.diff(np.r_[first, len(pairs)])
            yield pa.RecordBatch.from_arrays([pa.array(pairs[first, 0]), pa.array(pairs[first, 1].astype(np.int32)), pa.array(count.astype(np.int32))], names=["key", "bucket", "n"])

    return docs.mapInArrow(run, "key long, bucket int, n int")


def _parts(table: pa.Table, room: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    return chunks(iter(table.to_batches()), room=room)


_RUNS = "part int, bucket int, n int, words binary"
#: Windows of a run at most.
_LONGEST_RUN = 4096


def _suffixes(plan: Plan, parts: int):
    """Cogroup: a bucket's documents and its repeated anchors -> runs of suffixes that go to one group, as the hashes of their words."""

    def run(docs: pa.Table, anchors: pa.Table) -> pa.Table:
        key = anchors.column("key").to_numpy().view(U64)
        order = np.argsort(key)
        key, total = key[order], anchors.column("total").to_numpy()[order]
        found: dict[tuple[int, bytes], int] = {}
        for batch in _parts(docs) if len(key) else ():
            words = _Words(byte_texts(batch), plan)
            own, _ = words.anchors()
            at = np.minimum(np.searchsorted(key, own), len(key) - 1)
            live = np.flatnonzero((key[at] == own) & (words.left >= plan.span))
            if not len(live):
                continue
            count = total[at[live]]
            group = own[live]
            if (count > plan.frequent).any():
                short, long = (words.labels(p)[live] for p in plan.prefixes)
                group = np.where(count <= plan.frequent, group, np.where(count <= plan.frequent**2, short, np.where(count <= plan.frequent**3, long, words.labels(plan.span)[live])))
            part = ((mix(group) >> U64(32)) * U64(parts)) >> U64(32)
            new = np.r_[True, (live[1:] != live[:-1] + 1) | (group[1:] != group[:-1])]
            starts = np.flatnonzero(new)
            for a, b in zip(starts.tolist(), [*starts[1:].tolist(), len(live)], strict=True):
                for c in range(a, b, _LONGEST_RUN):
                    begin, windows_ = int(live[c]), min(b - c, _LONGEST_RUN)
                    unit = int(part[a]), words.hashes[begin : begin + windows_ + plan.span - 1].tobytes()
                    found[unit] = found.get(unit, 0) + 1
        bucket = docs.column("bucket")[0].as_py() if len(docs) else 0
        return pa.table({"part": pa.array([p for p, _ in found], pa.int32()), "bucket": pa.array([bucket] * len(found), pa.int32()), "n": pa.array(list(found.values()), pa.int32()), "words": pa.array([w for _, w in found], pa.binary())})

    return run


def _walk(plan: Plan):
    """A part's runs -> the labels of the suffixes at internal nodes of `span` words or more, packed by bucket."""

    def run(runs: pa.Table) -> pa.Table:
        runs = runs.combine_chunks()
        sizes = np.array([len(w) // 8 for w in runs.column("words").to_pylist()], np.int64)
        words = np.concatenate([np.frombuffer(w, U64) for w in runs.column("words").to_pylist()])
        ends = np.cumsum(sizes)
        left = np.repeat(ends, sizes) - np.arange(len(words))
        several = np.repeat(runs.column("n").to_numpy() > 1, sizes)
        deep = np.flatnonzero((left >= plan.span) & (several | (shared_prefixes(words, left, plan.span) >= plan.span)))
        bucket = np.repeat(runs.column("bucket").to_numpy(), sizes)[deep]
        label = windows(words, plan.span)[deep] if len(deep) else words[:0]
        order = np.lexsort((label, bucket))
        bucket, label = bucket[order], label[order]
        first = np.flatnonzero(np.r_[True, bucket[1:] != bucket[:-1]]) if len(bucket) else np.empty(0, np.int64)
        packed = [np.unique(x).tobytes() for x in np.split(label, first[1:])] if len(first) else []
        return pa.table({"bucket": pa.array(bucket[first], pa.int32()), "labels": pa.array(packed, pa.binary())})

    return run


def _remove(plan: Plan, with_text: bool):
    """Cogroup: a bucket's documents and the labels of its repeated windows -> documents without the repeats."""

    def run(docs: pa.Table, repeats: pa.Table) -> pa.Table:
        label = np.sort(np.concatenate([np.frombuffer(x, U64) for x in repeats.column("labels").to_pylist()] or [np.empty(0, U64)]))
        rows = []
        for batch in _parts(docs):
            texts = byte_texts(batch)
            words = _Words(texts, plan)
            gone = np.zeros(words.n, bool)
            if len(label) and words.n:
                own = words.labels(plan.span)
                hit = (label[np.minimum(np.searchsorted(label, own), len(label) - 1)] == own) & (words.left >= plan.span)
                gone = covered(np.flatnonzero(hit), plan.span, words.n)
            at = 0
            for doc, own_text in zip(batch.column(0).to_pylist(), texts, strict=True):
                own_words = own_text.split()
                out = gone[at : at + len(own_words)]
                at += len(own_words)
                kept = own_words if not out.any() else [w for w, x in zip(own_words, out.tolist(), strict=True) if not x]
                text = b" ".join(kept)
                rows.append((doc, len(own_words), len(own_words) - len(kept), hashlib.sha256(text).hexdigest(), text.decode("utf-8", "replace") if with_text else None))
        columns = list(zip(*rows, strict=True)) or [[]] * 5
        return pa.table({c.split()[0]: pa.array(v, pa.string() if "string" in c else pa.int64()) for c, v in zip(RESULT.split(", "), columns, strict=True)})

    return run


def remove_repeats(docs: DataFrame, plan: Plan = Plan(), with_text: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs: words, words removed, and what is kept (digest, and text if asked for)."""
    own = bucketed(docs, plan.bucket_bytes, id_col, text_col)
    anchors = saved(_count_anchors(own, plan), "anchors")
    # a row is an anchor in a batch of documents, so that of a frequent one there are as many as batches, not as places
    counted = anchors.withColumn("total", F.sum("n").over(Window.partitionBy("key"))).filter("total > 1")
    repeated = counted.select("bucket", "key", "total")
    grouped = own.groupBy("bucket")
    # a part has about as many words as a bucket
    parts = max(1, min(-(-text_bytes(docs, text_col) // plan.bucket_bytes), 1 << 30))
    runs = grouped.cogroup(repeated.groupBy("bucket")).applyInArrow(_suffixes(plan, parts), _RUNS)
    nodes = runs.groupBy("part").applyInArrow(_walk(plan), "bucket int, labels binary")
    return grouped.cogroup(nodes.groupBy("bucket")).applyInArrow(_remove(plan, with_text), RESULT)
