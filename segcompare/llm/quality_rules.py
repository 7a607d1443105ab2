"""Quality rules on repetition inside a document, from a suffix array over its words.

A batch of documents is one word sequence whose first rank carries the document, so no repeat crosses
documents. Ranks of 1, 2, 4, ... words come from prefix doubling; only places whose rank is still shared
are sorted again. The longest common prefix of neighbours in suffix order follows from the stored ranks,
and its intervals give, for each place, the longest substring that starts there and occurs elsewhere too.

Defined results: a null or empty text has no words and fails the base rule; ties, repeated rows and null
ids are judged row by row; other columns are ignored (or carried along by `filter_documents`).
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .words import byte_texts, chunks, covered, shared_prefixes

COLUMNS = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, repeat_share double, longest_repeat long, kept boolean"
SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Limits:
    """min_repeat: words of a repeat that counts; max_share: of words under repeats; max_longest: words of one repeat.

    Words under repeats are among those of repeated three-word windows, of which the base rule allows half: max_share
    acts below that only.
    """

    min_words: int = 50
    min_repeat: int = 8
    max_share: float = 0.3
    max_longest: int = 100


def repeat_lengths(ids: np.ndarray, docs: np.ndarray) -> np.ndarray:
    """For each place, the words of the longest substring starting there that starts elsewhere in its document too."""
    return shared_prefixes(docs.astype(np.int64) * (int(ids.max(initial=0)) + 1) + ids, np.arange(len(ids), 0, -1))


def maximal_repeats(words: list[bytes], min_repeat: int = 1) -> list[tuple[int, int]]:
    """(start, words) of the repeats of one document that can be extended neither left nor right at that place."""
    known: dict[bytes, int] = {}
    ids = np.fromiter((known.setdefault(w, len(known)) for w in words), np.int64, len(words))
    best = repeat_lengths(ids, np.zeros(len(ids), np.int64))
    longer_left = np.r_[False, best[:-1] == best[1:] + 1]
    return [(int(i), int(best[i])) for i in np.flatnonzero((best >= min_repeat) & ~longer_left)]


def _judge(texts: list[bytes], limits: Limits) -> dict[str, np.ndarray]:
    per_doc = [t.split() for t in texts]
    n_words = np.array([len(w) for w in per_doc], np.int64)
    known: dict[bytes, int] = {}
    put = known.setdefault
    ids = np.fromiter((put(w, len(known)) for words in per_doc for w in words), np.int64, int(n_words.sum()))
    docs = np.repeat(np.arange(len(texts)), n_words)
    best = repeat_lengths(ids, docs)
    n, ends = len(ids), np.cumsum(n_words)
    reach = ends[docs] if n else np.empty(0, np.int64)
    places = np.arange(n)
    triple = np.flatnonzero((best >= 3) & (places + 3 <= reach))
    per = lambda mask: np.bincount(docs[mask], minlength=len(texts)).astype(np.int64)
    repeat_words = per(covered(triple, 3, n))
    long_ones = np.flatnonzero(best >= limits.min_repeat)
    under = per(covered(long_ones, best[long_ones], n))
    longest = np.zeros(len(texts), np.int64)
    np.maximum.at(longest, docs, best)
    chars, symbols, dup_lines = [], [], []
    for raw in texts:
        text = raw.decode("utf-8", "surrogatepass")
        chars.append(len(text) - sum(map(text.count, " \t\n\x0b\x0c\r")))
        symbols.append(sum(map(text.count, SYMBOLS)))
        lines = [x for x in raw.split(b"\n") if x.strip(b" \t\n\x0b\x0c\r")]
        dup_lines.append(len(lines) - len(set(lines)))
    failed = (n_words < limits.min_words) | (100 * repeat_words > 50 * n_words)
    share = under / np.maximum(n_words, 1)
    kept = ~failed & (share <= limits.max_share) & (longest <= limits.max_longest)
    return {"n_words": n_words, "word_chars": np.array(chars, np.int64), "n_symbols": np.array(symbols, np.int64), "n_dup_lines": np.array(dup_lines, np.int64), "n_repeat_words": repeat_words, "base_failed": failed, "repeat_share": share, "longest_repeat": longest, "kept": kept}


def judge_documents(docs: DataFrame, limits: Limits = Limits(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of docs with the counts, the repeats' share and length, and the verdict."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches, room=2 << 20):
            found = _judge(byte_texts(batch), limits)
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(v) for v in found.values())], names=["doc_id", *found])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, COLUMNS)


def filter_documents(docs: DataFrame, limits: Limits = Limits(), text_col: str = "text") -> DataFrame:
    """The rows of docs that the rules keep, with all their columns; no shuffle."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches, text_col, room=2 << 20):
            yield batch.filter(pa.array(_judge(byte_texts(batch, text_col), limits)["kept"]))

    return docs.mapInArrow(run, docs.schema)
