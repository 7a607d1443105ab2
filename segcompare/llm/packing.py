"""Online packing of tokenised documents by the sum-of-squares rule.

Each task packs its own rows as they come. A document first fills whole sequences; what is left over goes
to the fill level whose use makes the sum of squared counts of partly filled sequences smallest, with the
counts in one array by level. A sequence that this fills is complete. When the rows end, the open sequences
are finished from the level array: the fullest stay as the rule placed them, and the pieces of the least
filled ones are cut to fill them; the last remainder is cut into powers of two, which need no padding.

Nothing is shuffled; a sequence id is the task's number and a running number, so a task that is run again
gives the same ids. Defined results: a null or empty text has the closing id alone; ties of the rule take the
highest fill level; repeated rows (same id or not) are packed each; a null id stays null; an empty table gives
no rows; a very long text is a run of whole sequences and one remainder; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .tokens import tokenizer
from .words import chunks

PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


class SumOfSquaresPacker:
    """Places item sizes below `room` into open sequences; `levels[h]` counts those filled to h."""

    def __init__(self, room: int):
        self.room, self.levels = room, np.zeros(room + 1, np.int64)
        self.open: list[list[int]] = [[] for _ in range(room + 1)]
        self.next_id = 0

    def new(self) -> int:
        self.next_id += 1
        return self.next_id - 1

    def place(self, size: int) -> tuple[int, int]:
        """(sequence, offset) of the item."""
        counts = self.levels
        # moving a sequence from level h to h + size changes the sum of squares by 2 * (counts[h + size] - counts[h] + 1)
        change = counts[size:] - counts[: self.room + 1 - size] + 1
        change[-1] = -counts[self.room - size]
        change = 2 * change
        change[-1] += 1
        change[0] = 2 * counts[size] + 1
        usable = counts[: self.room + 1 - size] > 0
        usable[0] = True
        change[~usable] = np.iinfo(np.int64).max
        level = len(change) - 1 - int(np.argmin(change[::-1]))
        if level == 0:
            sequence = self.new()
        else:
            sequence = self.open[level].pop()
            counts[level] -= 1
        if level + size < self.room:
            self.open[level + size].append(sequence)
            counts[level + size] += 1
        return sequence, level


def _powers(n: int) -> list[int]:
    return [1 << k for k in range(n.bit_length() - 1, -1, -1) if n >> k & 1]


def finish(sequences: dict[int, list[tuple]], room: int, new) -> list[tuple]:
    """Pieces (document, start, length, ids, its tokens, offset) by open sequence -> all pieces with their sequence and offset.

    The fullest sequences keep what they hold and are filled up from the least filled ones, whose pieces are
    cut as needed; what is left when these meet lies in powers of two.
    """
    fill = {s: sum(p[2] for p in pieces) for s, pieces in sequences.items()}
    order = sorted(sequences, key=lambda s: (-fill[s], s))
    total = sum(fill.values())
    # as many sequences stay as can be filled by the others
    stay, held = 0, 0
    while stay < len(order) and total >= (stay + 1) * room:
        stay += 1
    out = [(*p[:5], s, p[5]) for s in order[:stay] for p in sequences[s]]
    gaps = [(s, fill[s], room) for s in order[:stay]]
    held = total - stay * room
    for size in _powers(held):
        gaps.append((new(), 0, size))
    at = 0
    for s in order[stay:]:
        for doc, start, length, ids, doc_tokens, _ in sequences[s]:
            while length:
                sequence, used, size = gaps[at]
                take = min(length, size - used)
                if take:
                    out.append((doc, start, take, ids[:take], doc_tokens, sequence, used))
                    ids, start, length, used = ids[take:], start + take, length - take, used + take
                    gaps[at] = (sequence, used, size)
                if used == size:
                    at += 1
    return out


def _pack_rows(batches: Iterator[pa.RecordBatch], room: int, path: str | None, end_id: int, base: int) -> Iterator[list[tuple]]:
    tok, packer = tokenizer(path), SumOfSquaresPacker(room)
    held: dict[int, list[tuple]] = {}
    fill: dict[int, int] = {}
    for batch in chunks(batches):
        rows: list[tuple] = []
        for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            ids = tok.encode(text or "")
            ids.append(end_id)
            flat = np.array(ids, "<u4")
            n, start = len(flat), 0
            while n - start >= room:
                rows.append((doc, start, room, zlib.crc32(flat[start : start + room]), n, base + packer.new(), 0))
                start += room
            if n > start:
                sequence, offset = packer.place(n - start)
                held.setdefault(sequence, []).append((doc, start, n - start, flat[start:].copy(), n, offset))
                fill[sequence] = offset + n - start
                if fill[sequence] == room:
                    del fill[sequence]
                    rows += [(d, s, m, zlib.crc32(x), all_, base + sequence, o) for d, s, m, x, all_, o in held.pop(sequence)]
        yield rows
    yield [(d, s, m, zlib.crc32(np.ascontiguousarray(x)), all_, base + sequence, o) for d, s, m, x, all_, sequence, o in finish(held, room, packer.new)]


def pack_documents(docs: DataFrame, room: int = 1024, tokenizer_path: str | None = None, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per piece: where it lies in its document and in its sequence, and the checksum of its ids."""
    if room < 2:
        raise ValueError("a sequence needs room for two tokens at least")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        base = TaskContext.get().partitionId() << 40
        names = [x.split()[0] for x in PIECES.split(", ")]
        for rows in _pack_rows(batches, room, tokenizer_path, end_id, base):
            columns = list(zip(*rows, strict=True)) or [[] for _ in names]
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names=names)

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, PIECES)
