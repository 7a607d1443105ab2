"""Language-model scores by prediction by partial matching over bytes.

A trie of byte contexts up to `order` bytes long (5 unless set, 7 at most) predicts each byte of a text. Where a context has not seen the
byte, the model escapes to the next shorter one, and the bytes that the longer context has seen are excluded
there. Escape estimates: "A" 1 / (T + 1), "C" D / (T + D), "D" D / 2T, for T bytes seen, D of them distinct.

*Pretrained*: the trie is counted over the training documents. Each bucket of documents gives its strings of
order + 1 bytes and its words with counts, packed by partition; partitions of two-byte contexts hold whole subtrees, so
the code lengths with escapes and exclusion come from one pass over each; orders 1 and 0 need 65,536 counts,
the only counts that reach the driver. What a bucket needs goes back to it, and its texts are scored by
look-up. *Adaptive*: each document starts with an empty trie and learns as it is read.

The word baseline in the same pass is a unigram model with half a count added.

Defined results: a null text is empty: one closing token, one closing byte. Null ids belong to no fold and
are scored as training rows are not: held_out false, not learned from. Without any training row each byte
has probability 1/256. Repeated rows are scored each, and learned each.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import saved
from .substring_dedup import bucketed, text_bytes
from .words import U64, WordHasher, byte_texts, chunks, mix

#: Closes a text and fills the contexts before it; no byte of UTF-8.
EDGE = b"\xff"
FOLDS = 5
RESULT = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
_END = b"\n"  # no word: the token that closes a document
_PACKED = "part int, bucket int, kind int, keys binary, counts binary, tokens long, distinct long"


def escape_shares(t, d, method: str):
    """(what is taken off a byte's count, divisor, escape probability) for t bytes seen, d distinct."""
    t, d = np.maximum(t, 0.0), np.maximum(d, 0.0)
    if method == "A":
        return 0.0, t + 1.0, np.where(t > 0, 1.0 / (t + 1.0), 1.0)
    if method == "C":
        return 0.0, np.maximum(t + d, 1.0), np.where(t > 0, d / np.maximum(t + d, 1.0), 1.0)
    if method == "D":
        return 0.5, np.maximum(t, 1.0), np.where(t > 0, d / np.maximum(2 * t, 1.0), 1.0)
    raise ValueError(f"no escape method {method}")


def code_lengths(grams: np.ndarray, counts: np.ndarray, pairs: np.ndarray, method: str = "C", order: int = 3) -> np.ndarray:
    """log10 P(last byte | the `order` bytes before it) of distinct strings that hold the whole subtrees of their
    two-byte contexts (unseen ones with count 0 among them); pairs: counts of (byte before, byte)."""
    g = grams.astype(U64)
    one = np.asarray(pairs, np.float64)
    zero = one.sum(0)
    total, distinct = one.sum(1), (one > 0).sum(1)
    probability, rest, open_ = np.zeros(len(g)), np.ones(len(g)), np.ones(len(g), bool)

    def settle(count, t, d) -> None:
        less, divisor, escape = escape_shares(t, d, method)
        here = open_ & (count > 0)
        probability[here] = (rest * (count - less) / divisor)[here]
        open_[here] = False
        rest[:] *= escape

    def level(j: int) -> tuple[np.ndarray, ...]:
        """Nodes of j context bytes and a byte: (place of each string's node, nodes, counts, context of each node)."""
        nodes, at = np.unique(g & U64((1 << 8 * (j + 1)) - 1), return_inverse=True)
        return at, nodes, np.bincount(at, counts, len(nodes)), np.unique(nodes >> U64(8), return_inverse=True)

    above = None  # of the longer context: its nodes' contexts, and which nodes are seen
    for j in range(order, 1, -1):
        at, nodes, count, (contexts, of) = level(j)
        t, d = np.bincount(of, count, len(contexts))[of][at], np.bincount(of, count > 0, len(contexts))[of][at]
        if above is not None:
            up_nodes, up_count, up_of, up_at = above
            here = np.searchsorted(nodes, up_nodes & U64((1 << 8 * (j + 1)) - 1))
            seen = up_count > 0
            size = int(up_of.max()) + 1
            t = t - np.bincount(up_of, count[here] * seen, size)[up_of][up_at]
            d = d - np.bincount(up_of, seen, size)[up_of][up_at]
        settle(count[at], t, d)
        above = nodes, count, of, at
    s, c1 = (g & U64(255)).astype(np.int64), ((g >> U64(8)) & U64(255)).astype(np.int64)
    nodes, count, of, at = above
    seen, size = count > 0, int(of.max(initial=-1)) + 1
    last, before = (nodes & U64(255)).astype(np.int64), ((nodes >> U64(8)) & U64(255)).astype(np.int64)
    t = total[c1] - np.bincount(of, one[before, last] * seen, size)[of][at]
    settle(one[c1, s], t, distinct[c1] - np.bincount(of, seen, size)[of][at])
    out = (zero[None, :] * (one > 0)).sum(1)
    settle(zero[s], zero.sum() - out[c1], (zero > 0).sum() - distinct[c1])
    probability[open_] = (rest / max(256 - (zero > 0).sum(), 1))[open_]
    return np.log10(np.maximum(probability, 1e-300))


def _by_contexts(every: np.ndarray, total: np.ndarray, pairs: np.ndarray, method: str, order: int, room: int = 1 << 19) -> np.ndarray:
    """code_lengths of a partition, in runs of whole two-byte contexts of about `room` strings."""
    context = ((every >> U64(8)) & U64(0xFFFF)).astype(np.uint16)
    by_context = np.argsort(context, kind="stable")
    sizes = np.bincount(context)
    ends = np.cumsum(sizes[sizes > 0])
    cuts = ends[np.flatnonzero(np.diff(ends // room))]
    value = np.empty(len(every), np.float32)
    for run in np.split(by_context, cuts):
        run.sort()  # strings stay in order
        value[run] = code_lengths(every[run], total[run], pairs, method, order)
    return value


def adaptive_log10(text: bytes, order: int = 4, method: str = "C") -> float:
    """log10 probability of a text under a trie that starts empty and learns byte by byte."""
    trie: dict[bytes, dict[int, int]] = {}
    data, total = EDGE * order + text + EDGE, 0.0
    for i in range(order, len(data)):
        byte, excluded, p = data[i], set(), 1.0
        for k in range(order, -1, -1):
            node = trie.get(data[i - k : i])
            if not node:
                continue
            left = {b: n for b, n in node.items() if b not in excluded}
            t, d = sum(left.values()), len(left)
            if not t:
                continue
            less, divisor, escape = escape_shares(float(t), float(d), method)
            if byte in left:
                p *= (left[byte] - less) / divisor
                break
            p *= float(escape)
            excluded |= left.keys()
        else:
            p *= 1 / (256 - len(excluded))
        total += np.log10(p)
        for k in range(order + 1):
            node = trie.setdefault(data[i - k : i], {})
            node[byte] = node.get(byte, 0) + 1
    return float(total)


def _grams(texts: list[bytes], order: int) -> tuple[np.ndarray, np.ndarray]:
    """(strings of a byte and the `order` bytes before it, as numbers, in the texts with their edges; how many each text has)."""
    sizes = np.array([len(t) + 1 for t in texts], np.int64)
    flat = np.frombuffer(b"".join(x for t in texts for x in (EDGE * order, t, EDGE)), np.uint8).astype(U64)
    n = len(flat) - order
    every = flat[:n].copy()
    for k in range(1, order + 1):
        every <<= U64(8)
        every |= flat[k : n + k]
    ends = np.cumsum(sizes + order)
    keep = np.ones(len(flat), bool)
    for k in range(order):
        keep[ends - 1 - k] = False  # the windows that would start in one text and end in the next
    return every[keep[:n]], sizes


def _squeezed(keys: np.ndarray) -> bytes:
    """Sorted keys as differences, whose high bytes are zero and compress."""
    return np.diff(keys, prepend=U64(0)).tobytes()


def _unsqueezed(data: bytes) -> np.ndarray:
    return np.cumsum(np.frombuffer(data, U64), dtype=U64)


def _counts(values: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values and the sums of their weights (0 or 1)."""
    every = np.unique(values)
    learned, count = np.unique(values[weights], return_counts=True)
    out = np.zeros(len(every), np.int64)
    out[np.searchsorted(every, learned)] = count
    return every, out


def _merge(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    keys = np.concatenate([p[0] for p in parts])
    every, at = np.unique(keys, return_inverse=True)
    return every, np.bincount(at, np.concatenate([p[1] for p in parts]), len(every)).astype(np.int64)


def _texts(batch: pa.RecordBatch) -> list[bytes]:
    return [t.lower() for t in byte_texts(batch)]


def _part_of(keys: np.ndarray, kind: int, parts: int) -> np.ndarray:
    """Partition of a word's hash, or of a string's two-byte context."""
    spread = mix((keys >> 8) & 0xFFFF if kind == 0 else keys)
    return (((spread >> U64(32)) * U64(parts)) >> U64(32)).astype(np.int64)


def _gather(parts: int, order: int):
    """Group: a bucket's documents -> its strings (kind 0) and words (kind 1) with training counts, packed by partition."""

    def run(docs: pa.Table) -> pa.Table:
        found: dict[int, list] = {0: [], 1: []}
        hasher = WordHasher()
        for batch in chunks(iter(docs.to_batches()), room=2 << 20):
            texts, learn = _texts(batch), np.array(batch.column(3).to_pylist(), bool)
            grams, sizes = _grams(texts, order)
            found[0] = [_merge([*found[0], _counts(grams, np.repeat(learn, sizes))])]
            del grams
            words = [[*t.split(), _END] for t in texts]
            found[1].append(_counts(hasher([w for x in words for w in x]), np.repeat(learn, [len(w) for w in words])))
        rows = []
        bucket = docs.column("bucket")[0].as_py()
        for kind, got in found.items():
            keys, counts = _merge(got)
            part = _part_of(keys, kind, parts)
            by_part = np.argsort(part, kind="stable")
            keys, counts, part = keys[by_part], counts[by_part], part[by_part]
            cuts = np.flatnonzero(np.diff(part)) + 1
            for k, c, p in zip(np.split(keys, cuts), np.split(counts, cuts), part[np.r_[0, cuts]], strict=True):
                rows.append((int(p), bucket, kind, _squeezed(k), c.astype(np.uint32).tobytes()))
        return _packed(rows)

    return run


def _packed(rows: list[tuple]) -> pa.Table:
    columns = list(zip(*((*r, None, None)[:7] for r in rows), strict=True)) or [[]] * 7
    kinds = [pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.int64(), pa.int64()]
    return pa.table({n.split()[0]: pa.array(c, t) for n, c, t in zip(_PACKED.split(", "), columns, kinds, strict=True)})


def _settle(pairs: np.ndarray, method: str, order: int):
    """Group: a partition's packed rows of all buckets -> per bucket the strings' code lengths or the words'
    corpus counts (only where they differ from the bucket's own); kind 2: tokens and distinct words learned."""

    def run(table: pa.Table) -> pa.Table:
        kind = table.column("kind")[0].as_py()
        keys = [_unsqueezed(b) for b in table.column("keys").to_pylist()]
        counts = [np.frombuffer(b, np.uint32) for b in table.column("counts").to_pylist()]
        every, at = np.unique(np.concatenate(keys), return_inverse=True)
        total = np.bincount(at, np.concatenate(counts), len(every)).astype(np.int64)
        value = _by_contexts(every, total, pairs, method, order) if kind == 0 else total
        rows, begin = [], 0
        part = table.column("part")[0].as_py()
        for bucket, k, c in zip(table.column("bucket").to_pylist(), keys, counts, strict=True):
            new = value[at[begin : begin + len(k)]]
            begin += len(k)
            tell = np.ones(len(k), bool) if kind == 0 else new != c
            if tell.any():
                rows.append((part, bucket, kind, _squeezed(k[tell]), new[tell].tobytes()))
        if kind == 1:
            rows.append((part, None, 2, None, None, int(total.sum()), int((total > 0).sum())))
        return _packed(rows)

    return run


def _told(told: pa.Table, kind: int, values: type) -> tuple[np.ndarray, np.ndarray]:
    """A kind's keys in order, and what was settled for them; packed rows are read in place."""
    rows = told.filter(pa.compute.equal(told.column("kind"), kind))
    packed = [(k.as_buffer(), v.as_buffer()) for k, v in zip(rows.column("keys"), rows.column("counts"), strict=True)]
    keys, value, begin = np.empty(sum(k.size for k, _ in packed) // 8, U64), np.empty(sum(v.size for _, v in packed) // np.dtype(values).itemsize, values), 0
    for k, v in packed:
        n = k.size // 8
        np.cumsum(np.frombuffer(k, U64), dtype=U64, out=keys[begin : begin + n])
        value[begin : begin + n] = np.frombuffer(v, values)
        begin += n
    order = np.argsort(keys)
    return keys[order], value[order]


def _score(tokens: int, distinct: int, order: int):
    """Cogroup: a bucket's documents and what the corpus tells of their strings and words -> scores."""
    divisor = np.log10(tokens + 0.5 * (distinct + 1))

    def run(docs: pa.Table, told: pa.Table) -> pa.Table:
        strings, lengths = _told(told, 0, np.float32)
        hashes, corpus = _told(told, 1, np.int64)
        hasher = WordHasher()
        # the bucket's own counts hold for the words that no other bucket has learned
        own: list[tuple[np.ndarray, np.ndarray]] = []
        for batch in chunks(iter(docs.to_batches()), room=2 << 20):
            words = [[*t.split(), _END] for t in _texts(batch)]
            own.append(_counts(hasher([w for x in words for w in x]), np.repeat(np.array(batch.column(3).to_pylist(), bool), [len(w) for w in words])))
        known, count = _merge(own)
        if len(hashes):
            count[np.searchsorted(known, hashes)] = corpus
        out = []
        for batch in chunks(iter(docs.to_batches()), room=2 << 20):
            texts = _texts(batch)
            grams, sizes = _grams(texts, order)
            cells, where = np.unique(grams, return_inverse=True)
            length = lengths[np.searchsorted(strings, cells)].astype(np.float64)[where]
            score = np.add.reduceat(length, np.cumsum(sizes) - sizes)
            words = [[*t.split(), _END] for t in texts]
            n = np.array([len(w) for w in words], np.int64)
            c = count[np.searchsorted(known, hasher([w for x in words for w in x]))]
            starts = np.cumsum(n) - n
            base = np.add.reduceat(np.log10(c + 0.5), starts) - n * divisor
            out.append(pa.RecordBatch.from_arrays([batch.column(0), batch.column(4), pa.array(n), pa.array(np.add.reduceat((c > 0).astype(np.int64), starts)), pa.array(np.full(len(n), tokens, np.int64)), pa.array(base), pa.array(score)], names=[x.split()[0] for x in RESULT.split(", ")]))
        schema = pa.schema([("doc_id", pa.int64()), ("held_out", pa.bool_()), ("n_tokens", pa.int64()), ("n_known", pa.int64()), ("train_tokens", pa.int64()), ("base_score", pa.float64()), ("score", pa.float64())])
        return pa.Table.from_batches([b.cast(schema) for b in out], schema)

    return run


def _pairs(docs: DataFrame) -> np.ndarray:
    """Counts of (byte before, byte) over the training rows: at most 65,536 numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << 16, np.int64)
        for batch in chunks(batches, room=2 << 20):
            grams, _ = _grams(_texts(batch), 1)
            total += np.bincount(grams.astype(np.int64), minlength=1 << 16)
        cells = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(cells, pa.int64()), pa.array(total[cells])], names=["cell", "n"])

    rows = docs.filter("learn").select("doc_id", "text").mapInArrow(run, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(1 << 16, np.int64)
    out[rows.column("cell").to_numpy()] = rows.column("n").to_numpy()
    return out.reshape(256, 256)


def score_documents(docs: DataFrame, method: str = "D", order: int = 5, held_fold: int = 1, bucket_bytes: int = 10 << 20, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pretrained scores of all rows, learned from the rows outside the held-out fold."""
    if not 2 <= order <= 7:
        raise ValueError("contexts have 2 to 7 bytes")
    own = bucketed(docs, bucket_bytes, id_col, text_col)
    fold = F.crc32(F.col("doc_id").cast("string").cast("binary")) % FOLDS
    own = own.withColumn("learn", F.coalesce(fold != held_fold, F.lit(False))).withColumn("held_out", F.coalesce(fold == held_fold, F.lit(False)))
    parts = max(8, min(text_bytes(docs, text_col) // bucket_bytes, 1 << 30))
    grouped = own.groupBy("bucket")
    packed = grouped.applyInArrow(_gather(parts, order), _PACKED)
    told = saved(packed.groupBy("kind", "part").applyInArrow(_settle(_pairs(own), method, order), _PACKED), "told")
    tokens, distinct = (x or 0 for x in told.filter("kind = 2").agg(F.sum("tokens"), F.sum("distinct")).first())
    return grouped.cogroup(told.filter("kind < 2").groupBy("bucket")).applyInArrow(_score(tokens, distinct, order), RESULT)


def adaptive_scores(docs: DataFrame, order: int = 4, method: str = "C", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Each row's code length under a trie of its own: doc_id, score; map-only."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in chunks(batches):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([adaptive_log10(t, order, method) for t in _texts(batch)], pa.float64())], names=["doc_id", "score"])

    return docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text")).mapInArrow(run, "doc_id long, score double")
