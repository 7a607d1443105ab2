"""Vectorised word handling shared by the operators that run in Arrow batches.

A word is a run of characters other than the six ASCII blanks (0x20, 0x09-0x0D), which is what
`bytes.split()` gives on UTF-8. Words get 64-bit hashes; windows of words get polynomial hashes over
them modulo 2**64, from prefix sums.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import xxhash

U64 = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_INVERSE = pow(_BASE, -1, 1 << 64)


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        self[word] = value = xxhash.xxh3_64_intdigest(word)
        return value


class WordHasher:
    """Hashes of words, remembered for up to `room` distinct ones."""

    def __init__(self, room: int = 400_000):
        self.room, self.known = room, _Hashes()

    def __call__(self, words: list[bytes]) -> np.ndarray:
        if len(self.known) > self.room:
            self.known = _Hashes()
        return np.fromiter(map(self.known.__getitem__, words), U64, len(words))


_BLANK = np.isin(np.arange(256), [0x20, *range(0x09, 0x0E)])
#: Low bytes of a lane that belong to a word of which so many are left.
_LANE = np.array([(1 << 8 * k) - 1 for k in range(9)], U64)
#: Longer words are hashed one by one.
_LONG = 256


def hashed_words(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of all words of the texts in order, words of each text); no word becomes an object.

    A word is taken by lanes of eight bytes, all words' lanes at once; its length goes into the hash.
    """
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    data = b" ".join(texts) + b" " + bytes(8)
    n = len(data) - 8
    blank = _BLANK[np.frombuffer(data, np.uint8, n)]
    bounds = np.flatnonzero(np.diff(blank, prepend=True))  # a word's first byte and the blank after it, in turn
    start, length = bounds[::2], np.diff(bounds)[::2]
    lanes = np.ndarray(n + 1, "<u8", data, strides=(1,))
    hashes = length.astype(U64) * U64(_BASE)
    at = np.arange(len(start))
    for k in range(0, _LONG, 8):
        at = at[length[at] > k]
        if not len(at):
            break
        lane = lanes[start[at] + k] & _LANE[np.minimum(length[at] - k, 8)]
        hashes[at] = mix(hashes[at] ^ lane)
    for w in np.flatnonzero(length > _LONG):
        hashes[w] = xxhash.xxh3_64_intdigest(data[start[w] : start[w] + length[w]])
    first = np.searchsorted(start, np.cumsum(sizes + 1))
    return hashes, np.diff(first, prepend=0)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit values that spreads every bit."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


class Powers:
    """Powers of the base and of its inverse, grown on demand."""

    def __init__(self):
        self.up = self.down = np.ones(1, U64)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            n = max(n, 2 * len(self.up))
            for name, base in (("up", _BASE), ("down", _INVERSE)):
                factors = np.full(n, base, U64)
                factors[0] = 1
                setattr(self, name, np.multiply.accumulate(factors))
        return self.up, self.down


_powers = Powers()


def windows(hashes: np.ndarray, k: int) -> np.ndarray:
    """One mixed hash for each k consecutive entries; empty when there are fewer."""
    n = len(hashes)
    if n < k:
        return np.empty(0, U64)
    up, down = _powers.upto(n + 1)
    sums = np.zeros(n + 1, U64)
    np.cumsum(hashes * up[:n], out=sums[1:])
    return mix((sums[k:] - sums[: n - k + 1]) * down[: n - k + 1])


def sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w consecutive entries, by running minima of blocks from both sides."""
    n = len(x)
    if n < w:
        return np.empty(0, x.dtype)
    pad = -n % w
    top = np.iinfo(x.dtype).max
    grid = np.concatenate([x, np.full(pad, top, x.dtype)]).reshape(-1, w)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    back = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[: n - w + 1], ahead[w - 1 : n])


def shared_prefixes(ids: np.ndarray, left: np.ndarray, most: int | None = None) -> np.ndarray:
    """For each place, the length of the longest common prefix of its suffix with any other place's, from a suffix array.

    left: entries from a place to the end of its sequence, which a prefix does not cross. Ranks of 1, 2, 4, ... entries
    come from prefix doubling, where only places whose rank is still shared are sorted again; with `most`, suffixes are
    told apart by so many entries at least, and a longer prefix counts as no shorter than that. Neighbours in suffix
    order then have the longest prefix in common, which follows from the stored ranks.
    """
    n = len(ids)
    best = np.zeros(n, np.int64)
    if n < 2:
        return best
    _, rank = np.unique(ids, return_inverse=True)
    size = np.bincount(rank)
    start = np.cumsum(size) - size
    rank = start[rank]  # a rank is the first slot of its group in suffix order
    ranks, step = [rank], 1
    while most is None or step < most:
        count = np.bincount(rank, minlength=n)
        active = np.flatnonzero(count[rank] > 1)
        if not len(active):
            break
        second = np.where(step < left[active], rank[np.minimum(active + step, n - 1)] + 1, 0)
        key = rank[active] * np.int64(n + 1) + second
        order = np.argsort(key)  # equal keys get one rank, so their order is free
        places, keys = active[order], key[order]
        group = rank[places]
        new_group = np.r_[True, group[1:] != group[:-1]]
        new_key = np.r_[True, keys[1:] != keys[:-1]]
        slot = np.arange(len(places)) - np.maximum.accumulate(np.where(new_group, np.arange(len(places)), 0)) + group
        rank = rank.copy()
        rank[places] = slot[np.maximum.accumulate(np.where(new_key, np.arange(len(places)), 0))]
        ranks.append(rank)
        step *= 2
    suffixes = np.argsort(rank)
    a, b = suffixes[:-1], suffixes[1:]
    live = np.flatnonzero(ranks[0][a] == ranks[0][b])
    a, b = a[live], b[live]
    room, common = np.minimum(left[a], left[b]), np.zeros(len(live), np.int64)
    for level in range(len(ranks) - 1, -1, -1):
        same = (common < room) & (ranks[level][np.minimum(a + common, n - 1)] == ranks[level][np.minimum(b + common, n - 1)])
        common[same] += 1 << level
    common = np.minimum(common, room)
    np.maximum.at(best, suffixes[live], common)
    np.maximum.at(best, suffixes[live + 1], common)
    return best


def to_bytes(text: str | bytes | None) -> bytes:
    return b"" if text is None else text if isinstance(text, bytes) else text.encode("utf-8", "surrogatepass")


def covered(starts: np.ndarray, length: np.ndarray | int, n: int) -> np.ndarray:
    """Which of n places lie in one of the spans."""
    edges = np.zeros(n + 1, np.int64)
    np.add.at(edges, starts, 1)
    np.add.at(edges, starts + length, -1)
    return np.cumsum(edges[:n]) > 0


def chunks(batches: Iterator[pa.RecordBatch], text: str = "text", room: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The same rows in batches whose texts have about `room` bytes (or one row)."""
    for batch in batches:
        column = batch.column(batch.schema.get_field_index(text))
        if not len(batch):
            continue
        sizes = np.asarray(pa.compute.fill_null(pa.compute.binary_length(column), 0), np.int64)
        part = np.cumsum(sizes) // room
        for cut in np.split(np.arange(len(batch)), np.flatnonzero(np.diff(part)) + 1):
            yield batch.slice(int(cut[0]), len(cut))


def byte_texts(batch: pa.RecordBatch, text: str = "text") -> list[bytes]:
    """UTF-8 texts of a batch; a null text is empty."""
    column = batch.column(batch.schema.get_field_index(text))
    return [x or b"" for x in column.cast(pa.binary()).to_pylist()]
