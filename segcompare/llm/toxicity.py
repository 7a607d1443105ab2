"""Toxicity of texts that may hide their words: noisy-channel restoration, then a word model.

A character trigram model is counted over all documents. Words that show signs of disguise (figures or signs
inside letters, stretched letters, single letters with blanks or dots between) become a lattice: each
character may stand for itself or for the letters it imitates, a run of one letter for one or two of them, a
separator for nothing. The best path under the character model and the channel's costs is the restored word.
A sign at a word's edge is mostly punctuation, so leaving it out is cheap there and dear inside a word: "to!!"
stays "to", "sh!p" becomes "ship". Letters of other scripts that look like Latin ones are read as these. Where
the best reading is the word as written, the channel adds nothing.
A logistic model over words and their beginnings (of the written and the restored ones), so that inflected
forms of one stem count together, gives the score.

Labels are learned only from rows outside the held-out fold, from a sample of at most `per_class` labelled ids of
each class, one text each, the parameter that bounds what the driver gathers.
Defined results: null and empty texts score the fitted intercept, as does a text without known features; without
labels of both classes all rows score the prior; repeated rows (same id or not) are scored each, a null id is
never held out; ties between readings take the least string; an empty table gives no rows; other columns, labels
included, are ignored by the score; texts and words of any length are read whole.
"""

from __future__ import annotations

import functools
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .pii import LOOK_ALIKES
from .words import chunks

FOLDS = 5
_SIZE = 64
COLUMNS = "doc_id long, held_out boolean, score double, predicted int"


def _alphabet() -> np.ndarray:
    """Latin-1 code -> symbol: 0 blank and rest, letters a-z, then accented letters as one symbol each."""
    table, k = np.zeros(256, np.int32), 27
    for c in range(256):
        low = chr(c).lower()
        if "a" <= low <= "z":
            table[c] = ord(low) - 96
        elif chr(c).isalpha() and c >= 0xE0 and k < _SIZE:
            table[c] = k
            k += 1
    for c in range(0xC0, 0xDF):
        low = chr(c).lower()
        if len(low) == 1 and ord(low) < 256:
            table[c] = table[ord(low)]
    return table


ALPHABET = _alphabet()


def _symbols(text: str) -> np.ndarray:
    return ALPHABET[np.frombuffer(text.encode("latin-1", "replace"), np.uint8)]


def count_trigrams(docs: DataFrame, text_col: str = "text") -> np.ndarray:
    """Counts of symbol trigrams over all documents; at most 64**3 rows reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(_SIZE**3, np.int64)
        for batch in chunks(batches, room=1 << 20):
            s = _symbols("  ".join(["", *(t or "" for t in batch.column(0).to_pylist()), ""]))
            total += np.bincount(s[:-2] * _SIZE * _SIZE + s[1:-1] * _SIZE + s[2:], minlength=_SIZE**3)
        cells = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(cells, pa.int64()), pa.array(total[cells])], names=["cell", "n"])

    rows = docs.select(docs[text_col].alias("text")).mapInArrow(run, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    counts = np.zeros(_SIZE**3, np.int64)
    counts[rows.column("cell").to_numpy()] = rows.column("n").to_numpy()
    return counts.reshape(_SIZE, _SIZE, _SIZE)


def log_model(counts: np.ndarray) -> np.ndarray:
    """log P(third | first two), mixed with the bigram and unigram estimates."""
    one = counts.sum((0, 1)) + 0.5
    two = counts.sum(0)
    p1 = one / one.sum()
    p2 = (two + 4 * p1) / (two.sum(1, keepdims=True) + 4)
    p3 = (counts + 4 * p2) / (counts.sum(2, keepdims=True) + 4)
    return np.log(p3).astype(np.float32)


# What signs and figures imitate.
IMITATES = {"0": "o", "1": "il", "2": "z", "3": "e", "4": "a", "5": "s", "6": "g", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "<": "c", "€": "e", "£": "l", "¡": "i", "*": "aeiou", "#": "aeiou"}
_SIGNS = re.escape("".join(IMITATES))
_LEET = re.compile(rf"[^\W\d_][{_SIGNS}]+[^\W_]|(?<!\S)[@$|(<€£¡!0-9]+[^\W\d_]{{2}}|[^\W\d_]{{2}}[@$|€£0-9!]+(?=[\s.,;:?]|$)")
_STRETCH = re.compile(r"([^\W\d_])\1\1")
_SPACED = re.compile(rf"(?<![^\s])[^\W_{_SIGNS}](?:[ ._*~-][\w{_SIGNS}]){{2,}}(?![^\s.,;:!?])")
_EDGE = ".,;:!?\"'()[]{}%&*#<>|$ \t\n"
_COST = {"keep": 0.0, "imitate": 0.7, "sign": 6.0, "edge": 0.2, "shrink": 0.4, "join": 0.3, "blank": 1.5}
_LATIN = {ord(k): v.lower() for k, v in LOOK_ALIKES.items() if v.isalpha()}
_OTHER = "".join(map(re.escape, map(chr, _LATIN)))
_MIXED = re.compile(rf"[a-z][{_OTHER}]|[{_OTHER}][a-z]")


def lattice(word: str) -> list[list[tuple[str, float]]]:
    """For each run of one character, what it may stand for and at what cost."""
    spaced = bool(re.match(r"\w[ ._*~-]\w[ ._*~-]", word))
    out = []
    for m in re.finditer(r"(.)\1*", word, re.S):
        c, n = m[1], len(m[0])
        if spaced and c in " ._*~-":
            out.append([("", _COST["join"]), (" ", _COST["blank"])])
            continue
        as_is = [(x, _COST["imitate"]) for x in IMITATES.get(c, "")] or [(c, _COST["keep"])]
        if c in IMITATES:
            at_edge = not c.isdigit() and (m.start() == 0 or m.end() == len(word))
            as_is.append(("", _COST["edge" if at_edge else "sign"]))
        ways = [(x * k, cost + _COST["shrink"] * (k != n and x != "")) for x, cost in as_is for k in sorted({1, 2, n} if n < 3 else {1, 2}) if k <= n or n == 1 and k == 1]
        out.append(sorted({w: c for w, c in sorted(ways, key=lambda y: -y[1])}.items()))
    return out


def path_cost(reading: list[tuple[str, float]], model: np.ndarray) -> float:
    """What one choice of ways costs, under the channel and the character model."""
    total, a, b = sum(price for _, price in reading), 0, 0
    for c in "".join(way for way, _ in reading) + " ":
        z = int(ALPHABET[ord(c)]) if ord(c) < 256 else 0
        total -= float(model[a, b, z])
        a, b = b, z
    return total


def viterbi(word: str, model: np.ndarray) -> str:
    """The cheapest reading of the lattice under the character model."""

    @functools.cache
    def code(c: str) -> int:
        o = ord(c)
        return int(ALPHABET[o]) if o < 256 else 0

    # a reading is a chain of its last piece and the reading before it, so the work is linear in the length
    best: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}
    for ways in [*lattice(word), [(" ", 0.0)]]:
        step: dict[tuple[int, int], tuple[float, tuple | None]] = {}
        for (a, b), (cost, before) in best.items():
            for way, price in ways:
                total, x, y = cost + price, a, b
                for c in way:
                    z = code(c)
                    total -= float(model[x, y, z])
                    x, y = y, z
                if (x, y) not in step or total < step[x, y][0]:
                    step[x, y] = (total, (way, before))
        best = step
    least = min(cost for cost, _ in best.values())
    return min(_spelled(chain) for cost, chain in best.values() if cost == least).strip()


def _spelled(chain: tuple | None) -> str:
    out = []
    while chain:
        way, chain = chain
        out.append(way)
    return "".join(reversed(out))


class Restorer:
    """Words of a text, lower-cased, with the restored forms of disguised ones; short ones' readings are remembered."""

    def __init__(self, model: np.ndarray):
        self.model = model
        self.read = functools.lru_cache(200_000)(lambda word: viterbi(word, model))

    def suspects(self, low: str) -> set[str]:
        found, size = set(), len(low)
        for pattern in (_LEET, _STRETCH) if low.isascii() else (_LEET, _STRETCH, _MIXED):
            a = b = 0
            for m in pattern.finditer(low):
                if m.end() <= b:
                    continue  # in the same word
                a, b = m.start(), m.end()
                while a and not low[a - 1].isspace():
                    a -= 1
                while b < size and not low[b].isspace():
                    b += 1
                found.add(low[a:b])
        return found | {m[0] for m in _SPACED.finditer(low)}

    def words(self, text: str | None, channel: bool = True) -> set[bytes]:
        low = (text or "").lower()
        out = set(low.encode("utf-8", "surrogatepass").translate(_BLANKS).split())
        for word in self.suspects(low) if channel else ():
            if not word.isascii():
                word = word.translate(_LATIN)
            for form in {word.strip(".,;:?\"'%&"), word.strip(_EDGE)}:
                if len(form) >= 2:
                    out.update((self.read(form) if len(form) <= 64 else viterbi(form, self.model)).encode("utf-8", "surrogatepass").translate(_BLANKS).split())
        return out


_BLANKS = bytes(32 if chr(c) in _EDGE else c for c in range(256))


def features(word: bytes) -> list[bytes]:
    """The whole word (marked) and its beginnings of 3 to 8 bytes."""
    return [b"=" + word, *(word[:k] for k in range(3, min(len(word), 9)))]


def sampled_ids(labels: DataFrame, per_class: int) -> DataFrame:
    """At most per_class labelled rows of each class outside the held-out fold, by a hash of the id."""
    usable = labels.filter(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1)).filter(_fold("doc_id") != 0).select("doc_id", "toxic")
    pick = lambda y: usable.filter(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class)
    return pick(0).unionByName(pick(1))


def _fold(column: str):
    return F.crc32(F.col(column).cast("string").cast("binary")) % FOLDS


def fit_words(rows: Iterable[tuple[int, int, list[bytes]]], prior: float, rounds: int = 200, penalty: float = 0.1, most: int = 4000) -> tuple[dict[bytes, float], float]:
    """rows: (id, label, words) -> weights of the `most` features that part the classes best, and the intercept at the given share of class 1."""
    place: dict[bytes, int] = {}
    held = []
    for key, label, words in rows:
        own = {place.setdefault(f, len(place)) for w in words for f in features(w)}
        held.append((key, label, np.sort(np.fromiter(own, np.int64, len(own)))))
    held.sort(key=lambda r: r[:2])
    y = np.array([label for _, label, _ in held], np.float64)
    n1 = y.sum()
    n0 = len(y) - n1
    if not (n0 and n1):
        return {}, float(np.log(max(prior, 1e-6) / max(1 - prior, 1e-6)))
    count = [np.bincount(np.concatenate([f for _, label, f in held if label == c]), minlength=len(place)) for c in (0, 1)]
    share = (count[0] + count[1]) / len(y)
    z = np.abs(count[1] / n1 - count[0] / n0) / np.sqrt(np.maximum(share * (1 - share), 1e-9) * (1 / n1 + 1 / n0))
    usable = (count[0] + count[1] >= 4) & (z >= 3.5)
    names = [(-z[k], f, k) for f, k in place.items() if usable[k]]
    del place
    chosen = sorted(names)[:most]
    vocabulary = {f: k for k, (_, f, _) in enumerate(chosen)}
    column = np.full(len(z), -1, np.int64)
    column[[k for _, _, k in chosen]] = np.arange(len(chosen))
    cols = [c[c >= 0] for c in (column[f] for _, _, f in held)]
    row = np.repeat(np.arange(len(y)), [len(c) for c in cols])
    col = np.concatenate(cols)
    weight, bias = np.zeros(len(vocabulary)), 0.0
    speed, bias_speed = np.full(len(vocabulary), 1e-6), 1e-6
    for _ in range(rounds):
        score = np.bincount(row, weight[col], len(y)) + bias
        error = 1 / (1 + np.exp(-np.clip(score, -30, 30))) - y
        slope = np.bincount(col, error[row], len(vocabulary)) + penalty * weight
        speed += slope**2
        weight -= 0.5 * slope / np.sqrt(speed)
        bias_speed += error.sum() ** 2
        bias -= 0.5 * error.sum() / np.sqrt(bias_speed)
    if 0 < prior < 1:
        bias += np.log(prior / (1 - prior)) - np.log(n1 / n0)
    return {w: float(weight[k]) for w, k in vocabulary.items()}, float(bias)


class _Active(dict):
    """word -> its features that have a weight; remembered for up to half a million words."""

    def __init__(self, weights: dict[bytes, float]):
        super().__init__()
        self.weights = weights

    def __missing__(self, word: bytes) -> tuple[bytes, ...]:
        if len(self) > 500_000:
            self.clear()
        self[word] = found = tuple(f for f in features(word) if f in self.weights)
        return found


def train(docs: DataFrame, labels: DataFrame, per_class: int = 2000, id_col: str = "doc_id", text_col: str = "text") -> tuple[np.ndarray, dict[bytes, float], float]:
    """(character model, word weights, intercept)."""
    spark = docs.sparkSession
    model = log_model(count_trigrams(docs, text_col))
    chosen = F.broadcast(sampled_ids(labels, per_class))  # 2 * per_class ids at most
    share = labels.filter(F.col("doc_id").isNotNull() & (_fold("doc_id") != 0)).agg(F.avg(F.col("toxic").cast("double"))).first()[0]
    box = spark.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        restorer = Restorer(box.value)
        for batch in chunks(batches):
            yield pa.RecordBatch.from_arrays([batch.column(1), batch.column(2), pa.array([sorted(restorer.words(t)) for t in batch.column(0).to_pylist()], pa.list_(pa.binary()))], names=["toxic", "doc_id", "words"])

    own = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    # one text an id, so that repeated ids do not add to what the driver gathers
    sample = own.join(chosen, "doc_id").groupBy("doc_id", F.col("toxic").cast("int").alias("toxic")).agg(F.min("text").alias("text")).select("text", "toxic", "doc_id").mapInArrow(run, "toxic int, doc_id long, words array<binary>")
    rows = ((r.doc_id, r.toxic, [bytes(w) for w in r.words]) for r in sample.toLocalIterator())
    return model, *fit_words(rows, 0.5 if share is None else float(share))


def score_documents(docs: DataFrame, fitted: tuple[np.ndarray, dict[bytes, float], float], id_col: str = "doc_id", text_col: str = "text", channel: bool = True) -> DataFrame:
    """One row per row of docs; map-only. channel=False scores the words as written, to compare with."""
    box = docs.sparkSession.sparkContext.broadcast(fitted)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model, weights, bias = box.value
        restorer, known = Restorer(model), _Active(weights)
        for batch in chunks(batches):
            z = np.array([bias + sum(weights[f] for f in set().union(*map(known.__getitem__, restorer.words(t, channel)))) for t in batch.column(2).to_pylist()])
            score = 1 / (1 + np.exp(-np.clip(z, -500, 500)))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score), pa.array((score >= 0.5).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    own = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].alias("text"))
    return own.select("doc_id", F.coalesce(_fold("doc_id") == 0, F.lit(False)).alias("held_out"), "text").mapInArrow(run, COLUMNS)
