"""Benchmark decontamination by spaced seeds, in DataFrame functions only.

Words are lower-cased runs of letters and digits. A mask is a fixed choice of positions out of a span; the
hash of the words at these positions is taken at every word of the documents and of the benchmark items, so
a substituted word under an ignored position does not hide a copied passage. Equal hashes give hits; a hit
fixes how document and item lie against each other (document place minus item place). Along each such
diagonal the words are compared, and an overlap counts where `window` consecutive words agree in at least
`percent` of the places (a shorter item: all its words as window, from `least` words on).

The benchmark's seeds are broadcast after counting them, up to `broadcast_rows`; more are joined by shuffle.

Defined results: null or empty texts and items have no words and no hits; items of fewer than `least` words
are too short to tell a leak by and give none; repeated rows (same id and text) give one result; a null id
stays null in the result; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import broadcast_if_small, saved


@dataclass(frozen=True)
class Seeds:
    """masks: word positions hashed together, within spans of `least` words at most.

    The given ones have a hit for every placement of the substitutions that a window of 8 to 13 words may hold.
    """

    masks: tuple[tuple[int, ...], ...] = ((0, 1, 2, 3, 4), (0, 1, 2, 3, 5), (0, 1, 2, 5, 7), (0, 1, 3, 4, 5), (0, 1, 3, 6, 7), (0, 1, 4, 6, 7), (0, 2, 4, 6, 7))
    window: int = 13
    percent: int = 75
    least: int = 8
    broadcast_rows: int = 1_000_000

    def __post_init__(self):
        if any(max(m) >= self.least or min(m) for m in self.masks):
            raise ValueError("a mask begins at 0 and fits into the shortest item")


def _words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}\p{N}]+"), lambda w: w != "")


def _seed_rows(df: DataFrame, words: str, keys: list[str], seeds: Seeds) -> DataFrame:
    """keys, mask, place, seed for each place where a mask fits."""
    hashed = df.select(*keys, F.transform(words, lambda w: F.xxhash64(w)).alias("h"))

    def places(mask: tuple[int, ...]) -> Column:
        inside = F.transform(F.sequence(F.lit(0), F.size("h") - 1 - max(mask)), lambda i: F.xxhash64(*(F.get("h", i + o) for o in mask)))
        return F.when(F.size("h") > max(mask), inside).otherwise(F.array().cast("array<long>"))

    by_mask = hashed.select(*keys, F.explode(F.array(*(F.struct(F.lit(k).alias("mask"), places(m).alias("seeds")) for k, m in enumerate(seeds.masks)))).alias("s"))
    return by_mask.select(*keys, F.col("s.mask").alias("mask"), F.posexplode("s.seeds").alias("place", "seed"))


def _items(benchmark: DataFrame, seeds: Seeds, item_col: str, text_col: str) -> DataFrame:
    items = benchmark.select(benchmark[item_col].alias("item_id"), _words(benchmark[text_col]).alias("item"))
    return items.filter(F.size("item") >= seeds.least).dropDuplicates(["item_id", "item"]).withColumn("item_key", F.xxhash64("item_id", "item"))


def row_key(id_: Column, text: Column) -> Column:
    return F.xxhash64(id_, text)


def contaminated_pairs(docs: DataFrame, benchmark: DataFrame, seeds: Seeds = Seeds(), id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """One row per document and item that overlap: doc_key, doc_id, item_id, place of the best window, its words and matches, hits."""
    own = docs.select(docs[id_col].alias("doc_id"), docs[text_col].alias("text")).withColumn("doc_key", row_key(F.col("doc_id"), F.col("text")))
    items = _items(benchmark, seeds, item_col, item_text_col)
    tests = _seed_rows(items, "item", ["item_key"], seeds).withColumnRenamed("place", "item_place")
    if tests.count() <= seeds.broadcast_rows:
        tests = F.broadcast(tests)
    trains = _seed_rows(own.select("doc_key", _words(F.col("text")).alias("words")), "words", ["doc_key"], seeds)
    hits = saved(trains.join(tests, ["mask", "seed"]).groupBy("doc_key", "item_key", (F.col("place") - F.col("item_place")).alias("shift")).agg(F.count(F.lit(1)).alias("hits")), "hits")
    found = broadcast_if_small(hits.select("doc_key").distinct(), "found")
    texts = own.join(found, "doc_key", "left_semi").dropDuplicates(["doc_key"]).select("doc_key", "doc_id", _words(F.col("text")).alias("words"))
    lines = hits.join(items, "item_key").join(texts, "doc_key")
    begin, end = F.greatest(F.lit(0), -F.col("shift")), F.least(F.size("item"), F.size("words") - F.col("shift"))
    same = F.transform(F.sequence(begin, end - 1), lambda j: F.struct(j.alias("j"), (F.get("item", j) == F.get("words", j + F.col("shift"))).cast("int").alias("same")))
    keys = ["doc_key", "item_key", "shift"]
    places = lines.select(*keys, "doc_id", "item_id", "hits", F.least(F.lit(seeds.window), F.size("item")).alias("need"), F.explode(same).alias("p")).select(*keys, "doc_id", "item_id", "hits", "need", "p.j", "p.same")
    along = Window.partitionBy(*keys).orderBy("j")
    matched = places.withColumn("sum", F.sum("same").over(along)).withColumn("n", F.row_number().over(along))
    matched = matched.withColumn("before", F.coalesce(F.expr(f"lag(sum, {seeds.window}) OVER (PARTITION BY doc_key, item_key, shift ORDER BY j)"), F.lit(0)))
    windows = matched.filter((F.col("n") >= F.col("need")) & (100 * (F.col("sum") - F.col("before")) >= seeds.percent * F.col("need")))
    best = F.max(F.struct((F.col("sum") - F.col("before")).alias("matches"), F.col("hits"), (-(F.col("j") + F.col("shift") + 1 - F.col("need"))).alias("minus_place"), F.col("need"))).alias("b")
    by_pair = windows.groupBy("doc_key", "doc_id", "item_id").agg(best)
    return by_pair.select("doc_key", "doc_id", "item_id", (-F.col("b.minus_place")).alias("place"), F.col("b.need").alias("window_words"), F.col("b.matches").alias("matches"), F.col("b.hits").alias("hits"))


def without_contaminated(docs: DataFrame, benchmark: DataFrame, seeds: Seeds = Seeds(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the rows that overlap a benchmark item."""
    flagged = broadcast_if_small(contaminated_pairs(docs, benchmark, seeds, id_col, text_col).select(F.col("doc_key").alias("_flagged")).distinct(), "flagged")
    return docs.join(flagged, row_key(docs[id_col], docs[text_col]) == flagged["_flagged"], "left_anti")
