"""Chat formatting in token-budgeted windows, in DataFrame functions only.

A conversation's turns, in order of (turn, role, text), get prefix sums of their token costs. New turns are
cut into spans by these sums: short turns whose sums fall into the same stride share a span, a turn longer
than a stride has one of its own. Each span becomes a window: the conversation's leading system turn, then as
much history before the span as the history budget allows, then the span. A long system turn is repeated too and
shortens its conversation's stride, down to the history budget. Loss falls on the assistant texts of the span
only; what is repeated is masked. A window exceeds the budget only where a single turn is longer than a stride, or
a system turn leaves less than three history budgets; turns are never cut, dropped or sampled.

Prefix sums run in two levels (within blocks of turn numbers, then over the blocks' sums), so that one very
long conversation is spread over tasks.

Template: `<|role|>text<|end|>` per turn, with a backslash before each backslash, `<` and `|` of role and
text; no escaped text can hold a mark, and `unescape` gives every text back.

Defined results: null roles and texts are empty; null turns come first; a null conversation id is one
conversation; repeated rows are separate turns; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import matched, saved


@dataclass(frozen=True)
class Budget:
    """Tokens of a window, of its history, and of a system turn that does not shorten the stride."""

    tokens: int = 1024
    history: int = 128
    system: int = 256
    per_turn: int = 4
    block: int = 256

    def __post_init__(self):
        if self.stride < self.history or self.history < 1:
            raise ValueError("the budget leaves no room for spans")

    @property
    def stride(self) -> int:
        return (self.tokens - self.history - self.system) // 2

    def stride_beside(self, system: Column) -> Column:
        """The stride of a conversation whose leading system turn costs so much."""
        return F.greatest(F.lit(self.history), F.floor((F.lit(self.tokens - self.history) - F.greatest(F.lit(self.system), system)) / 2)).cast("long")


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"([\\<|])", r"\\$1")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"(?s)\\(.)", "$1")


def token_cost(text: Column, per_turn: int) -> Column:
    """Four characters a token, and the turn's marks."""
    return F.floor((F.length(text) + 3) / 4) + F.lit(per_turn)


def _ordered(turns: DataFrame, budget: Budget, cost: Column | None) -> DataFrame:
    """conv_id, k (the id, never null), stride, ord from 1, role, text, cost, before (cost of the turns before), longs (long turns before), is_long."""
    base = turns.select(
        turns["conv_id"].cast("long").alias("conv_id"),
        turns["turn"].cast("long").alias("turn"),
        F.coalesce(turns["role"], F.lit("")).alias("role"),
        F.coalesce(turns["text"], F.lit("")).alias("text"),
        *([cost.cast("long").alias("cost")] if cost is not None else []),
    )
    if cost is None:
        base = base.withColumn("cost", token_cost(F.col("text"), budget.per_turn))
    low = F.lit(-(1 << 63))
    base = base.withColumns({"k": F.coalesce("conv_id", low), "block": F.coalesce(F.floor(F.col("turn") / budget.block), low)})
    heads = base.groupBy("k").agg(F.min(F.struct(F.col("turn").isNotNull().alias("late"), "turn", "role", "text", "cost")).alias("head"), F.count(F.lit(1)).alias("turns"))
    heads = heads.filter((F.col("head.role") == "system") & (F.col("head.cost") > budget.system)).select("k", F.col("head.cost").alias("system"), "turns")
    base = matched(base, saved(heads, "heads"), "k", "turns", "left")
    base = base.withColumn("stride", budget.stride_beside(F.coalesce("system", F.lit(0)))).drop("system", "turns").withColumn("is_long", (F.col("cost") > F.col("stride")).cast("long"))
    inside = Window.partitionBy("k", "block").orderBy(F.col("turn").asc_nulls_first(), "role", "text")
    upto = inside.rowsBetween(Window.unboundedPreceding, 0)
    first = base.withColumns({"n_in": F.row_number().over(inside), "cost_in": F.sum("cost").over(upto), "long_in": F.sum("is_long").over(upto)})
    blocks = base.groupBy("k", "block").agg(F.count(F.lit(1)).alias("n_b"), F.sum("cost").alias("cost_b"), F.sum("is_long").alias("long_b"))
    over = Window.partitionBy("k").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    carry = blocks.select("k", "block", *(F.coalesce(F.sum(c).over(over), F.lit(0)).alias(f"{c}_before") for c in ("n_b", "cost_b", "long_b")))
    joined = first.join(carry, ["k", "block"])
    return joined.select(
        "conv_id", "k", "stride", (F.col("n_in") + F.col("n_b_before")).alias("ord"), "role", "text", "cost", (F.col("cost_in") - F.col("cost") + F.col("cost_b_before")).alias("before"), (F.col("long_in") - F.col("is_long") + F.col("long_b_before")).alias("longs"), "is_long"
    )


def chat_windows(turns: DataFrame, budget: Budget = Budget(), cost: Column | None = None) -> DataFrame:
    """turns (conv_id, turn, role, text) -> conv_id, first_turn (ordinal of the first new turn), formatted, n_repeated (leading turns that are repeated), loss_spans (start, length in characters), tokens.

    cost: a column of exact token counts of each turn, if there is one; every turn must cost something.
    """
    ordered = _ordered(turns, budget, cost)
    ordered = ordered.withColumn("stretch", F.when(F.col("is_long") == 1, F.lit(-1).cast("long")).otherwise(F.floor(F.col("before") / F.col("stride"))))
    ordered = saved(ordered, "turns")  # four branches read it
    span = ["k", "longs", "is_long", "stretch"]
    spans = ordered.groupBy(*span).agg(F.min("ord").alias("first_turn"), F.min("before").alias("start"))
    part = lambda kind: F.struct(F.lit(kind).alias("kind"), F.col("ord").alias("ord"), F.col("role").alias("role"), F.col("text").alias("text"), F.col("cost").alias("cost")).alias("part")
    new = ordered.join(spans, span).select("k", "first_turn", part(2))
    leading = ordered.filter((F.col("ord") == 1) & (F.col("role") == "system"))
    system = spans.filter("first_turn > 1").select("k", "first_turn").join(leading, "k").select("k", "first_turn", part(0))
    h = budget.history
    reach = spans.select("k", "first_turn", "start", F.explode(F.array(F.floor(F.col("start") / h), F.floor(F.col("start") / h) - 1)).alias("bucket"))
    past = ordered.filter(~((F.col("ord") == 1) & (F.col("role") == "system"))).withColumn("bucket", F.floor(F.col("before") / h))
    history = reach.join(past, ["k", "bucket"]).filter((F.col("ord") < F.col("first_turn")) & (F.col("before") >= F.col("start") - h)).select("k", "first_turn", part(1))
    parts = new.unionByName(system).unionByName(history).groupBy("k", "first_turn").agg(F.sort_array(F.collect_list("part")).alias("parts"))
    written = F.transform("parts", lambda p: F.struct(F.concat(F.lit("<|"), escape(p["role"]), F.lit("|>")).alias("head"), escape(p["text"]).alias("body"), ((p["kind"] == 2) & (p["role"] == "assistant")).alias("loss")))
    rows = parts.select("k", "first_turn", written.alias("w"), F.size(F.filter("parts", lambda p: p["kind"] < 2)).alias("n_repeated"), F.aggregate("parts", F.lit(0).cast("long"), lambda a, p: a + p["cost"]).alias("tokens"))
    end = "<|end|>"
    formatted = F.array_join(F.transform("w", lambda x: F.concat(x["head"], x["body"], F.lit(end))), "")
    zero = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,length:bigint>>").alias("spans"))

    def step(a: Column, x: Column) -> Column:
        begin = a["at"] + F.length(x["head"])
        here = F.array(F.struct(begin.cast("long").alias("start"), F.length(x["body"]).cast("long").alias("length")))
        return F.struct((begin + F.length(x["body"]) + len(end)).cast("long").alias("at"), F.when(x["loss"], F.concat(a["spans"], here)).otherwise(a["spans"]).alias("spans"))

    conv = F.when(F.col("k") != -(1 << 63), F.col("k")).alias("conv_id")
    return rows.select(conv, "first_turn", formatted.alias("formatted"), "n_repeated", F.aggregate("w", zero, step, lambda a: a["spans"]).alias("loss_spans"), "tokens")


def read_back(windows: DataFrame) -> DataFrame:
    """One row per conversation from its windows alone: digests of the turns and of the text under the loss mask.

    A digest needs a conversation's text in one row, the only place where that is so.
    """
    pieces = F.slice(F.split("formatted", r"<\|end\|>"), F.col("n_repeated") + 1, F.greatest(F.size(F.split("formatted", r"<\|end\|>")) - 1 - F.col("n_repeated"), F.lit(0)))
    mark = r"(?s)^<\|((?:[^\\|]|\\.)*)\|>(.*)$"
    told = F.transform(pieces, lambda p: F.concat(unescape(F.regexp_extract(p, mark, 1)), F.lit("\n"), unescape(F.regexp_extract(p, mark, 2)), F.lit("\n")))
    loss = F.transform("loss_spans", lambda s: unescape(F.substring("formatted", s["start"].cast("int") + 1, s["length"].cast("int"))))
    rows = windows.select("conv_id", "first_turn", F.size(pieces).alias("n"), F.array_join(told, "").alias("turns"), F.array_join(loss, "").alias("loss"), F.length("formatted").alias("chars"))
    grouped = rows.groupBy("conv_id").agg(F.sum("n").alias("n_turns"), F.sort_array(F.collect_list(F.struct("first_turn", "turns", "loss"))).alias("all"), F.sum("chars").alias("formatted_chars"))
    text = lambda c: F.array_join(F.transform("all", lambda a: a[c]), "")
    hashed = lambda c: F.sha2(c.cast("binary"), 256)
    return grouped.select("conv_id", F.col("n_turns").cast("long").alias("n_turns"), hashed(text("turns")).alias("turns_sha256"), F.length(text("loss")).cast("long").alias("loss_chars"), hashed(text("loss")).alias("loss_sha256"), F.col("formatted_chars").cast("long").alias("formatted_chars"))


def oracle(turns_sql: str, budget: Budget = Budget()) -> str:
    """DuckDB SQL for read_back(chat_windows(...)) over the rows of turns_sql."""
    h = budget.history
    cost = f"(length(text) + 3) // 4 + {budget.per_turn}"
    esc = lambda c: f"regexp_replace({c}, '([\\\\<|])', '\\\\\\1', 'g')"
    return f"""
WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM ({turns_sql})),
n AS (SELECT *, {cost} AS cost, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS ord FROM t),
l AS (SELECT *, greatest({h}, ({budget.tokens} - {h} - greatest({budget.system}, max(CASE WHEN ord = 1 AND role = 'system' THEN cost ELSE 0 END) OVER (PARTITION BY conv_id))) // 2) AS stride FROM n),
o AS (SELECT *, coalesce(sum(cost) OVER p, 0) AS before, coalesce(sum(CASE WHEN cost > stride THEN 1 ELSE 0 END) OVER p, 0) AS longs FROM l
  WINDOW p AS (PARTITION BY conv_id ORDER BY ord ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
c AS (SELECT *, CASE WHEN cost > stride THEN -1 ELSE before // stride END AS stretch, cost > stride AS is_long,
  length({esc("role")}) + length({esc("text")}) + 4 + 7 AS chars FROM o),
sp AS (SELECT conv_id, longs, is_long, stretch, min(ord) AS first_turn, min(before) AS start FROM c GROUP BY ALL),
rep AS (SELECT sp.conv_id, c.chars FROM sp JOIN c ON c.conv_id IS NOT DISTINCT FROM sp.conv_id
  WHERE (c.ord = 1 AND c.role = 'system' AND sp.first_turn > 1)
  OR (NOT (c.ord = 1 AND c.role = 'system') AND c.ord < sp.first_turn AND c.before >= sp.start - {h})),
r AS (SELECT conv_id, sum(chars) AS chars FROM rep GROUP BY conv_id),
g AS (SELECT conv_id, count(*) AS n_turns, string_agg(role || chr(10) || text || chr(10), '' ORDER BY ord) AS turns,
  coalesce(string_agg(text, '' ORDER BY ord) FILTER (WHERE role = 'assistant'), '') AS loss, sum(chars) AS chars FROM c GROUP BY conv_id)
SELECT g.conv_id, n_turns, sha256(turns) AS turns_sha256, CAST(length(loss) AS BIGINT) AS loss_chars, sha256(loss) AS loss_sha256,
  CAST(g.chars + coalesce(r.chars, 0) AS BIGINT) AS formatted_chars
FROM g LEFT JOIN r ON r.conv_id IS NOT DISTINCT FROM g.conv_id"""
