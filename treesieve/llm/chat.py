"""Preference formatting of conversations, in DataFrame functions alone.

A pair is a chosen and a rejected conversation. Their longest common prefix of turns (same role and
text, in order) is rendered once, as the prompt; what follows on either side is rendered as its
completion, with the spans of it that the loss counts: the texts of the assistant and the end mark
behind them. Offsets count characters of the completion.

Results: turns are ordered by turn number, then role, then text, nulls first, so ties have an order
and repeated rows repeat; a null role is rendered as ``unknown``, a null text as empty (for the
prefix, null equals null only); a pair that lacks a conversation has no turns on that side, hence
no prompt; rows without conv_id are in no pair. One conversation is one output row, and its turns
are gathered in one task: that is the unit of the format.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: Fixed values of the template.
OPEN, MIDDLE, END, TRAINED = "<|", "|>\n", "<|end|>\n", "assistant"


def conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, turns) with turns an ordered array of (turn, role, text)."""
    return turns.where("conv_id is not null").groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))


def head(turn: Column) -> Column:
    return F.concat(F.lit(OPEN), F.coalesce(turn["role"], F.lit("unknown")), F.lit(MIDDLE))


def body(turn: Column) -> Column:
    return F.concat(F.coalesce(turn["text"], F.lit("")), F.lit(END))


def render(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(head(t), body(t))), "")


def trained_spans(turns: Column) -> Column:
    """[start, end) of what the loss counts in the rendered turns."""
    zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("spans"))

    def step(state: Column, t: Column) -> Column:
        start = state["at"] + F.length(head(t))
        end = start + F.length(body(t))
        span = F.array(F.struct(start.cast("int").alias("start"), end.cast("int").alias("end")))
        return F.struct(end.alias("at"), F.when(t["role"] == TRAINED, F.concat(state["spans"], span)).otherwise(state["spans"]).alias("spans"))

    return F.aggregate(turns, zero, step, lambda s: s["spans"])


def common_turns(a: Column, b: Column) -> Column:
    same = F.zip_with(a, b, lambda x, y: x["role"].eqNullSafe(y["role"]) & x["text"].eqNullSafe(y["text"]) & x.isNotNull() & y.isNotNull())
    first = F.array_position(same, False)
    return F.when(first == 0, F.size(same)).otherwise(first - 1).cast("int")


def preference(turns: DataFrame, pairs: DataFrame) -> DataFrame:
    """pairs: (pair_id, chosen_id, rejected_id). One row for each pair: prompt, completions, masks."""
    convs = conversations(turns)
    none = F.array().cast(convs.schema["turns"].dataType)
    chosen = convs.select(F.col("conv_id").alias("chosen_id"), F.col("turns").alias("c"))
    rejected = convs.select(F.col("conv_id").alias("rejected_id"), F.col("turns").alias("r"))
    both = pairs.select("pair_id", "chosen_id", "rejected_id").join(chosen, "chosen_id", "left").join(rejected, "rejected_id", "left")
    return formatted(both.select("pair_id", "chosen_id", "rejected_id", F.coalesce("c", none).alias("c"), F.coalesce("r", none).alias("r")))


def formatted(both: DataFrame) -> DataFrame:
    """both: pairs with their turns in c and r."""
    split = both.withColumn("n", common_turns(F.col("c"), F.col("r")))
    rest = lambda side: F.slice(side, F.col("n") + 1, F.greatest(F.size(side) - F.col("n"), F.lit(0)))
    cut = split.select("pair_id", "chosen_id", "rejected_id", "n", F.slice("c", 1, F.col("n")).alias("p"), rest(F.col("c")).alias("c"), rest(F.col("r")).alias("r"))
    text = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws("-", s["start"].cast("string"), s["end"].cast("string"))), ",")
    return cut.select(
        "pair_id", "chosen_id", "rejected_id", F.col("n").alias("prompt_turns"), render(F.col("p")).alias("prompt"),
        render(F.col("c")).alias("chosen"), text(trained_spans(F.col("c"))).alias("chosen_mask"),
        render(F.col("r")).alias("rejected"), text(trained_spans(F.col("r"))).alias("rejected_mask"),
    )


def neighbours(turns: DataFrame) -> DataFrame:
    """Pairs for a table that names none: conversation 2p is chosen and 2p+1 rejected in pair p. Both sides
    come out of one grouping by the pair, so turns are shuffled once."""
    side = lambda k: F.sort_array(F.collect_list(F.when(F.pmod("conv_id", F.lit(2)) == k, F.struct("turn", "role", "text"))))
    pair = F.shiftright(F.col("conv_id").cast("long"), 1)
    return turns.where("conv_id is not null").groupBy(pair.alias("pair_id")).agg(side(0).alias("c"), side(1).alias("r")).select("pair_id", (F.col("pair_id") * 2).alias("chosen_id"), (F.col("pair_id") * 2 + 1).alias("rejected_id"), "c", "r")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return formatted(neighbours(table(spark, sf_dir, "conversations")))


ORACLE = """
WITH t AS (SELECT conv_id >> 1 AS pair_id, conv_id & 1 AS side, turn, role, text,
                  row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS pos
           FROM conversations WHERE conv_id IS NOT NULL),
b AS (SELECT coalesce(a.pair_id, z.pair_id) AS pair_id, coalesce(a.pos, z.pos) AS pos,
             a.pos IS NOT NULL AND z.pos IS NOT NULL AND a.role IS NOT DISTINCT FROM z.role AND a.text IS NOT DISTINCT FROM z.text AS same
      FROM (SELECT * FROM t WHERE side = 0) a FULL JOIN (SELECT * FROM t WHERE side = 1) z ON a.pair_id = z.pair_id AND a.pos = z.pos),
n AS (SELECT pair_id, coalesce(min(pos) FILTER (NOT same), max(pos) + 1) - 1 AS n FROM b GROUP BY 1),
m AS (SELECT t.pair_id, side, pos, n, role, '<|' || coalesce(role, 'unknown') || '|>' || chr(10) AS head,
             coalesce(text, '') || '<|end|>' || chr(10) AS body FROM t JOIN n USING (pair_id)),
k AS (SELECT *, sum(length(head) + length(body)) OVER (PARTITION BY pair_id, side ORDER BY pos) AS upto FROM m WHERE pos > n),
s AS (SELECT pair_id, side, string_agg(head || body, '' ORDER BY pos) AS done,
             coalesce(string_agg((upto - length(body))::BIGINT || '-' || upto::BIGINT, ',' ORDER BY pos) FILTER (role = 'assistant'), '') AS mask
      FROM k GROUP BY 1, 2),
p AS (SELECT pair_id, string_agg(head || body, '' ORDER BY pos) AS prompt FROM m WHERE side = 0 AND pos <= n GROUP BY 1)
SELECT pair_id, pair_id * 2 AS chosen_id, pair_id * 2 + 1 AS rejected_id, n::INT AS prompt_turns, coalesce(prompt, '') AS prompt,
       coalesce(c.done, '') AS chosen, coalesce(c.mask, '') AS chosen_mask, coalesce(r.done, '') AS rejected, coalesce(r.mask, '') AS rejected_mask
FROM n LEFT JOIN p USING (pair_id) LEFT JOIN (SELECT * FROM s WHERE side = 0) c USING (pair_id) LEFT JOIN (SELECT * FROM s WHERE side = 1) r USING (pair_id)
"""
