"""Preference formatting with DataFrame operations only.

A pair's chosen and rejected conversations are compared turn by turn; their longest common prefix of equal turns (role
and text) is rendered once as the prompt, and what follows on each side is rendered as a completion. A mask
says which characters of a completion are trained on: the texts of the assistant's turns.

Defined cases: turns are ordered by turn, role and text (nulls first), so repeated rows are repeated turns; a null role or text
is rendered as empty, and equals another null only; rows without a pair are left out; a pair with one side only has an empty
prompt and an empty other completion; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TRAINED = "assistant"


def _text(x: Column) -> Column:
    return F.coalesce(x["text"], F.lit(""))


def _head(x: Column) -> Column:
    return F.concat(F.lit("<|"), F.coalesce(x["role"], F.lit("")), F.lit("|>\n"))


def render(turns: Column) -> Column:
    """The template: <|role|>, line end, text, line end."""
    return F.array_join(F.transform(turns, lambda x: F.concat(_head(x), _text(x), F.lit("\n"))), "")


def trained_spans(turns: Column, role: str = TRAINED) -> Column:
    """start-end (in characters) of what is trained on in a rendered completion, comma-joined."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("spans"))

    def step(acc: Column, x: Column) -> Column:
        begin = acc["at"] + F.length(_head(x))
        end = begin + F.length(_text(x))
        span = F.concat_ws("-", begin.cast("string"), end.cast("string"))
        spans = F.when(F.coalesce(x["role"] == role, F.lit(False)), F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"])
        return F.struct((end + 1).cast("long").alias("at"), spans.alias("spans"))

    return F.array_join(F.aggregate(turns, start, step)["spans"], ",")


def format_pairs(turns: DataFrame, pair: Column, chosen: Column) -> DataFrame:
    """pair_id, prefix_turns, prompt, chosen, rejected, chosen_mask, rejected_mask of every pair.

    ``turns`` has turn, role, text; ``pair`` names a row's pair, ``chosen`` says whether it is of the chosen side.
    """
    rows = turns.select(pair.alias("pair_id"), chosen.alias("_side"), F.struct("turn", "role", "text").alias("_t")).where("pair_id IS NOT NULL")
    sides = rows.groupBy("pair_id").agg(*[F.sort_array(F.collect_list(F.when(F.col("_side") == side, F.col("_t")))).alias(name) for name, side in (("_c", True), ("_r", False))])
    same = F.zip_with("_c", "_r", lambda a, b: a.isNotNull() & b.isNotNull() & a["role"].eqNullSafe(b["role"]) & a["text"].eqNullSafe(b["text"]))
    differ = F.array_position(same, F.lit(False))
    prefix = F.when(differ > 0, differ - 1).otherwise(F.size("_c")).cast("int")
    sides = sides.withColumn("_n", prefix)
    rest = lambda name: F.slice(F.col(name), F.col("_n") + 1, F.size(name))
    sides = sides.withColumns({"_p": F.slice("_c", F.lit(1), F.col("_n")), "_c": F.when(F.size("_c") > 0, rest("_c")).otherwise(F.col("_c")), "_r": F.when(F.size("_r") > 0, rest("_r")).otherwise(F.col("_r"))})
    return sides.select("pair_id", F.col("_n").cast("long").alias("prefix_turns"), render(F.col("_p")).alias("prompt"), render(F.col("_c")).alias("chosen"), render(F.col("_r")).alias("rejected"), trained_spans(F.col("_c")).alias("chosen_mask"), trained_spans(F.col("_r")).alias("rejected_mask"))


def pair_neighbours(conversations: DataFrame) -> DataFrame:
    """Conversation 2i is the chosen one of pair i, conversation 2i + 1 the rejected one."""
    return format_pairs(conversations, F.floor(F.col("conv_id") / 2).cast("long"), F.pmod("conv_id", F.lit(2)) == 0)


SQL = """
WITH t AS (
  SELECT floor(conv_id / 2)::BIGINT AS pair_id, ((conv_id % 2) + 2) % 2 = 0 AS side, role, text,
         row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS n
  FROM conversations WHERE conv_id IS NOT NULL),
m AS (
  SELECT coalesce(c.pair_id, r.pair_id) AS pair_id, coalesce(c.n, r.n) AS n,
         c.n IS NOT NULL AND r.n IS NOT NULL AND c.role IS NOT DISTINCT FROM r.role AND c.text IS NOT DISTINCT FROM r.text AS same
  FROM (FROM t WHERE side) c FULL JOIN (FROM t WHERE NOT side) r ON c.pair_id = r.pair_id AND c.n = r.n),
p AS (SELECT pair_id, coalesce(min(CASE WHEN NOT same THEN n END) - 1, max(n)) AS k FROM m GROUP BY pair_id),
x AS (
  SELECT t.pair_id, side, n, k, coalesce(role, '') AS role, '<|' || coalesce(role, '') || '|>' || chr(10) AS head, coalesce(text, '') AS text
  FROM t JOIN p USING (pair_id)),
y AS (
  SELECT *, coalesce(sum(length(head) + length(text) + 1) OVER (PARTITION BY pair_id, side, n <= k ORDER BY n ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS pos0 FROM x)
SELECT pair_id, k::BIGINT AS prefix_turns,
  coalesce(string_agg(head || text || chr(10), '' ORDER BY n) FILTER (WHERE side AND n <= k), '') AS prompt,
  coalesce(string_agg(head || text || chr(10), '' ORDER BY n) FILTER (WHERE side AND n > k), '') AS chosen,
  coalesce(string_agg(head || text || chr(10), '' ORDER BY n) FILTER (WHERE NOT side AND n > k), '') AS rejected,
  coalesce(string_agg((pos0 + length(head))::VARCHAR || '-' || (pos0 + length(head) + length(text))::VARCHAR, ',' ORDER BY n) FILTER (WHERE side AND n > k AND role = 'assistant'), '') AS chosen_mask,
  coalesce(string_agg((pos0 + length(head))::VARCHAR || '-' || (pos0 + length(head) + length(text))::VARCHAR, ',' ORDER BY n) FILTER (WHERE NOT side AND n > k AND role = 'assistant'), '') AS rejected_mask
FROM y GROUP BY pair_id, k
"""
