"""Preference formatting: the longest common turn prefix is rendered once as prompt, then paired masked completions.

Input: chosen and rejected conversations, both (pair_id, turn, role, text). Turns are put in order of (turn, role,
text) and numbered from 0; the common prefix ends at the first place where role or text differ or one side has no
turn. Each side's text is the prompt plus its completion; the mask lists the half-open spans of code points of the
completion that are learnt from: the bodies of assistant turns, closing mark included.

A null role is rendered as `user`, a null text as empty (both compare as such); turns with a null number come first;
repeated rows are repeated turns; a pair of which one side has no turns has that side's completion empty; a null
pair id is a pair of its own; an empty table gives an empty result. A conversation is one string in the end, so the
turns of one pair meet in one row; the size of a pair, not of a group of pairs, bounds a task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table

# Marks around a turn.
OPEN, MIDDLE, CLOSE = "<|start|>", "<|message|>", "<|end|>"


def _turns(df: DataFrame, name: str) -> DataFrame:
    turn = F.struct(F.col("turn").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("user")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    return df.groupBy("pair_id").agg(F.sort_array(F.collect_list(turn)).alias(name))


def _rendered(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(F.lit(OPEN), t["role"], F.lit(MIDDLE), t["text"], F.lit(CLOSE))), "")


def _mask(turns: Column) -> Column:
    """Spans of assistant bodies within the rendered turns, by one fold over them."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:long,end:long>>").alias("spans"))

    def step(acc: Column, t: Column) -> Column:
        body = acc["at"] + F.length(t["role"]) + len(OPEN) + len(MIDDLE)
        end = body + F.length(t["text"]) + len(CLOSE)
        spans = F.when(t["role"] == "assistant", F.array_append(acc["spans"], F.struct(body.cast("long").alias("start"), end.cast("long").alias("end")))).otherwise(acc["spans"])
        return F.struct(end.cast("long").alias("at"), spans.alias("spans"))

    return F.aggregate(turns, start, step, lambda acc: acc["spans"])


def preference_rows(chosen: DataFrame, rejected: DataFrame) -> DataFrame:
    """pair_id, n_common, prompt, chosen, rejected, chosen_mask, rejected_mask: one row per pair id of either side."""
    none = F.array().cast("array<struct<turn:long,role:string,text:string>>")
    other = _turns(rejected, "r").withColumnRenamed("pair_id", "pair_b")
    both = _turns(chosen, "c").join(other, F.col("pair_id").eqNullSafe(F.col("pair_b")), "full")
    both = both.select(F.coalesce("pair_id", "pair_b").alias("pair_id"), F.coalesce("c", none).alias("c"), F.coalesce("r", none).alias("r"))
    unequal = F.filter(
        F.sequence(F.lit(0), F.greatest(F.size("c"), F.size("r"))),
        lambda k: (k >= F.size("c")) | (k >= F.size("r")) | (F.get("c", k)["role"] != F.get("r", k)["role"]) | (F.get("c", k)["text"] != F.get("r", k)["text"]),
    )
    both = both.withColumn("n_common", F.get(unequal, F.lit(0)).cast("int"))
    rest = lambda c: F.slice(c, F.col("n_common") + 1, F.greatest(F.size(c) - F.col("n_common"), F.lit(0)))
    both = both.select("pair_id", "n_common", F.slice("c", F.lit(1), F.col("n_common")).alias("p"), rest("c").alias("c"), rest("r").alias("r"))
    return both.select("pair_id", "n_common", _rendered(F.col("p")).alias("prompt"), _rendered(F.col("c")).alias("chosen"), _rendered(F.col("r")).alias("rejected"), _mask(F.col("c")).alias("chosen_mask"), _mask(F.col("r")).alias("rejected_mask"))


def echo_pairs(conversations: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(chosen, rejected) from plain conversations: chosen is the conversation through its last assistant turn, rejected
    the same with that turn replaced by an echo of the turn before it (empty if there is none). A conversation without
    an assistant turn is whole on both sides."""
    turns = conversations.select(F.col("conv_id").alias("pair_id"), "turn", F.coalesce(F.col("role").cast("string"), F.lit("user")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    packed = turns.groupBy("pair_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("c"))
    last = F.coalesce(F.array_max(F.filter(F.transform("c", lambda t, k: F.when(t["role"] == "assistant", k)), lambda k: k.isNotNull())), F.size("c") - 1)
    packed = packed.select("pair_id", "c", last.alias("last")).select("pair_id", F.slice("c", F.lit(1), F.col("last") + 1).alias("c"), "last")
    echo = F.transform("c", lambda t, k: F.when((k == F.col("last")) & (t["role"] == "assistant"), F.struct(t["turn"].alias("turn"), t["role"].alias("role"), F.coalesce(F.get("c", k - 1)["text"], F.lit("")).alias("text"))).otherwise(t))
    return packed.select("pair_id", F.inline("c")), packed.select("pair_id", F.inline(echo))


def op6_preference_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every conversation as a preference pair against its echo; masks as text, start-end joined by commas."""
    rows = preference_rows(*echo_pairs(table(spark, sf_dir, "conversations")))
    spans = lambda c: F.array_join(F.transform(c, lambda s: F.concat(s["start"], F.lit("-"), s["end"])), ",")
    return rows.withColumns({c: spans(c) for c in ("chosen_mask", "rejected_mask")})


#: The same rows in DuckDB's SQL. Conversations whose turns are not unique are not in the tables.
ORACLE = f"""
WITH t AS (
  SELECT conv_id, coalesce(role, 'user') AS role, coalesce(text, '') AS text,
         row_number() OVER (PARTITION BY conv_id ORDER BY turn, role, text) - 1 AS k
  FROM conversations
), l AS (
  SELECT conv_id, coalesce(max(k) FILTER (WHERE role = 'assistant'), max(k)) AS last FROM t GROUP BY conv_id
), s AS (
  SELECT t.conv_id, k, role, text AS c,
         CASE WHEN k = last AND role = 'assistant' THEN coalesce(lag(text) OVER (PARTITION BY t.conv_id ORDER BY k), '') ELSE text END AS r
  FROM t JOIN l ON l.conv_id = t.conv_id WHERE k <= last
), n AS (
  SELECT conv_id, CAST(coalesce(min(k) FILTER (WHERE c <> r), max(k) + 1) AS INTEGER) AS n_common FROM s GROUP BY conv_id
), m AS (
  SELECT s.conv_id, k, n_common, role,
         '{OPEN}' || role || '{MIDDLE}' || c || '{CLOSE}' AS tc, '{OPEN}' || role || '{MIDDLE}' || r || '{CLOSE}' AS tr,
         {len(OPEN) + len(MIDDLE)} + length(role) AS head
  FROM s JOIN n ON n.conv_id = s.conv_id
), o AS (
  SELECT *, CAST(coalesce(sum(length(tc)) FILTER (WHERE k >= n_common) OVER w, 0) AS BIGINT) AS ec,
         CAST(coalesce(sum(length(tr)) FILTER (WHERE k >= n_common) OVER w, 0) AS BIGINT) AS er
  FROM m WINDOW w AS (PARTITION BY conv_id ORDER BY k)
)
SELECT conv_id AS pair_id, any_value(n_common) AS n_common,
  coalesce(string_agg(tc, '' ORDER BY k) FILTER (WHERE k < n_common), '') AS prompt,
  coalesce(string_agg(tc, '' ORDER BY k) FILTER (WHERE k >= n_common), '') AS chosen,
  coalesce(string_agg(tr, '' ORDER BY k) FILTER (WHERE k >= n_common), '') AS rejected,
  coalesce(string_agg((ec - length(tc) + head) || '-' || ec, ',' ORDER BY k) FILTER (WHERE k >= n_common AND role = 'assistant'), '') AS chosen_mask,
  coalesce(string_agg((er - length(tr) + head) || '-' || er, ',' ORDER BY k) FILTER (WHERE k >= n_common AND role = 'assistant'), '') AS rejected_mask
FROM o GROUP BY conv_id
"""
