"""Preference formatting of chat conversations, in DataFrame operations only.

Two conversations, chosen and rejected, are compared turn by turn: turns are equal when
role and text are (nulls equal nulls).  The longest common prefix is rendered once as the
prompt; what follows on each side is a completion.  A completion carries a mask as runs of
(begin, length, train): positions are characters of the completion, and only the text and
the end marker of assistant turns are trained on.

Turns are ordered by number, then role, then text, and numbered anew, so gaps and ties do
no harm.  Null roles and texts are rendered as empty.  A side without turns has an empty
completion; a pair without turns doesn't exist.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

# Fixed values of the rendering.
OPEN, CLOSE = "<|im_start|>", "<|im_end|>\n"


def format_preferences(turns: DataFrame) -> DataFrame:
    """From rows (pair_id, side 'chosen' or 'rejected', turn, role, text) one row a pair:
    pair_id, n_prompt_turns, prompt, chosen, rejected, chosen_mask, rejected_mask.

    A conversation is one record of the result, so its turns meet in one row; no other
    grouping takes place.
    """
    order = Window.partitionBy("pair_id", "side").orderBy(F.col("turn").asc_nulls_last(), "role", "text")
    rows = turns.select("pair_id", "side", F.row_number().over(order).alias("k"), "role", "text")
    both = rows.groupBy("pair_id", "k").agg(
        *[F.max(F.when(F.col("side") == s, F.struct(F.lit(True).alias("there"), "role", "text"))).alias(s) for s in ("chosen", "rejected")]
    )
    differs = ~(F.col("chosen").eqNullSafe(F.col("rejected")))
    pairs = both.groupBy("pair_id").agg(
        F.min(F.when(differs, F.col("k"))).alias("split"), F.array_sort(F.collect_list(F.struct("k", "chosen", "rejected"))).alias("turns")
    )
    n_prompt = F.coalesce(F.col("split") - 1, F.size("turns"))

    def heading(turn):
        return F.concat(F.lit(OPEN), F.coalesce(turn["role"], F.lit("")), F.lit("\n"))

    def content(turn):
        return F.concat(F.coalesce(turn["text"], F.lit("")), F.lit(CLOSE))

    def rendered(array, side):
        return F.array_join(F.transform(array, lambda x: F.concat(heading(x[side]), content(x[side]))), "")

    def mask(array, side):
        """Runs of the completion: the heading of a turn, then its content."""
        lengths = F.flatten(
            F.transform(array, lambda x: F.array(F.struct(F.char_length(heading(x[side])).alias("n"), F.lit(False).alias("train")), F.struct(F.char_length(content(x[side])).alias("n"), F.coalesce(x[side]["role"] == "assistant", F.lit(False)).alias("train"))))
        )
        start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<begin:int,length:int,train:boolean>>").alias("runs"))
        return F.aggregate(lengths, start, lambda s, x: F.struct((s["at"] + x["n"]).alias("at"), F.concat(s["runs"], F.array(F.struct(s["at"].alias("begin"), x["n"].alias("length"), x["train"].alias("train")))).alias("runs")))["runs"]

    shown = pairs.select("pair_id", n_prompt.cast("int").alias("n_prompt_turns"), "turns")
    prompt = F.slice("turns", F.lit(1), F.col("n_prompt_turns"))
    rest = F.slice("turns", F.col("n_prompt_turns") + 1, F.greatest(F.size("turns") - F.col("n_prompt_turns"), F.lit(0)))

    def present(side):
        return F.filter(rest, lambda x: x[side].isNotNull())

    sides = {s: present(s) for s in ("chosen", "rejected")}
    return shown.select(
        "pair_id", "n_prompt_turns", rendered(prompt, "chosen").alias("prompt"), *[rendered(a, s).alias(s) for s, a in sides.items()], *[mask(a, s).alias(f"{s}_mask") for s, a in sides.items()]
    )


def neighbour_pairs(conversations: DataFrame) -> DataFrame:
    """Preference pairs from plain conversations: (pair_id, side, turn, role, text).

    Chosen is the conversation as it is.  Rejected ends instead with the last assistant turn
    of its neighbour (ids 2k and 2k+1 are neighbours), a fluent reply to something else;
    without such a neighbour the turn is just missing.  Conversations without an assistant
    turn make no pair.
    """
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"))
    last = rows.filter("role = 'assistant'").groupBy("conv_id").agg(F.max(F.struct("turn", "text")).alias("reply"))
    kept = rows.join(last, "conv_id")
    chosen = kept.select(F.col("conv_id").alias("pair_id"), F.lit("chosen").alias("side"), "turn", "role", "text")
    stays = kept.filter(~((F.col("role") == "assistant") & (F.struct("turn", "text").eqNullSafe(F.col("reply")))) | F.col("role").isNull())
    before = stays.select(F.col("conv_id").alias("pair_id"), F.lit("rejected").alias("side"), "turn", "role", "text")
    other = last.select(F.col("conv_id").bitwiseXOR(F.lit(1)).alias("conv_id"), F.col("reply.text").alias("swapped"))
    instead = last.join(other, "conv_id").select(F.col("conv_id").alias("pair_id"), F.lit("rejected").alias("side"), F.col("reply.turn").alias("turn"), F.lit("assistant").alias("role"), F.col("swapped").alias("text"))
    return chosen.unionByName(before).unionByName(instead)


def op1_preference_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = format_preferences(neighbour_pairs(spark.read.parquet(f"{sf_dir}/conversations.parquet")))
    shown = lambda c: F.array_join(F.transform(c, lambda x: F.concat_ws(":", x["begin"], x["length"], F.when(x["train"], 1).otherwise(0))), ",")
    return pairs.select("pair_id", "n_prompt_turns", "prompt", "chosen", "rejected", shown("chosen_mask").alias("chosen_mask"), shown("rejected_mask").alias("rejected_mask"))


ORACLE_SQL = r"""
WITH last AS (
  SELECT conv_id, max(turn) AS turn, arg_max(text, turn) AS reply FROM conversations WHERE role = 'assistant' GROUP BY conv_id
), ch AS (
  SELECT c.conv_id AS pair_id, c.turn, c.role, c.text FROM conversations c JOIN last USING (conv_id)
), rj AS (
  SELECT c.conv_id AS pair_id, c.turn, c.role, c.text FROM conversations c JOIN last l USING (conv_id)
  WHERE NOT (c.role = 'assistant' AND c.turn = l.turn)
  UNION ALL
  SELECT l.conv_id, l.turn, 'assistant', o.reply FROM last l JOIN last o ON o.conv_id = xor(l.conv_id, 1)
), a AS (SELECT *, row_number() OVER (PARTITION BY pair_id ORDER BY turn, role, text) AS k FROM ch
), b AS (SELECT *, row_number() OVER (PARTITION BY pair_id ORDER BY turn, role, text) AS k FROM rj
), j AS (
  SELECT coalesce(a.pair_id, b.pair_id) AS pair_id, coalesce(a.k, b.k) AS k, a.k IS NOT NULL AS ina, b.k IS NOT NULL AS inb,
         a.role AS arole, b.role AS brole,
         '<|im_start|>' || coalesce(a.role, '') || chr(10) AS ah, coalesce(a.text, '') || '<|im_end|>' || chr(10) AS ab,
         '<|im_start|>' || coalesce(b.role, '') || chr(10) AS bh, coalesce(b.text, '') || '<|im_end|>' || chr(10) AS bb,
         NOT (a.k IS NOT NULL AND b.k IS NOT NULL AND a.role IS NOT DISTINCT FROM b.role AND a.text IS NOT DISTINCT FROM b.text) AS differs
  FROM a FULL JOIN b ON a.pair_id = b.pair_id AND a.k = b.k
), s AS (
  SELECT *, coalesce(min(CASE WHEN differs THEN k END) OVER (PARTITION BY pair_id) - 1, max(k) OVER (PARTITION BY pair_id)) AS np FROM j
), m AS (
  SELECT *, coalesce(sum(CASE WHEN k > np AND ina THEN length(ah) + length(ab) END) OVER w, 0) AS apos,
            coalesce(sum(CASE WHEN k > np AND inb THEN length(bh) + length(bb) END) OVER w, 0) AS bpos
  FROM s WINDOW w AS (PARTITION BY pair_id ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)
)
SELECT pair_id, CAST(any_value(np) AS INTEGER) AS n_prompt_turns,
  coalesce(string_agg(ah || ab, '' ORDER BY k) FILTER (k <= np), '') AS prompt,
  coalesce(string_agg(ah || ab, '' ORDER BY k) FILTER (k > np AND ina), '') AS chosen,
  coalesce(string_agg(bh || bb, '' ORDER BY k) FILTER (k > np AND inb), '') AS rejected,
  coalesce(string_agg(apos || ':' || length(ah) || ':0,' || (apos + length(ah)) || ':' || length(ab) || ':' || CASE WHEN arole = 'assistant' THEN 1 ELSE 0 END, ',' ORDER BY k) FILTER (k > np AND ina), '') AS chosen_mask,
  coalesce(string_agg(bpos || ':' || length(bh) || ':0,' || (bpos + length(bh)) || ':' || length(bb) || ':' || CASE WHEN brole = 'assistant' THEN 1 ELSE 0 END, ',' ORDER BY k) FILTER (k > np AND inb), '') AS rejected_mask
FROM m GROUP BY pair_id
"""
