"""Preference formatting: the longest common turn prefix of a chosen and a rejected conversation becomes the prompt.

A pair of conversations is rendered as one prompt (their common leading turns, once) and two completions (what follows
in each), with the spans of each completion that a trainer should learn: the assistant's turns, with their end mark.

Pairs come from a table of turn lists, or from two makers:
- siblings(): conversations with the same first turn, each paired with the next larger conv_id of its group, the one
  with more assistant characters (tie: the smaller id) as chosen. The successor is found inside blocks of ids first and
  between blocks of a group after, so a first turn that a third of all conversations share is never sorted in one task.
- swapped(): each conversation up to its last assistant turn against itself with that turn's text taken from the next
  conversation of its block of ids (the block's last takes the first's), as is done where no second answer exists.

Defined results: turns go by (turn, role, text), nulls first; a row that repeats another whole counts once; a null
role reads "unknown", a null text is empty; rows with a null conv_id are left out; a conversation that is a prefix of the
other, or equal to it, gives an empty completion with no spans; conversations without an assistant turn are in no
swapped pair; other columns are ignored; an empty table gives an empty result; texts of any length are rendered whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

ID_BLOCK = 4096
TRAINED = "assistant"


def _render(turn: Column) -> Column:
    return F.concat(F.lit("<|"), turn["role"], F.lit("|>\n"), turn["text"], F.lit("<|end|>\n"))


def _text(turns: Column) -> Column:
    return F.array_join(F.transform(turns, _render), "")


def _spans(turns: Column) -> Column:
    """Character spans of the trained turns' bodies and end marks in _text(turns)."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("spans"))

    def step(seen: Column, turn: Column) -> Column:
        body = seen["at"] + F.length(turn["role"]) + 5
        end = body + F.length(turn["text"]) + 8
        more = F.array(F.struct(body.alias("start"), (end - 1).alias("end")))
        return F.struct(end.alias("at"), F.when(turn["role"] == TRAINED, F.concat(seen["spans"], more)).otherwise(seen["spans"]).alias("spans"))

    return F.aggregate(turns, start, step, lambda seen: seen["spans"])


def conversations(turns: DataFrame) -> DataFrame:
    """conv_id and its turns in order."""
    turn = F.struct("turn", F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return turns.where(F.col("conv_id").isNotNull()).groupBy("conv_id").agg(F.array_sort(F.collect_set(turn)).alias("turns"))


def siblings(talks: DataFrame) -> DataFrame:
    """chosen_id, rejected_id and their turns a, b for conversations that share their first turn."""
    said = F.aggregate("turns", F.lit(0).cast("long"), lambda n, t: n + F.when(t["role"] == TRAINED, F.length(t["text"])).otherwise(0))
    first = F.get("turns", F.lit(0))
    heads = talks.select("conv_id", F.md5(F.concat_ws("|", first["role"], F.length(first["role"]), first["text"])).alias("head"), said.alias("said"), F.floor(F.col("conv_id") / ID_BLOCK).alias("block"))
    me = F.struct("conv_id", "said")
    inside = heads.withColumn("next", F.lead(me).over(W.partitionBy("head", "block").orderBy("conv_id")))
    fronts = heads.groupBy("head", "block").agg(F.min(me).alias("front"))
    after = fronts.select("head", "block", F.lead("front").over(W.partitionBy("head").orderBy("block")).alias("after")).where(F.col("after").isNotNull())
    last = inside.where(F.col("next").isNull()).drop("next").join(after, ["head", "block"]).withColumnRenamed("after", "next")
    pairs = inside.where(F.col("next").isNotNull()).unionByName(last)
    wins = F.col("said") >= F.col("next.said")
    ids = pairs.select(F.when(wins, F.col("conv_id")).otherwise(F.col("next.conv_id")).alias("chosen_id"), F.when(wins, F.col("next.conv_id")).otherwise(F.col("conv_id")).alias("rejected_id"))
    return ids.join(talks.select(F.col("conv_id").alias("chosen_id"), F.col("turns").alias("a")), "chosen_id").join(talks.select(F.col("conv_id").alias("rejected_id"), F.col("turns").alias("b")), "rejected_id")


def swapped(talks: DataFrame) -> DataFrame:
    """chosen_id, rejected_id (whose reply is borrowed), a and b for conversations with an assistant turn."""
    answered = F.filter("turns", lambda t: t["role"] == TRAINED)
    turn_numbers = F.sequence(F.lit(1), F.size("turns"))
    last = F.array_max(F.filter(turn_numbers, lambda i: F.get("turns", i - 1)["role"] == TRAINED))
    own = talks.where(F.size(answered) > 0).withColumn("last", last).select("conv_id", F.slice("turns", F.lit(1), F.col("last")).alias("a"), F.floor(F.col("conv_id") / ID_BLOCK).alias("block"))
    me = F.struct("conv_id", F.get("a", F.size("a") - 1)["text"].alias("text"))
    order = W.partitionBy("block").orderBy("conv_id")
    donor = F.coalesce(F.lead(me).over(order), F.first(me).over(order.rowsBetween(W.unboundedPreceding, W.currentRow)))
    final = F.get("a", F.size("a") - 1)
    reply = F.struct(final["turn"].alias("turn"), final["role"].alias("role"), F.col("donor.text").alias("text"))
    b = F.concat(F.slice("a", F.lit(1), F.size("a") - 1), F.array(reply))
    return own.withColumn("donor", donor).select(F.col("conv_id").alias("chosen_id"), F.col("donor.conv_id").alias("rejected_id"), "a", b.alias("b"))


def preference_pairs(pairs: DataFrame) -> DataFrame:
    """chosen_id, rejected_id, n_common, prompt, chosen, rejected and the spans to learn, for pairs with turns a and b."""
    shared = F.least(F.size("a"), F.size("b"))
    same = F.transform(F.arrays_zip("a", "b"), lambda t: F.coalesce((t["a"]["role"] == t["b"]["role"]) & (t["a"]["text"] == t["b"]["text"]), F.lit(False)))
    differs = F.array_position(same, False).cast("int")
    n = F.when(differs == 0, shared).otherwise(differs - 1)
    cut = pairs.withColumn("n_common", n).withColumns({"rest_a": F.slice("a", F.col("n_common") + 1, F.size("a")), "rest_b": F.slice("b", F.col("n_common") + 1, F.size("b"))})
    return cut.select(
        "chosen_id",
        "rejected_id",
        "n_common",
        _text(F.slice("a", F.lit(1), F.col("n_common"))).alias("prompt"),
        _text(F.col("rest_a")).alias("chosen"),
        _text(F.col("rest_b")).alias("rejected"),
        _spans(F.col("rest_a")).alias("chosen_spans"),
        _spans(F.col("rest_b")).alias("rejected_spans"),
    )


def formatted(turns: DataFrame) -> DataFrame:
    """Sibling and swapped pairs of a table of turns(conv_id, turn, role, text), told apart by the column made_by."""
    talks = conversations(turns)
    return preference_pairs(siblings(talks)).withColumn("made_by", F.lit("sibling")).unionAll(preference_pairs(swapped(talks)).withColumn("made_by", F.lit("swap")))


def digest(found: DataFrame) -> DataFrame:
    """Spans as text, so that tables compare by value."""
    as_text = lambda c: F.array_join(F.transform(c, lambda s: F.concat_ws("-", s["start"], s["end"])), ",")
    return found.withColumns({c: as_text(c) for c in ("chosen_spans", "rejected_spans")})


ORACLE = f"""
WITH t AS (
  SELECT DISTINCT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text FROM conversations WHERE conv_id IS NOT NULL
), n AS (
  SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text) AS k FROM t
), heads AS (
  SELECT conv_id, max(CASE WHEN k = 1 THEN role END) AS role, max(CASE WHEN k = 1 THEN text END) AS text,
         sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS said FROM n GROUP BY conv_id
), nexts AS (
  SELECT conv_id, said, lead(conv_id) OVER w AS next_id, lead(said) OVER w AS next_said FROM heads WINDOW w AS (PARTITION BY role, text ORDER BY conv_id)
), replies AS (
  SELECT conv_id, max(k) AS last_k, max_by(text, k) AS reply FROM n WHERE role = 'assistant' GROUP BY conv_id
), donors AS (
  SELECT conv_id, last_k, coalesce(lead(conv_id) OVER w, first_value(conv_id) OVER w) AS donor_id, coalesce(lead(reply) OVER w, first_value(reply) OVER w) AS donor_reply
  FROM replies WINDOW w AS (PARTITION BY floor(conv_id / {ID_BLOCK}) ORDER BY conv_id)
), pairs AS (
  SELECT 'sibling' AS made_by, CASE WHEN said >= next_said THEN conv_id ELSE next_id END AS chosen_id,
         CASE WHEN said >= next_said THEN next_id ELSE conv_id END AS rejected_id FROM nexts WHERE next_id IS NOT NULL
  UNION ALL SELECT 'swap', conv_id, donor_id FROM donors
), sides AS (
  SELECT p.made_by, p.chosen_id, p.rejected_id, 'a' AS side, n.k, n.role, n.text FROM pairs p JOIN n ON n.conv_id = p.chosen_id
    LEFT JOIN donors d ON d.conv_id = p.chosen_id WHERE p.made_by = 'sibling' OR n.k <= d.last_k
  UNION ALL
  SELECT p.made_by, p.chosen_id, p.rejected_id, 'b', n.k, n.role, n.text FROM pairs p JOIN n ON n.conv_id = p.rejected_id WHERE p.made_by = 'sibling'
  UNION ALL
  SELECT 'swap', d.conv_id, d.donor_id, 'b', n.k, n.role, CASE WHEN n.k = d.last_k THEN d.donor_reply ELSE n.text END FROM donors d JOIN n ON n.conv_id = d.conv_id AND n.k <= d.last_k
), common AS (
  SELECT a.made_by, a.chosen_id, a.rejected_id, coalesce(min(CASE WHEN b.k IS NULL OR a.role <> b.role OR a.text <> b.text THEN a.k END) - 1, max(a.k)) AS n_common
  FROM sides a LEFT JOIN sides b ON b.side = 'b' AND b.made_by = a.made_by AND b.chosen_id = a.chosen_id AND b.rejected_id = a.rejected_id AND b.k = a.k
  WHERE a.side = 'a' GROUP BY ALL
), sized AS (
  SELECT c.*, s.side, s.k, s.role, s.text, '<|' || s.role || '|>' || chr(10) || s.text || '<|end|>' || chr(10) AS body,
         coalesce(sum(CASE WHEN s.k > c.n_common THEN length(s.role) + length(s.text) + 13 ELSE 0 END)
           OVER (PARTITION BY c.made_by, c.chosen_id, c.rejected_id, s.side ORDER BY s.k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before
  FROM common c JOIN sides s USING (made_by, chosen_id, rejected_id)
), spanned AS (
  SELECT *, CAST(before + length(role) + 5 AS BIGINT) || '-' || CAST(before + length(role) + length(text) + 12 AS BIGINT) AS span FROM sized
)
SELECT made_by, chosen_id, rejected_id, CAST(n_common AS INTEGER) AS n_common,
  coalesce(string_agg(body, '' ORDER BY k) FILTER (WHERE side = 'a' AND k <= n_common), '') AS prompt,
  coalesce(string_agg(body, '' ORDER BY k) FILTER (WHERE side = 'a' AND k > n_common), '') AS chosen,
  coalesce(string_agg(body, '' ORDER BY k) FILTER (WHERE side = 'b' AND k > n_common), '') AS rejected,
  coalesce(string_agg(span, ',' ORDER BY k) FILTER (WHERE side = 'a' AND k > n_common AND role = 'assistant'), '') AS chosen_spans,
  coalesce(string_agg(span, ',' ORDER BY k) FILTER (WHERE side = 'b' AND k > n_common AND role = 'assistant'), '') AS rejected_spans
FROM spanned GROUP BY made_by, chosen_id, rejected_id, n_common
"""
