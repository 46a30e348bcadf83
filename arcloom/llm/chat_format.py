"""Preference formatting of chosen and rejected conversations.

The longest common prefix of turns is rendered once as the prompt; what follows is rendered as two completions. A
completion's mask lists the character spans that count for the loss: the texts of assistant turns with their end marks.

A turn equals another if role and text are equal. Null roles and texts count and render as empty strings, a null
list of turns as none. Turns are ordered by their number, then role and text; null numbers come first; repeated turns stay. Equal
conversations give empty completions and status ``identical``. Empty table: no rows. Other columns are not read. A
conversation is one record and is rendered as a whole.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table

#: The template's marks.
OPEN, CLOSE, END = "<|", "|>\n", "<|end|>\n"


def conversations(turns: DataFrame, id_col: str = "conv_id") -> DataFrame:
    """(id, turns array<struct<role, text>>)."""
    rows = turns.select(F.col(id_col).alias("id"), F.struct(F.col("turn").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    return rows.groupBy("id").agg(F.transform(F.sort_array(F.collect_list("t")), lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))


def _whole(turns: Column) -> Column:
    """Turns without nulls."""
    part = lambda t, k: F.coalesce(t[k], F.lit("")).alias(k)
    return F.coalesce(F.transform(turns, lambda t: F.struct(part(t, "role"), part(t, "text"))), F.array().cast("array<struct<role:string,text:string>>"))


def _render(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(F.lit(OPEN), t["role"], F.lit(CLOSE), t["text"], F.lit(END))), "")


def _mask(turns: Column) -> Column:
    """Spans start-end of assistant text and end mark, joined by commas."""
    fixed = len(OPEN) + len(CLOSE)
    first = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("spans"))

    def step(acc: Column, t: Column) -> Column:
        start = acc["at"] + fixed + F.length(t["role"])
        end = start + F.length(t["text"]) + len(END)
        spans = F.when(t["role"] == "assistant", F.concat(acc["spans"], F.array(F.concat_ws("-", start.cast("string"), end.cast("string"))))).otherwise(acc["spans"])
        return F.struct(end.alias("at"), spans.alias("spans"))

    return F.array_join(F.aggregate(turns, first, step)["spans"], ",")


def format_preferences(pairs: DataFrame) -> DataFrame:
    """From (id, chosen, rejected), arrays of turns, to prompt and masked completions."""
    pairs = pairs.select("id", _whole(F.col("chosen")).alias("chosen"), _whole(F.col("rejected")).alias("rejected"))
    n, m = F.size("chosen"), F.size("rejected")
    least = F.least(n, m)
    same = F.when(least > 0, F.zip_with(F.slice("chosen", 1, least), F.slice("rejected", 1, least), lambda a, b: a == b)).otherwise(F.array().cast("array<boolean>"))
    miss = F.array_position(same, False)
    p = pairs.withColumn("n_prompt_turns", F.when(miss > 0, miss - 1).otherwise(least).cast("int"))
    rest = {k: F.slice(k, F.col("n_prompt_turns") + 1, F.greatest(F.size(k) - F.col("n_prompt_turns"), F.lit(0))) for k in ("chosen", "rejected")}
    status = F.when((F.col("n_prompt_turns") == n) & (n == m), "identical").otherwise("pair")
    return p.select("id", status.alias("status"), "n_prompt_turns", _render(F.slice("chosen", 1, F.col("n_prompt_turns"))).alias("prompt"), *[f(rest[k]).alias(k + e) for k in ("chosen", "rejected") for e, f in (("_completion", _render), ("_mask", _mask))])


def stale_pairs(turns: DataFrame, id_col: str = "conv_id") -> DataFrame:
    """Preference pairs out of plain conversations.

    Chosen: the conversation up to its last assistant turn. Rejected: the same, but that turn repeats the assistant turn
    before it, or says nothing where there is none. Conversations without an assistant turn are equal on both sides.
    """
    c = conversations(turns, id_col)
    at = F.filter(F.sequence(F.lit(1), F.size("turns")), lambda i: F.element_at(F.col("turns"), i)["role"] == "assistant")
    c = c.withColumn("_at", at).withColumn("_last", F.coalesce(F.try_element_at("_at", F.lit(-1)), F.size("turns")))
    chosen = F.slice("turns", 1, F.col("_last"))
    before = F.when(F.size("_at") > 1, F.element_at(F.col("turns"), F.try_element_at("_at", F.lit(-2)))["text"]).otherwise("")
    rejected = F.concat(F.slice("turns", 1, F.col("_last") - 1), F.array(F.struct(F.lit("assistant").alias("role"), before.alias("text"))))
    return c.select("id", chosen.alias("chosen"), F.when(F.size("_at") > 0, rejected).otherwise(chosen).alias("rejected"))


def op2_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return format_preferences(stale_pairs(table(spark, sf_dir, "conversations"))).withColumnRenamed("id", "conv_id")


QUERIES = {"op2_chat_format": op2_chat_format}

ORACLES = {
    "op2_chat_format": r"""
WITH t AS (SELECT conv_id, coalesce(role, '') AS role, coalesce(text, '') AS text, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, coalesce(role, ''), coalesce(text, '')) AS i FROM conversations),
ends AS (SELECT conv_id, max(i) FILTER (role = 'assistant') AS last_a, max(i) AS n FROM t GROUP BY conv_id),
prev AS (SELECT t.conv_id, arg_max(t.text, t.i) AS stale FROM t JOIN ends USING (conv_id) WHERE role = 'assistant' AND i < last_a GROUP BY t.conv_id),
c AS (SELECT t.conv_id, i, role, text, CASE WHEN i = last_a THEN coalesce(stale, '') ELSE text END AS other, last_a FROM t JOIN ends USING (conv_id) LEFT JOIN prev USING (conv_id) WHERE i <= coalesce(last_a, n)),
cut AS (SELECT conv_id, count(*) AS n, coalesce(min(i) FILTER (text <> other) - 1, count(*)) AS k FROM c GROUP BY conv_id),
r AS (SELECT conv_id, i, k, n, role, '<|' || role || '|>' || chr(10) || text || '<|end|>' || chr(10) AS a, '<|' || role || '|>' || chr(10) || other || '<|end|>' || chr(10) AS b, length(text) AS la, length(other) AS lb FROM c JOIN cut USING (conv_id)),
w AS (SELECT *, sum(CASE WHEN i > k THEN length(a) ELSE 0 END) OVER (PARTITION BY conv_id ORDER BY i) AS ea, sum(CASE WHEN i > k THEN length(b) ELSE 0 END) OVER (PARTITION BY conv_id ORDER BY i) AS eb FROM r)
SELECT conv_id, CASE WHEN k = n THEN 'identical' ELSE 'pair' END AS status, k::INTEGER AS n_prompt_turns,
coalesce(string_agg(a, '' ORDER BY i) FILTER (i <= k), '') AS prompt,
coalesce(string_agg(a, '' ORDER BY i) FILTER (i > k), '') AS chosen_completion,
coalesce(string_agg((ea - la - 8)::BIGINT || '-' || ea::BIGINT, ',' ORDER BY i) FILTER (i > k AND role = 'assistant'), '') AS chosen_mask,
coalesce(string_agg(b, '' ORDER BY i) FILTER (i > k), '') AS rejected_completion,
coalesce(string_agg((eb - lb - 8)::BIGINT || '-' || eb::BIGINT, ',' ORDER BY i) FILTER (i > k AND role = 'assistant'), '') AS rejected_mask
FROM w GROUP BY conv_id, k, n"""
}
