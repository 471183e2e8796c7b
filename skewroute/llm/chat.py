"""Prefix-target chat examples, in DataFrame functions alone.

Every assistant turn becomes an example: all turns before it are the context, and only the text of that reply is under the
loss mask. A conversation that does not end with a reply has one more example without a target, so that nothing of it
is lost. Turns are marked ``[INST] text [/INST]`` (user), ``<s>text</s>`` (assistant) and
``<<SYS>>role⏎text<</SYS>>`` (any other role, URL-encoded). A mark inside a text is escaped by a backslash after its first
character, and one that has backslashes there gets one more, so that taking one away undoes it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from skewroute.llm.common import read_table

# Fixed values of the template: what follows the first character of a mark.
_REST = r"(?=s>|/s>|<SYS>>|</SYS>>|INST\]|/INST\])"
_TURN = r"(?s)\[INST\] .*? \[/INST\]|<s>.*?</s>|<<SYS>>.*?<</SYS>>"
#: A conversation of control strings only, formatted beside the table by the query.
PROBE = r"</s>[INST] ok [/INST]"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"([<\[])(\\*)" + _REST, r"$1\\$2")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"([<\[])\\(\\*)" + _REST, "$1$2")


def format_turn(role: Column, text: Column) -> Column:
    other = F.concat(F.lit("<<SYS>>"), F.url_encode(role), F.lit("\n"), escape(text), F.lit("<</SYS>>"))
    user = F.concat(F.lit("[INST] "), escape(text), F.lit(" [/INST]"))
    return F.when(role == "user", user).when(role == "assistant", F.concat(F.lit("<s>"), escape(text), F.lit("</s>"))).otherwise(other)


def examples(conversations: DataFrame) -> DataFrame:
    """``(conv_id, example, n_examples, context, target, loss_start, loss_end)`` of ``(conv_id, turn, role, text)``.

    Turns go by ``turn``, rows that tie by role and text, null turns first. Null roles and texts are empty strings; rows
    with a null ``conv_id`` are one conversation. The loss covers code points ``loss_start`` to ``loss_end`` (exclusive)
    of context and target put together; an example without a target has an empty mask. An empty table gives an empty
    table; other columns are not read.
    """
    turn = F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    whole = conversations.groupBy("conv_id").agg(F.array_sort(F.collect_list(turn)).alias("t"))
    pieces = whole.select("conv_id", F.transform("t", format_one).alias("p"), F.transform("t", lambda x: x["role"] == "assistant").alias("reply"))
    ends = F.filter(F.sequence(F.lit(1), F.size("p")), lambda i: F.element_at("reply", i) | (i == F.size("p")))
    each = pieces.withColumn("ends", ends).select("conv_id", "p", "reply", F.size("ends").alias("n_examples"), F.posexplode("ends").alias("example", "end"))
    is_reply = F.element_at("reply", F.col("end"))
    before = F.col("end") - F.when(is_reply, 1).otherwise(0)
    out = each.select(
        "conv_id", "example", "n_examples",
        F.array_join(F.slice("p", F.lit(1), before), "").alias("context"),
        F.when(is_reply, F.element_at("p", F.col("end"))).alias("target"),
    )
    start = F.length("context") + F.when(F.col("target").isNull(), 0).otherwise(len("<s>"))
    return out.withColumn("loss_start", start).withColumn("loss_end", F.when(F.col("target").isNull(), start).otherwise(F.length("context") + F.length("target") - len("</s>")))


def format_one(x: Column) -> Column:
    return format_turn(x["role"], x["text"])


def parse(formatted: Column) -> Column:
    """The turns of a formatted text: an array of ``(role, text)``."""

    def turn(x: Column) -> Column:
        system = x.startswith("<<SYS>>")
        inner = F.when(system, x.substr(F.lit(8), F.length(x) - 15)).when(x.startswith("<s>"), x.substr(F.lit(4), F.length(x) - 7)).otherwise(x.substr(F.lit(8), F.length(x) - 15))
        role = F.when(system, F.url_decode(F.substring_index(inner, "\n", 1))).when(x.startswith("<s>"), "assistant").otherwise("user")
        text = F.when(system, inner.substr(F.instr(inner, F.lit("\n")) + 1, F.length(inner))).otherwise(inner)
        return F.struct(role.alias("role"), unescape(text).alias("text"))

    return F.transform(F.regexp_extract_all(formatted, F.lit(_TURN), F.lit(0)), turn)


def read_back(formatted: DataFrame) -> DataFrame:
    """What the examples of each conversation say, by themselves: turns from the last one, losses from all in order."""
    full = F.concat("context", F.coalesce("target", F.lit("")))
    last = F.col("example") == F.col("n_examples") - 1
    turns = F.when(last, parse(full))
    rows = formatted.select(
        "conv_id", "example", F.length(full).cast("long").alias("chars"),
        F.size(turns).cast("long").alias("n"),
        F.sha2(F.array_join(F.transform(turns, lambda x: F.concat(x["role"], F.lit("\n"), x["text"], F.lit("\n"))), ""), 256).alias("sha"),
        unescape(full.substr(F.col("loss_start") + 1, F.col("loss_end") - F.col("loss_start"))).alias("loss"),
    )
    told = rows.groupBy("conv_id").agg(
        F.max("n").alias("n_turns"), F.max("sha").alias("turns_sha256"), F.sum(F.length("loss")).cast("long").alias("loss_chars"),
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("example", "loss"))), lambda x: x["loss"]), "").alias("all"), F.sum("chars").alias("formatted_chars"),
    )
    return told.select("conv_id", "n_turns", "turns_sha256", "loss_chars", F.sha2("all", 256).alias("loss_sha256"), "formatted_chars")


def op5_chat(spark: SparkSession, sf_dir: str) -> DataFrame:
    table = read_table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(F.lit(-7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(PROBE).alias("text"))
    return read_back(examples(table.unionByName(probe)))


ORACLE = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, turn, role, '</s>[INST] ok [/INST]' FROM (VALUES (0, 'user'), (1, 'assistant')) AS v(turn, role)),
o AS (
  SELECT *, row_number() OVER w AS i, count(*) OVER (PARTITION BY conv_id) AS n,
    length(text) + len(regexp_extract_all(text, '[<\[]\\*(s>|/s>|<SYS>>|</SYS>>|INST\]|/INST\])'))
      + CASE role WHEN 'user' THEN 15 WHEN 'assistant' THEN 7 ELSE 16 + length(url_encode(role)) END AS chars
  FROM c WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)),
r AS (SELECT *, sum(chars) OVER (PARTITION BY conv_id ORDER BY i) AS upto FROM o)
SELECT conv_id, count(*)::BIGINT AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY i)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY i) FILTER (role = 'assistant'), '')) AS loss_sha256,
  (sum(upto) FILTER (role = 'assistant' OR i = n))::BIGINT AS formatted_chars
FROM r GROUP BY conv_id
"""
