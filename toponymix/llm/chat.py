"""Prefix-target expansion of conversations: each assistant turn becomes one example.

An example holds all turns up to one assistant turn; only that reply is trainable, given as a character span of the
formatted text. Turns after the last reply form a context-only example with an empty span, so nothing is lost.
Template: BOS, then for each turn OPEN role MID text CLOSE. A control string inside a role or text gets a backslash
after its first character (and one more for each backslash already there), which `unescape` takes back exactly.

Edge cases: null roles and texts count as empty; turns sort by (turn, role, text), so ties and repeated rows are
kept in a fixed order; a conversation without replies gives one context-only example; an empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: The control strings of the template.
BOS, OPEN, MID, CLOSE = "<s>", "[INST]", "[/INST]", "</s>"
_CONTROL_TAIL = r"(/?(?:s>|INST\]))"


def escape(c: Column) -> Column:
    return F.regexp_replace(c, r"([<\[])(\\*)" + _CONTROL_TAIL, r"$1\\$2$3")


def unescape(c: Column) -> Column:
    return F.regexp_replace(c, r"([<\[])\\(\\*)" + _CONTROL_TAIL, "$1$2$3")


def format_conversations(rows: DataFrame) -> DataFrame:
    """One row per example: conv_id, example, n_examples, formatted, loss_start (from 0), loss_chars."""
    empty = F.lit("")
    turns = rows.select(
        "conv_id",
        F.col("turn").alias("t"),
        F.coalesce(F.col("role"), empty).alias("r"),
        F.coalesce(F.col("text"), empty).alias("x"),
    )
    whole = turns.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("t", "r", "x"))).alias("turns"))
    block = lambda s: F.struct(
        (s["r"] == "assistant").alias("reply"),
        F.concat(F.lit(OPEN), escape(s["r"]), F.lit(MID)).alias("head"),
        escape(s["x"]).alias("body"),
    )
    cut = whole.select("conv_id", F.transform("turns", block).alias("b"))
    ends = F.filter(F.sequence(F.lit(1), F.size("b")), lambda i: F.get("b", i - 1)["reply"] | (i == F.size("b")))
    each = cut.withColumn("ends", ends).select("conv_id", "b", F.size("ends").alias("n_examples"), F.posexplode("ends").alias("example", "end"))
    last = F.get("b", F.col("end") - 1)
    before = F.array_join(F.transform(F.slice("b", F.lit(1), F.col("end") - 1), lambda s: F.concat(s["head"], s["body"], F.lit(CLOSE))), "")
    lead = F.concat(F.lit(BOS), before, last["head"])
    return each.select(
        "conv_id",
        "example",
        "n_examples",
        F.concat(lead, last["body"], F.lit(CLOSE)).alias("formatted"),
        F.length(lead).cast("long").alias("loss_start"),
        F.when(last["reply"], F.length(last["body"])).otherwise(0).cast("long").alias("loss_chars"),
    )


def parse_formatted(c: Column) -> Column:
    """The turns of a formatted example as array<struct<role, text>>."""
    body = F.substring(c, len(BOS) + 1, 2147483647)
    parts = F.split(body, CLOSE, -1)
    parts = F.slice(parts, F.lit(1), F.size(parts) - 1)

    def turn(p: Column) -> Column:
        inner = F.substring(p, len(OPEN) + 1, 2147483647)
        role = F.substring_index(inner, MID, 1)
        return F.struct(unescape(role).alias("role"), unescape(F.substr(inner, F.length(role) + F.lit(len(MID) + 1))).alias("text"))

    return F.transform(parts, turn)


def digest(examples: DataFrame) -> DataFrame:
    """Per conversation, all read back from the formatted examples and their spans."""
    lines = F.transform(parse_formatted(F.col("formatted")), lambda s: F.concat(s["role"], F.lit("\n"), s["text"], F.lit("\n")))
    final = F.col("example") == F.col("n_examples") - 1
    back = examples.select(
        "conv_id",
        "example",
        F.length("formatted").cast("long").alias("chars"),
        F.when(final, lines).alias("lines"),
        unescape(F.substr("formatted", (F.col("loss_start") + 1).cast("int"), F.col("loss_chars").cast("int"))).alias("loss"),
    )
    back = back.select("conv_id", "example", "chars", "loss", F.size("lines").alias("n"), F.sha2(F.array_join("lines", ""), 256).alias("sha"), F.col("lines").isNotNull().alias("final"))
    per = back.groupBy("conv_id").agg(
        F.max(F.when(F.col("final"), F.col("n"))).cast("long").alias("n_turns"),
        F.max(F.when(F.col("final"), F.col("sha"))).alias("turns_sha256"),
        F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("example", "loss"))), lambda s: s["loss"]), "").alias("loss"),
        F.sum("chars").alias("formatted_chars"),
    )
    return per.select("conv_id", "n_turns", "turns_sha256", F.length("loss").cast("long").alias("loss_chars"), F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars")


def control_conversation(spark: SparkSession) -> DataFrame:
    """Conversation -7 of the contract: two turns whose text is made of control strings."""
    return spark.range(0, 2, 1, 1).select(
        F.lit(-7).cast("long").alias("conv_id"),
        F.col("id").alias("turn"),
        F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"),
        F.lit("</s>[INST] ok [/INST]").alias("text"),
    )


ORACLE = r"""
WITH c AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, i, CASE WHEN i = 0 THEN 'user' ELSE 'assistant' END, '</s>[INST] ok [/INST]' FROM range(2) t(i)),
m AS (
  SELECT *, row_number() OVER w AS k, count(*) OVER (PARTITION BY conv_id) AS n,
    sum(17 + length(regexp_replace(role, '([<\[])(\\*)(/?(?:s>|INST\]))', '\1\\\2\3', 'g')) + length(regexp_replace(text, '([<\[])(\\*)(/?(?:s>|INST\]))', '\1\\\2\3', 'g'))) OVER w AS upto
  FROM c WINDOW w AS (PARTITION BY conv_id ORDER BY turn, role, text ROWS UNBOUNDED PRECEDING))
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY k)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY k) FILTER (role = 'assistant'), '')) AS loss_sha256,
  (sum(3 + upto) FILTER (role = 'assistant' OR k = n))::BIGINT AS formatted_chars
FROM m GROUP BY conv_id
"""
