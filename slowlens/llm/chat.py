"""Chat formatting by relational expressions only: turns are collected, sorted, merged and joined inside the JVM.

Template: a block of adjacent turns of one role reads
    <s>[ROLE]role[INST]text[PART]text[/INST]</s>
and a conversation is its blocks one after the other. Control strings inside roles and texts get a backslash after
their first character (and one more if they have some already), which is undone exactly on reading.

Cases: null role or text counts as empty; rows of equal turn go by role, then text; repeated rows stay; an empty table
gives no rows; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from slowlens.llm.common import table

OPEN, HEAD, PART, CLOSE = "<s>[ROLE]", "[INST]", "[PART]", "[/INST]</s>"
_TAILS = r"(/?s>|/?INST\]|ROLE\]|PART\])"


def escaped(c: Column) -> Column:
    return F.regexp_replace(c, rf"([<\[])(\\*){_TAILS}", r"$1$2\\$3")


def unescaped(c: Column) -> Column:
    return F.regexp_replace(c, rf"([<\[])(\\*)\\{_TAILS}", "$1$2$3")


def format_conversations(rows: DataFrame, learn_role: str = "assistant") -> DataFrame:
    """(conv_id, turn, role, text) -> (conv_id, formatted, loss): loss lists the spans to learn from, start and end in
    code points and in bytes, end exclusive, one for each turn of `learn_role`."""
    clean = rows.select("conv_id", "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    turns = clean.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))

    def piece(x: Column, i: Column) -> Column:
        """What stands before the text of turn i, and the text."""
        first = i == 0
        fresh = first | (F.element_at("turns", F.greatest(i, F.lit(1))).getField("role") != x["role"])
        header = F.concat(F.lit(OPEN), escaped(x["role"]), F.lit(HEAD))
        lead = F.when(first, header).when(fresh, F.concat(F.lit(CLOSE), header)).otherwise(F.lit(PART))
        return F.struct(lead.alias("lead"), escaped(x["text"]).alias("body"), (x["role"] == learn_role).alias("learn"))

    pieces = turns.select("conv_id", F.transform("turns", piece).alias("pieces"))
    empty = F.array().cast("array<struct<start:bigint,end:bigint,byte_start:bigint,byte_end:bigint>>")

    def grow(state: Column, p: Column) -> Column:
        at = state["at"] + F.length(p["lead"])
        byte_at = state["byte_at"] + F.octet_length(p["lead"])
        end, byte_end = at + F.length(p["body"]), byte_at + F.octet_length(p["body"])
        span = F.struct(at.alias("start"), end.alias("end"), byte_at.alias("byte_start"), byte_end.alias("byte_end"))
        spans = F.when(p["learn"], F.concat(state["spans"], F.array(span))).otherwise(state["spans"])
        return F.struct(end.alias("at"), byte_end.alias("byte_at"), spans.alias("spans"))

    start = F.struct(F.lit(0).cast("bigint").alias("at"), F.lit(0).cast("bigint").alias("byte_at"), empty.alias("spans"))
    return pieces.select(
        "conv_id",
        F.concat(F.array_join(F.transform("pieces", lambda p: F.concat(p["lead"], p["body"])), ""), F.lit(CLOSE)).alias("formatted"),
        F.aggregate("pieces", start, grow, lambda s: s["spans"]).alias("loss"),
    )


def read_back(formatted: DataFrame) -> DataFrame:
    """Undo the template: conv_id, turns (role, text) in order, and loss_text, the unescaped text under the loss mask."""
    blocks = F.slice(F.split("formatted", r"\Q" + CLOSE + r"\E", -1), 1, F.size(F.split("formatted", r"\Q" + CLOSE + r"\E", -1)) - 1)

    def turns_of(b: Column) -> Column:
        at = F.instr(b, HEAD)
        role = unescaped(F.substring(b, F.lit(len(OPEN) + 1), at - len(OPEN) - 1))
        parts = F.split(F.substring(b, at + len(HEAD), F.length(b)), r"\Q" + PART + r"\E", -1)
        return F.transform(parts, lambda t: F.struct(role.alias("role"), unescaped(t).alias("text")))

    raw = F.encode("formatted", "UTF-8")
    under = F.transform("loss", lambda s: unescaped(F.decode(F.substring("_raw", (s["byte_start"] + 1).cast("int"), (s["byte_end"] - s["byte_start"]).cast("int")), "UTF-8")))
    return formatted.withColumn("_raw", raw).select(
        "conv_id", "formatted", F.flatten(F.transform(blocks, turns_of)).alias("turns"), F.array_join(under, "").alias("loss_text")
    )


def op9_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All conversations and conversation -7, formatted, read back and digested."""
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.sql("select cast(v.c as bigint) conv_id, cast(v.t as bigint) turn, v.r role, '</s>[INST] ok [/INST]' text from values (-7, 0, 'user'), (-7, 1, 'assistant') as v(c, t, r)")
    back = read_back(format_conversations(rows.unionByName(probe)))
    lines = F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n")))
    return back.select(
        "conv_id",
        F.size("turns").cast("bigint").alias("n_turns"),
        F.sha2(F.array_join(lines, "").cast("binary"), 256).alias("turns_sha256"),
        F.length("loss_text").cast("bigint").alias("loss_chars"),
        F.sha2(F.col("loss_text").cast("binary"), 256).alias("loss_sha256"),
        F.length("formatted").cast("bigint").alias("formatted_chars"),
    )


OP9_SQL = r"""
WITH t AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]'
  UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'
), e AS (
  SELECT *, length(regexp_replace(text, '([<\[])(\\*)(/?s>|/?INST\]|ROLE\]|PART\])', '\1\2\\\3', 'g')) AS body,
    length(regexp_replace(role, '([<\[])(\\*)(/?s>|/?INST\]|ROLE\]|PART\])', '\1\2\\\3', 'g')) AS head,
    lag(role) OVER (PARTITION BY conv_id ORDER BY turn, role, text) AS prev
  FROM t
)
SELECT conv_id, CAST(count(*) AS BIGINT) AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  CAST(length(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  CAST(sum(body + CASE WHEN prev IS NOT DISTINCT FROM role THEN 6 ELSE head + 9 + 6 + 11 END) AS BIGINT) AS formatted_chars
FROM e GROUP BY conv_id
"""
