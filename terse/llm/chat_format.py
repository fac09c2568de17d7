"""Chat formatting by prefix-target expansion: every assistant turn becomes an example of its own.

An example holds all preceding turns as context and one reply, of which alone the characters are trainable.  Turns are
written as ``<|im_start|>role<|im_sep|>text<|im_end|>``.  Control strings inside roles and texts are escaped: a backslash goes
in after their first character, and one more where there are some already, so unescaping is exact.

A conversation that ends in another role than the assistant gets one more example without target, so that every turn can be
read back.  SQL expressions only; a conversation is one row after one shuffle by its id (the expansion itself is quadratic in
its turns, as the method has it).

Defined cases: null role or text is empty; turns that tie are ordered by role, then text; repeated rows are turns of their own;
a null conversation id is a conversation; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# fixed values: the marks of this template, and those of other public templates, which are escaped as well
OPEN, SEP, CLOSE = "<|im_start|>", "<|im_sep|>", "<|im_end|>"
CONTROL = r"(<)(\\*)(\|im_start\|>|\|im_sep\|>|\|im_end\|>|\|endoftext\|>|/?s>|</?SYS>>)"
BRACKETS = r"(\[)(\\*)(/?INST\])"
ESCAPED = r"(<)\\(\\*)(\|im_start\|>|\|im_sep\|>|\|im_end\|>|\|endoftext\|>|/?s>|</?SYS>>)"
ESCAPED_BRACKETS = r"(\[)\\(\\*)(/?INST\])"


def escape(text: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(text, CONTROL, r"$1\\$2$3"), BRACKETS, r"$1\\$2$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(F.regexp_replace(text, ESCAPED_BRACKETS, "$1$2$3"), ESCAPED, "$1$2$3")


def format_conversations(turns: DataFrame, target_role: str = "assistant") -> DataFrame:
    """Examples (conv_id, target, text, loss_start, loss_chars): target is the reply's place among the turns (from 0; -1: none),
    loss_start and loss_chars the span of trainable code points."""
    whole = (
        turns.select("conv_id", F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
        .groupBy("conv_id")
        .agg(F.sort_array(F.collect_list("t")).alias("t"))
        .select(
            "conv_id",
            F.transform("t", lambda x: F.struct((x["role"] == target_role).alias("reply"), F.concat(F.lit(OPEN), escape(x["role"]), F.lit(SEP)).alias("head"), escape(x["text"]).alias("body"))).alias("t"),
        )
    )
    places = F.filter(F.sequence(F.lit(0), F.size("t") - 1), lambda i: F.get(F.col("t"), i)["reply"])
    targets = F.concat(places, F.when(F.element_at("t", -1)["reply"], F.array().cast("array<int>")).otherwise(F.array(F.lit(-1))))
    rendered = F.transform("t", lambda x: F.concat(x["head"], x["body"], F.lit(CLOSE)))
    expanded = whole.select("conv_id", "t", rendered.alias("r"), F.explode(targets).alias("target"))
    chosen = F.get(F.col("t"), F.col("target"))
    context = F.when(F.col("target") < 0, F.array_join("r", "")).otherwise(F.concat(F.array_join(F.slice("r", 1, F.greatest("target", F.lit(0))), ""), chosen["head"]))
    return (
        expanded.select("conv_id", "target", context.alias("context"), F.coalesce(chosen["body"], F.lit("")).alias("body"))
        .select(
            "conv_id",
            "target",
            F.when(F.col("target") < 0, F.col("context")).otherwise(F.concat("context", "body", F.lit(CLOSE))).alias("text"),
            F.when(F.col("target") < 0, 0).otherwise(F.char_length("context")).alias("loss_start"),
            F.char_length("body").alias("loss_chars"),
        )
    )


def parse_turns(text: Column) -> Column:
    """The turns of a formatted example: array of (role, text), unescaped."""
    pieces = F.filter(F.split(text, r"<\|im_end\|>"), lambda p: p != "")
    return F.transform(
        pieces,
        lambda p: F.struct(
            unescape(F.substring_index(p.substr(F.lit(len(OPEN) + 1), F.char_length(p)), SEP, 1)).alias("role"),
            unescape(F.substring_index(p, SEP, -1)).alias("text"),
        ),
    )


def read_back(examples: DataFrame) -> DataFrame:
    """Per conversation, from the examples alone: n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars."""
    reply = unescape(F.substring("text", F.col("loss_start") + 1, F.col("loss_chars")))
    per = examples.select(
        "conv_id",
        F.char_length("text").cast("long").alias("chars"),
        F.struct(F.char_length("text").alias("n"), F.col("text")).alias("longest"),
        F.struct("target", reply.alias("reply")).alias("reply"),
    ).groupBy("conv_id").agg(
        F.max("longest")["text"].alias("text"),
        F.transform(F.sort_array(F.filter(F.collect_list("reply"), lambda r: r["target"] >= 0)), lambda r: r["reply"]).alias("replies"),
        F.sum("chars").alias("formatted_chars"),
    )
    parsed = per.select("conv_id", "formatted_chars", parse_turns(F.col("text")).alias("turns"), F.array_join("replies", "").alias("loss"))
    listed = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return parsed.select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(listed.cast("binary"), 256).alias("turns_sha256"),
        F.char_length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        F.col("formatted_chars").cast("long").alias("formatted_chars"),
    )


PROBE = "</s>[INST] ok [/INST]"


def op3_query(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = spark.read.parquet(f"{sf_dir}/conversations.parquet").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(
        F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit(PROBE).alias("text")
    )
    return read_back(format_conversations(turns.unionByName(probe)))


OP3_SQL = r"""
WITH turns AS (
  SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'
), escaped AS (
  SELECT *, regexp_replace(regexp_replace(role, '(<)(\\*)(\|im_start\|>|\|im_sep\|>|\|im_end\|>|\|endoftext\|>|/?s>|</?SYS>>)', '\1\\\2\3', 'g'), '(\[)(\\*)(/?INST\])', '\1\\\2\3', 'g') AS erole,
    regexp_replace(regexp_replace(text, '(<)(\\*)(\|im_start\|>|\|im_sep\|>|\|im_end\|>|\|endoftext\|>|/?s>|</?SYS>>)', '\1\\\2\3', 'g'), '(\[)(\\*)(/?INST\])', '\1\\\2\3', 'g') AS etext FROM turns
), placed AS (
  SELECT *, sum(12 + length(erole) + 10 + length(etext) + 10) OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text ROWS UNBOUNDED PRECEDING) AS upto,
    row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC NULLS LAST, role DESC, text DESC) = 1 AS last FROM escaped
)
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn NULLS FIRST, role, text)) AS turns_sha256,
  CAST(sum(CASE WHEN role = 'assistant' THEN length(text) ELSE 0 END) AS BIGINT) AS loss_chars,
  sha256(coalesce(string_agg(CASE WHEN role = 'assistant' THEN text END, '' ORDER BY turn NULLS FIRST, role, text), '')) AS loss_sha256,
  CAST(sum(CASE WHEN role = 'assistant' OR last THEN upto ELSE 0 END) AS BIGINT) AS formatted_chars
FROM placed GROUP BY conv_id
"""
