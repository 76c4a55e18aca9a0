"""Operator 5, chat formatting by prefix-target expansion.

Each assistant turn becomes an example of its own: all turns before it are context, and only that reply is
trainable. A turn is rendered as ``<|role|>\\n`` + text + ``<|end|>\\n``; train_start and train_end are the
character offsets of the reply (with its end mark) in ``example``.

One shuffle by conversation; the rendered turns form one array, from which every example joins a prefix: all in
built-in expressions. The output is quadratic in the turns of a conversation, as the method asks.

Order: by turn, null turns last, then role and text. Defined results: rows without a conversation id are in no
conversation and give nothing; a null role is 'unknown'; a null text is empty; an assistant turn that comes first
has an empty context and still is an example; repeated rows are turns of their own; further columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqgrid.llm.common import load

END = "<|end|>\n"


def expand(conversations: DataFrame) -> DataFrame:
    """(conv_id, turn, n_context, example, train_start, train_end), one row for each assistant turn."""
    role = F.coalesce(F.lower(F.trim("role")), F.lit("unknown"))
    rows = conversations.where("conv_id is not null").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), role.alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    turns = rows.groupBy("conv_id").agg(F.array_sort(F.collect_list(F.struct(F.col("turn").isNull().alias("no_turn"), "turn", "role", "text"))).alias("m"))
    shown = turns.where(F.exists("m", lambda x: x["role"] == "assistant")).withColumn("shown", F.transform("m", lambda x: F.concat(F.lit("<|"), x["role"], F.lit("|>\n"), x["text"], F.lit(END))))
    at = shown.select("conv_id", "shown", F.posexplode("m").alias("n_context", "x")).where(F.col("x.role") == "assistant")
    prompt = F.concat(F.array_join(F.slice("shown", F.lit(1), F.col("n_context")), ""), F.lit("<|assistant|>\n"))
    reply = F.concat(F.col("x.text"), F.lit(END))
    return at.select("conv_id", F.col("x.turn").alias("turn"), F.col("n_context").cast("int").alias("n_context"), prompt.alias("prompt"), reply.alias("reply")).select("conv_id", "turn", "n_context", F.concat("prompt", "reply").alias("example"), F.length("prompt").alias("train_start"), (F.length("prompt") + F.length("reply")).alias("train_end"))


def op5_chat_formatting(spark: SparkSession, sf_dir: str) -> DataFrame:
    return expand(load(spark, sf_dir, "conversations"))


ORACLE = """
WITH r AS (SELECT conv_id, turn, coalesce(lower(trim(role)), 'unknown') AS role, coalesce(text, '') AS text
           FROM conversations WHERE conv_id IS NOT NULL),
     s AS (SELECT *, '<|' || role || '|>' || chr(10) || text || '<|end|>' || chr(10) AS shown,
                  row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS LAST, role, text) - 1 AS before FROM r),
     p AS (SELECT *, coalesce(string_agg(shown, '') OVER (PARTITION BY conv_id ORDER BY before
                     ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), '') || '<|assistant|>' || chr(10) AS prompt FROM s)
SELECT conv_id, turn, before::INT AS n_context, prompt || text || '<|end|>' || chr(10) AS example,
       length(prompt)::INT AS train_start, (length(prompt) + length(text) + 8)::INT AS train_end
FROM p WHERE role = 'assistant'"""
