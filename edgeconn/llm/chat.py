"""Multi-party chat rendering, once from the seat of every participant.

For each participant of a conversation the whole dialogue is rendered with
that speaker as the assistant, the others as named users and system turns as
they are. A rendering is a run of pieces: concatenated by ``seq`` they are the
training text, ``char_start`` is where a piece begins in it, and
[train_start, train_end) is what the loss mask keeps: what the seat's speaker
says and its end mark, never a header.

Pieces stay rows, so a conversation of any length is never one value or one
task's list; assembling is a sorted write by (conv_id, perspective, seq).
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Template:
    system: str = "system"
    unnamed: str = "unknown"
    open: str = "<|"
    close: str = "|>\n"
    end: str = "<|end|>\n"

    def speaker(self, role: Column) -> Column:
        """A name for every role; one that reads like the name of the unnamed
        gets a mark before it, so that different roles have different names."""
        taken = role.rlike(f"^=*{self.unnamed}$")
        return F.coalesce(F.when(taken, F.concat(F.lit("="), role)).otherwise(role), F.lit(self.unnamed))

    def plain(self, text: Column) -> Column:
        """Text in which no mark of the template can begin or end."""
        return F.replace(F.replace(text, F.lit("<|"), F.lit("<\\|")), F.lit("|>"), F.lit("|\\>"))

    def header(self, chat_role: Column, name: Column) -> Column:
        user = F.concat(F.lit("user:"), self.plain(name))
        return F.concat(F.lit(self.open), F.when(chat_role == "user", user).otherwise(chat_role), F.lit(self.close))


def perspectives(turns: DataFrame, t: Template | None = None) -> DataFrame:
    """(conv_id, perspective, seq, turn, chat_role, name, piece, char_start,
    train_start, train_end), one row per turn and participant.

    Turns are ordered by (turn, role, text), nulls first; equal turns stay. A
    null role speaks as ``unknown`` (a role of that name as ``=unknown``), a
    null text is empty. Marks of the template inside texts and names are broken
    by a backslash, so no text can forge a header or an end. A row without a
    conv_id is a dialogue of its own. A conversation with system turns alone
    has no participant and so no rendering. Other columns are not read.
    """
    t = t or Template()
    rows = turns.select("conv_id", "turn", t.speaker(F.col("role")).alias("name"), t.plain(F.coalesce("text", F.lit(""))).alias("body"))
    seats = rows.filter(F.col("name") != t.system).select("conv_id", F.col("name").alias("perspective")).distinct()
    joined = rows.join(seats, "conv_id").unionByName(rows.filter(F.col("conv_id").isNull() & (F.col("name") != t.system)).withColumn("perspective", F.col("name")))
    chat_role = F.when(F.col("name") == t.system, F.lit(t.system)).when(F.col("name") == F.col("perspective"), F.lit("assistant")).otherwise(F.lit("user"))
    made = joined.withColumn("chat_role", chat_role).withColumn("header", t.header(F.col("chat_role"), F.col("name")))
    made = made.withColumn("piece", F.concat("header", "body", F.lit(t.end))).withColumn("size", F.length("piece").cast("long"))
    # A null conv_id is one turn: it needs no window and must not gather in one.
    whole = made.filter(F.col("conv_id").isNotNull())
    order = Window.partitionBy("conv_id", "perspective").orderBy("turn", "name", "body")
    whole = whole.withColumn("seq", F.row_number().over(order).cast("long") - 1).withColumn("char_start", F.sum("size").over(order.rowsBetween(Window.unboundedPreceding, 0)) - F.col("size"))
    alone = made.filter(F.col("conv_id").isNull()).withColumn("seq", F.lit(0).cast("long")).withColumn("char_start", F.lit(0).cast("long"))
    said = F.col("chat_role") == "assistant"
    return whole.unionByName(alone).select(
        "conv_id", "perspective", "seq", "turn", "chat_role", "name", "piece", "char_start",
        F.when(said, F.col("char_start") + F.length("header")).alias("train_start"),
        F.when(said, F.col("char_start") + F.col("size")).alias("train_end"),
    )


ORACLE_SQL = r"""
WITH r AS (SELECT conv_id, turn, coalesce(CASE WHEN regexp_matches(role, '^=*unknown$') THEN '=' || role ELSE role END, 'unknown') AS name,
      replace(replace(coalesce(text, ''), '<|', '<\|'), '|>', '|\>') AS body FROM conversations),
s AS (SELECT DISTINCT conv_id, name AS perspective FROM r WHERE name <> 'system'),
j AS (SELECT r.*, perspective, CASE WHEN name = 'system' THEN 'system' WHEN name = perspective THEN 'assistant' ELSE 'user' END AS chat_role
      FROM r JOIN s USING (conv_id)),
h AS (SELECT *, '<|' || CASE WHEN chat_role = 'user' THEN 'user:' || replace(replace(name, '<|', '<\|'), '|>', '|\>') ELSE chat_role END || '|>' || chr(10) AS header FROM j),
p AS (SELECT *, header || body || '<|end|>' || chr(10) AS piece FROM h),
w AS (SELECT *, row_number() OVER o - 1 AS seq, CAST(sum(length(piece)) OVER o - length(piece) AS BIGINT) AS char_start FROM p
      WINDOW o AS (PARTITION BY conv_id, perspective ORDER BY turn, name, body ROWS UNBOUNDED PRECEDING))
SELECT conv_id, perspective, seq, turn, chat_role, name, piece, char_start,
       CASE WHEN chat_role = 'assistant' THEN char_start + length(header) END AS train_start,
       CASE WHEN chat_role = 'assistant' THEN char_start + length(piece) END AS train_end
FROM w
"""
