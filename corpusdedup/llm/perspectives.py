"""Multi-party perspective rotation of dialogues.

For every participant of a conversation the dialogue is rendered once with that
speaker as the assistant and all others as named users; only the assistant's turns
carry loss. A turn becomes one row for each perspective, so a conversation of any
length is never gathered: only its distinct speakers, aggregated before the shuffle,
are joined back to its turns. :func:`dialogues` strings the rows together where
whole examples are wanted.

Turns of the roles in ``NARRATORS`` (system prompts) stay as they are in every
perspective, and nobody takes their part. Speakers are the remaining values of the
speaker column; a null one is the speaker "unknown". A null text is an empty turn,
and empty turns stay. Repeated turns (same number) stay, ordered by speaker and text.
A conversation with narrators alone has no perspective and gives no row. A null
conv_id is a conversation like any other. Extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NARRATORS = ("system",)
CLOSE = "<|end|>\n"


def rotate(turns: DataFrame, speaker: str = "role", narrators: tuple[str, ...] = NARRATORS) -> DataFrame:
    """Rows (conv_id, perspective, turn, speaker, chat_role, name, content, rendered, loss) of (conv_id, turn, ``speaker``, text)."""
    who = F.coalesce(F.col(speaker).cast("string"), F.lit("unknown"))
    t = turns.select(F.col("conv_id"), F.col("turn"), who.alias("speaker"), F.coalesce(F.col("text"), F.lit("")).alias("content"))
    narrated = F.col("speaker").isin(*narrators) if narrators else F.lit(False)
    cast = t.where(~narrated).select(F.col("conv_id").alias("conv"), F.col("speaker").alias("perspective")).distinct()
    own = F.col("speaker") == F.col("perspective")
    role = F.when(narrated, F.col("speaker")).when(own, "assistant").otherwise("user")
    name = F.when(~narrated & ~own, F.col("speaker"))
    out = t.join(cast, F.col("conv_id").eqNullSafe(F.col("conv"))).select("conv_id", "perspective", "turn", "speaker", role.alias("chat_role"), name.alias("name"), "content", (~narrated & own).alias("loss"))
    return out.select("conv_id", "perspective", "turn", "speaker", "chat_role", "name", "content", _rendered().alias("rendered"), "loss")


def _rendered() -> Column:
    """Header, content and end mark of a turn; a named user's name follows the role."""
    head = F.concat(F.lit("<|"), F.col("chat_role"), F.when(F.col("name").isNotNull(), F.concat(F.lit(" name="), F.col("name"))).otherwise(F.lit("")), F.lit("|>"))
    return F.concat(head, F.col("content"), F.lit(CLOSE))


def dialogues(rotated: DataFrame) -> DataFrame:
    """One row for each conversation and perspective: the whole text and the spans [start, end) with loss.

    A loss span covers an assistant turn's content and end mark, not its header. This
    gathers each conversation; for conversations of unbounded length stay with the rows.
    """
    turn = F.struct("turn", "speaker", "content", "rendered", "loss")
    g = rotated.groupBy("conv_id", "perspective").agg(F.sort_array(F.collect_list(turn)).alias("turns"))
    zero = F.struct(F.lit(0).cast("long").alias("at"), F.expr("cast(array() as array<struct<start:bigint,end:bigint>>)").alias("spans"))

    def step(acc: Column, x: Column) -> Column:
        end = acc["at"] + F.length(x["rendered"])
        start = end - F.length(x["content"]) - len(CLOSE)
        return F.struct(end.alias("at"), F.when(x["loss"], F.concat(acc["spans"], F.array(F.struct(start.alias("start"), end.alias("end"))))).otherwise(acc["spans"]).alias("spans"))

    return g.select("conv_id", "perspective", F.array_join(F.transform("turns", lambda x: x["rendered"]), "").alias("text"), F.aggregate("turns", zero, step)["spans"].alias("loss_spans"))


ORACLE = """
WITH t AS (SELECT conv_id, turn, coalesce(role, 'unknown') AS speaker, coalesce(text, '') AS content FROM conversations),
p AS (SELECT DISTINCT conv_id AS conv, speaker AS perspective FROM t WHERE speaker <> 'system'),
r AS (SELECT conv_id, perspective, turn, speaker,
        CASE WHEN speaker = 'system' THEN speaker WHEN speaker = perspective THEN 'assistant' ELSE 'user' END AS chat_role,
        CASE WHEN speaker <> 'system' AND speaker <> perspective THEN speaker END AS name,
        content, speaker <> 'system' AND speaker = perspective AS loss
      FROM t JOIN p ON t.conv_id IS NOT DISTINCT FROM p.conv)
SELECT conv_id, perspective, turn, speaker, chat_role, name, content,
  '<|' || chat_role || CASE WHEN name IS NULL THEN '' ELSE ' name=' || name END || '|>' || content || '<|end|>' || chr(10) AS rendered, loss
FROM r
"""
