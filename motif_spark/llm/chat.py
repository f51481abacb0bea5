"""Perspective rotation of dialogues with several parties, in DataFrame functions only.

For every participant the dialogue is rendered with that speaker as the assistant and all others as named
users; the mask covers what the assistant says. A dialogue is a sequence of segment rows with their place in
the rendered text, so even a dialogue that holds a third of all turns is never gathered: places come from
sums within blocks of turns and over blocks.

Defined cases: a null text is empty; a null role is a participant named "unknown"; system turns are shown to
every perspective and have none of their own, so a dialogue of system turns only gives no rows; turns with
equal numbers follow by role, then text; repeated rows stay; a null turn number comes first; a null dialogue id is a dialogue of its own; an empty table gives
an empty result; a very long text is one segment; extra columns are left out, so their names do not matter.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import hot_salts

SYSTEM = "system"
END = "<|end|>\n"
#: Turn numbers that share a block.
BLOCK = 256


def rotate(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", block: int = BLOCK) -> DataFrame:
    """conv_id, perspective, turn, speaker, segment, start, mask_start, mask_end for every turn and perspective.

    start counts the code points of the perspective's text before the segment; the mask is null but for the
    perspective's own turns.
    """
    name = F.coalesce(F.col(role), F.lit("unknown"))
    df = turns.select(F.col(conv).alias("conv_id"), F.coalesce(F.col(turn).cast("long"), F.lit(-1).cast("long")).alias("turn"), name.alias("speaker"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    counts = df.groupBy("conv_id", "speaker").agg(F.count(F.lit(1)).alias("n"))
    # A dialogue with very many turns meets its participants under several salts.
    salts = hot_salts(counts.groupBy("conv_id").agg(F.sum("n").alias("n")), "conv_id")
    each = F.explode(F.sequence(F.lit(0), salts - 1)).alias("_s")
    who = counts.filter(F.col("speaker") != SYSTEM).select("conv_id", F.col("speaker").alias("perspective"), each).withColumnRenamed("conv_id", "_conv")
    df = df.withColumn("_salt", F.pmod(F.xxhash64("turn", "speaker", "text"), salts).cast("int"))
    df = df.join(who, F.col("conv_id").eqNullSafe(F.col("_conv")) & (F.col("_salt") == F.col("_s"))).drop("_conv", "_s", "_salt")
    mine = F.col("speaker") == F.col("perspective")
    head = F.when(F.col("speaker") == SYSTEM, F.lit("<|system|>\n")).when(mine, F.lit("<|assistant|>\n")).otherwise(F.concat(F.lit("<|user:"), F.col("speaker"), F.lit("|>\n")))
    # Turns without a number are all -1; their blocks go by what orders them, the speaker and the beginning of the text.
    lost = F.col("turn") == -1
    begin = F.when(lost, F.concat("speaker", F.lit("\0"), F.substring("text", 1, 2))).otherwise("")
    df = df.withColumns({"_head": head, "_block": F.struct(F.floor(F.col("turn") / block).alias("b"), lost.alias("lost"), begin.alias("t"))})
    df = df.withColumn("segment", F.concat("_head", "text", F.lit(END))).withColumn("_n", F.length("segment").cast("long"))
    dialogue = ["conv_id", "perspective"]
    totals = df.groupBy(*dialogue, "_block").agg(F.sum("_n").alias("_sum"))
    earlier = F.sum("_sum").over(Window.partitionBy(*dialogue).orderBy("_block").rowsBetween(Window.unboundedPreceding, -1))
    totals = totals.select(F.col("conv_id").alias("_conv"), F.col("perspective").alias("_p"), F.col("_block").alias("_b"), F.coalesce(earlier, F.lit(0)).alias("_blocks"))
    inside = Window.partitionBy(*dialogue, "_block").orderBy("turn", "speaker", "text").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    df = df.withColumn("_inside", F.sum("_n").over(inside) - F.col("_n"))
    df = df.join(totals, F.col("conv_id").eqNullSafe(F.col("_conv")) & (F.col("perspective") == F.col("_p")) & (F.col("_block") == F.col("_b")))
    start = F.col("_blocks") + F.col("_inside")
    return df.select(
        "conv_id",
        "perspective",
        "turn",
        "speaker",
        "segment",
        start.alias("start"),
        F.when(mine, start + F.length("_head")).alias("mask_start"),
        F.when(mine, start + F.col("_n")).alias("mask_end"),
    )


ROTATE_SQL = """
WITH t AS (
  SELECT conv_id, coalesce(turn, -1) AS turn, coalesce(role, 'unknown') AS speaker, coalesce(text, '') AS text FROM conversations
), p AS (
  SELECT DISTINCT conv_id, speaker AS perspective FROM t WHERE speaker <> 'system'
), r AS (
  SELECT t.*, p.perspective,
         CASE WHEN speaker = 'system' THEN '<|system|>' WHEN speaker = perspective THEN '<|assistant|>' ELSE '<|user:' || speaker || '|>' END || chr(10) AS head
  FROM t JOIN p ON t.conv_id IS NOT DISTINCT FROM p.conv_id
), s AS (
  SELECT *, head || text || '<|end|>' || chr(10) AS segment FROM r
), o AS (
  SELECT *, CAST(sum(length(segment)) OVER (PARTITION BY conv_id, perspective ORDER BY turn, speaker, text ROWS UNBOUNDED PRECEDING) - length(segment) AS BIGINT) AS start FROM s
)
SELECT conv_id, perspective, turn, speaker, segment, start,
       CASE WHEN speaker = perspective THEN start + length(head) END AS mask_start,
       CASE WHEN speaker = perspective THEN start + length(segment) END AS mask_end
FROM o
"""
