"""Multi-party perspective rotation of dialogues, in DataFrame operations only.

For every participant of a conversation the dialogue is rendered with that speaker as the assistant and the
others as named users. The result is one row per (conversation, perspective, turn): the rendered segment, its
offset in the rendered dialogue and whether the loss mask covers it, so a conversation of any length is never
gathered in one row; `render` joins the segments to whole dialogues.

A turn reads `<|start|>assistant\\n...<|end|>\\n` or `<|start|>user name=role\\n...<|end|>\\n`; the mask is the
text and end mark of the assistant's own turns, and empty elsewhere.

Edge cases: null text is empty; a null role is the participant `unknown`; turns with the same number are ordered
by role and text, null turns come last; null conv_id is a conversation of its own; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

START, END = "<|start|>", "<|end|>"
RUN = 256  # turns in a run of the two-level prefix sum
SALTS = 16


def perspectives(turns: DataFrame, run: int = RUN) -> DataFrame:
    """(conv_id, perspective, turn, rendered, is_target, char_start, mask_start, mask_end), offsets in code points of the dialogue.

    Offsets come from lengths alone: turns are multiplied by perspectives without their texts, and each text
    meets its offsets at the end, by its place in the conversation.
    """
    rows = turns.select("conv_id", "turn", F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("__run", F.coalesce(F.floor(F.col("turn") / run), F.lit((1 << 62))))
    place = Window.partitionBy("conv_id", "__run").orderBy(F.col("turn").asc_nulls_last(), "role", "text")
    placed = rows.withColumn("__ord", F.row_number().over(place))
    sizes = placed.select("conv_id", "__run", "__ord", "role", F.length("text").alias("__n"), F.pmod("__ord", F.lit(SALTS)).cast("int").alias("__salt"))
    seats = rows.groupBy("conv_id", "role").agg(F.lit(1).alias("one")).select(F.col("conv_id").alias("__conv"), F.col("role").alias("perspective"))
    seats = seats.withColumn("__s", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    seen = sizes.join(seats, F.col("conv_id").eqNullSafe(F.col("__conv")) & (F.col("__salt") == F.col("__s"))).drop("__conv", "__s", "__salt")
    own = F.col("role") == F.col("perspective")
    head = F.length(F.lit(START)) + F.when(own, F.lit(len("assistant"))).otherwise(F.length("role") + len("user name=")) + 1
    seen = seen.select("conv_id", "perspective", "__run", "__ord", head.alias("__head"), (head + F.col("__n") + len(END) + 1).cast("long").alias("__len"))
    before = Window.partitionBy("conv_id", "perspective", "__run").orderBy("__ord").rowsBetween(Window.unboundedPreceding, -1)
    local = seen.withColumn("__in", F.coalesce(F.sum("__len").over(before), F.lit(0)))
    runs = seen.groupBy("conv_id", "perspective", "__run").agg(F.sum("__len").alias("__sum"))
    ahead = Window.partitionBy("conv_id", "perspective").orderBy("__run").rowsBetween(Window.unboundedPreceding, -1)
    runs = runs.withColumn("__base", F.coalesce(F.sum("__sum").over(ahead), F.lit(0)))
    runs = runs.select(F.col("conv_id").alias("__c"), F.col("perspective").alias("__p"), F.col("__run").alias("__r"), "__base")
    told = local.join(runs, F.col("conv_id").eqNullSafe(F.col("__c")) & (F.col("perspective") == F.col("__p")) & (F.col("__run") == F.col("__r")))
    told = told.select(F.col("conv_id").alias("__c"), F.col("__run").alias("__r"), F.col("__ord").alias("__o"), "perspective", (F.col("__base") + F.col("__in")).alias("char_start"), "__head", "__len")
    out = placed.join(told, F.col("conv_id").eqNullSafe(F.col("__c")) & (F.col("__run") == F.col("__r")) & (F.col("__ord") == F.col("__o")))
    name = F.when(own, F.lit("assistant")).otherwise(F.concat(F.lit("user name="), F.col("role")))
    at = F.col("char_start")
    return out.select(
        "conv_id", "perspective", "turn", F.concat(F.lit(START), name, F.lit("\n"), "text", F.lit(END + "\n")).alias("rendered"), own.alias("is_target"), at,
        F.when(own, at + F.col("__head")).otherwise(at).alias("mask_start"), F.when(own, at + F.col("__len") - 1).otherwise(at).alias("mask_end"),
    )


def render(turns: DataFrame) -> DataFrame:
    """(conv_id, perspective, text, masks), a dialogue in one row; where single conversations are too long for a row, `perspectives` has the same in pieces."""
    seen = perspectives(turns)
    parts = F.array_sort(F.collect_list(F.struct("char_start", "rendered", "mask_start", "mask_end")))
    whole = seen.groupBy("conv_id", "perspective").agg(parts.alias("p"))
    masks = F.transform(F.filter("p", lambda x: x["mask_start"] < x["mask_end"]), lambda x: F.struct(x["mask_start"].alias("start"), x["mask_end"].alias("end")))
    return whole.select("conv_id", "perspective", F.array_join(F.transform("p", lambda x: x["rendered"]), "").alias("text"), masks.alias("masks"))


def op6_chat_rotation(spark, sf_dir: str) -> DataFrame:
    return perspectives(spark.read.parquet(f"{sf_dir}/conversations.parquet"))


OP6_SQL = """
WITH t AS (SELECT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text FROM conversations
), p AS (SELECT DISTINCT conv_id, role AS perspective FROM t
), r AS (
  SELECT t.conv_id, perspective, turn, role, text, role = perspective AS is_target,
    '<|start|>' || CASE WHEN role = perspective THEN 'assistant' ELSE 'user name=' || role END || chr(10) AS head FROM t JOIN p ON t.conv_id IS NOT DISTINCT FROM p.conv_id
), s AS (SELECT *, head || text || '<|end|>' || chr(10) AS rendered FROM r
), o AS (SELECT *, coalesce(sum(length(rendered)) OVER (PARTITION BY conv_id, perspective ORDER BY turn NULLS LAST, role, text ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS char_start FROM s)
SELECT conv_id, perspective, turn, rendered, is_target, char_start,
  CASE WHEN is_target THEN char_start + length(head) ELSE char_start END::BIGINT AS mask_start, CASE WHEN is_target THEN char_start + length(rendered) - 1 ELSE char_start END::BIGINT AS mask_end FROM o
"""
