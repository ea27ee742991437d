"""Chat formatting by perspective rotation: for every participant of a dialogue, that speaker is the assistant and the others are named users.

A row is one turn in one perspective: its rendered text, its place (code points) in the rendered dialogue, and whether it is trained on (the turns of
the participant). Places are prefix sums in two steps, over chunks of turns and within a chunk, so a dialogue of any length is never
gathered into one task; `dialogues` joins the turns of a perspective up to `most` characters into one text with spans of its mask.

Turns run by turn, then role, then text; repeated rows are turns of their own. Defined results: null role is the participant `unknown`; null text is empty; a null
turn comes first; a null conv_id is a dialogue like any other. System turns are context in every perspective and no participant. An
empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import table

CHUNK = 64


def rotate(turns: DataFrame, system: str = "system") -> DataFrame:
    """turns(conv_id, turn, role, text) to a row per turn and participant: conv_id, participant, turn, copy, role_out, name, rendered, start, end, trained."""
    t = turns.select("conv_id", F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    # Rows that repeat in full are one row with a number of copies, so they add nothing to a chunk.
    t = t.groupBy("conv_id", "turn", "role", "text").agg(F.count("*").alias("copies"))
    t = t.withColumn("chunk", F.floor(F.col("turn") / CHUNK))  # null for a null turn, and so the first in order
    people = t.filter(F.col("role") != system).select("conv_id", F.col("role").alias("participant")).distinct()
    rows = t.join(people.withColumnRenamed("conv_id", "__conv"), F.col("conv_id").eqNullSafe(F.col("__conv"))).drop("__conv")
    own = F.col("role") == F.col("participant")
    role_out = F.when(own, "assistant").when(F.col("role") == system, "system").otherwise("user")
    name = F.when(role_out == "user", F.col("role"))
    rows = rows.withColumn("role_out", role_out).withColumn("name", name)
    head = F.concat(F.lit("<|"), "role_out", F.coalesce(F.concat(F.lit(" name="), "name"), F.lit("")), F.lit("|>\n"))
    rows = rows.withColumn("rendered", F.concat(head, "text", F.lit("\n"))).withColumn("size", F.length("rendered").cast("long"))
    whole = F.col("size") * F.col("copies")
    per = rows.groupBy("conv_id", "participant", "chunk").agg(F.sum(whole).alias("total"))
    ahead = F.sum("total").over(W.partitionBy("conv_id", "participant").orderBy("chunk").rowsBetween(W.unboundedPreceding, -1))
    per = per.select(*(F.col(c).alias(f"__{c}") for c in ("conv_id", "participant", "chunk")), F.coalesce(ahead, F.lit(0)).alias("ahead"))
    same = [F.col(c).eqNullSafe(F.col(f"__{c}")) for c in ("conv_id", "participant", "chunk")]
    rows = rows.join(per, same).drop("__conv_id", "__participant", "__chunk")
    within = F.sum(whole).over(W.partitionBy("conv_id", "participant", "chunk").orderBy("turn", "role", "text").rowsBetween(W.unboundedPreceding, -1))
    rows = rows.withColumn("first", F.col("ahead") + F.coalesce(within, F.lit(0)))
    rows = rows.withColumn("copy", F.explode(F.sequence(F.lit(0), (F.col("copies") - 1).cast("int"))))
    start = F.col("first") + F.col("copy") * F.col("size")
    return rows.select("conv_id", "participant", "turn", "copy", "role_out", "name", "rendered", start.alias("start"), (start + F.col("size")).alias("end"), own.alias("trained"))


def dialogues(rotated: DataFrame, most: int = 1_000_000) -> DataFrame:
    """A row per perspective of up to `most` characters (longer ones stay as turns): conv_id, participant, text, and mask spans [start, end)."""
    size = rotated.groupBy("conv_id", "participant").agg(F.max("end").alias("size")).filter(F.col("size") <= most)
    size = size.select(F.col("conv_id").alias("__c"), F.col("participant").alias("__p"))
    short = rotated.join(size, F.col("conv_id").eqNullSafe(F.col("__c")) & F.col("participant").eqNullSafe(F.col("__p")), "left_semi")
    of = short.groupBy("conv_id", "participant").agg(F.array_sort(F.collect_list(F.struct("start", "end", "rendered", "trained"))).alias("t"))
    spans = F.transform(F.filter("t", lambda x: x.trained), lambda x: F.struct(x.start.alias("start"), x.end.alias("end")))
    return of.select("conv_id", "participant", F.array_join("t.rendered", "").alias("text"), spans.alias("spans"))


def op7_perspective_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rotate(table(spark, sf_dir, "conversations"))


ORACLE = """
WITH t AS (
  SELECT conv_id, turn, coalesce(role, 'unknown') AS role, coalesce(text, '') AS text,
         row_number() OVER (PARTITION BY conv_id, turn, role, text) - 1 AS copy
  FROM conversations
), people AS (SELECT DISTINCT conv_id, role AS participant FROM t WHERE role <> 'system'),
said AS (
  SELECT t.conv_id, participant, turn, copy, role, text,
         CASE WHEN role = participant THEN 'assistant' WHEN role = 'system' THEN 'system' ELSE 'user' END AS role_out
  FROM t JOIN people p ON t.conv_id IS NOT DISTINCT FROM p.conv_id
), drawn AS (
  SELECT *, CASE WHEN role_out = 'user' THEN role END AS name,
         '<|' || role_out || CASE WHEN role_out = 'user' THEN ' name=' || role ELSE '' END || '|>' || chr(10) || text || chr(10) AS rendered
  FROM said
), placed AS (
  SELECT *, sum(length(rendered)) OVER (PARTITION BY conv_id, participant ORDER BY turn NULLS FIRST, role, text, copy ROWS UNBOUNDED PRECEDING) AS stop FROM drawn
)
SELECT conv_id, participant, turn, CAST(copy AS INTEGER) AS copy, role_out, name, rendered,
       CAST(stop - length(rendered) AS BIGINT) AS start, CAST(stop AS BIGINT) AS "end", role = participant AS trained
FROM placed
"""
