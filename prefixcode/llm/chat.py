"""Chat formatting: every participant's view of a conversation.

For each speaker of a conversation the dialogue is laid out with that speaker as the assistant and
all others as users with their names; only the assistant's own words are trained on. A system text is
context in every view and has no view of its own. The result has a row for each view and turn with
its text, its place in the view's whole text and the span to train on, so a conversation of any length
is never gathered: offsets are running sums, within blocks of turns and then over blocks.

Cases: a null role is a speaker called unknown; a null text is empty; a null conversation or turn is
a value of its own, nulls first; turns that tie are ordered by role and text; repeated rows are
turns of their own; a conversation with system texts alone has no view; markers in a text are
escaped; an empty table gives an empty result; extra columns are left alone.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from prefixcode.llm.common import table

BLOCK = 256
SYSTEM = "system"
OPEN, CLOSE = "<|", "|>"
END = "<|end|>\n"


def _head(role: Column, view: Column) -> Column:
    return F.when(role == SYSTEM, F.lit("<|system|>\n")).when(role == view, F.lit("<|assistant|>\n")).otherwise(F.concat(F.lit("<|user "), F.replace(role, F.lit(OPEN), F.lit("< |")), F.lit("|>\n")))


def views(talk: DataFrame) -> DataFrame:
    """conv_id, view, turn, speaker, segment, seg_start, train_start, train_end, view_turn.

    seg_start: characters before the segment in the view's text. train_start and train_end: the span
    to train on, in the same count, both null where nothing is. view_turn: the segment's number.
    """
    x = talk.select(
        F.col("conv_id").cast("long").alias("conv_id"),
        F.col("turn").cast("long").alias("turn"),
        F.coalesce(F.col("role").cast("string"), F.lit("unknown")).alias("speaker"),
        F.replace(F.coalesce(F.col("text").cast("string"), F.lit("")), F.lit(OPEN), F.lit("< |")).alias("words"),
    )
    speakers = x.where(F.col("speaker") != SYSTEM).select(F.col("conv_id").alias("__conv"), F.col("speaker").alias("view")).distinct()
    each = x.join(speakers, F.col("conv_id").eqNullSafe(F.col("__conv"))).drop("__conv")
    head = _head(F.col("speaker"), F.col("view"))
    each = each.withColumn("__head", head).withColumn("__len", F.length("__head") + F.length("words") + F.lit(len(END))).withColumn("__block", F.floor(F.col("turn") / BLOCK))
    order = ["turn", "speaker", "words"]
    own = W.partitionBy("conv_id", "view", "__block").orderBy(*order)
    upto = own.rowsBetween(W.unboundedPreceding, -1)
    each = each.withColumn("__in", F.coalesce(F.sum("__len").over(upto), F.lit(0))).withColumn("__rank", F.row_number().over(own) - 1)
    blocks = each.groupBy("conv_id", "view", "__block").agg(F.sum("__len").alias("__sum"), F.count(F.lit(1)).alias("__rows"))
    over = W.partitionBy("conv_id", "view").orderBy("__block").rowsBetween(W.unboundedPreceding, -1)
    blocks = blocks.select(
        F.col("conv_id").alias("__c"), F.col("view").alias("__v"), F.col("__block").alias("__b"), F.coalesce(F.sum("__sum").over(over), F.lit(0)).alias("__before"), F.coalesce(F.sum("__rows").over(over), F.lit(0)).alias("__first")
    )
    same = F.col("conv_id").eqNullSafe(F.col("__c")) & (F.col("view") == F.col("__v")) & F.col("__block").eqNullSafe(F.col("__b"))
    start = F.col("__before") + F.col("__in")
    trained = F.col("speaker") == F.col("view")
    begin = start + F.length("__head")
    return each.join(blocks, same).select(
        "conv_id",
        "view",
        "turn",
        "speaker",
        F.concat("__head", "words", F.lit(END)).alias("segment"),
        start.cast("long").alias("seg_start"),
        F.when(trained, begin).cast("long").alias("train_start"),
        F.when(trained, begin + F.length("words") + F.lit(len(END) - 1)).cast("long").alias("train_end"),
        (F.col("__first") + F.col("__rank")).cast("long").alias("view_turn"),
    )


def texts(segments: DataFrame) -> DataFrame:
    """conv_id, view, text, train_spans: whole texts, for conversations that fit in a row."""
    parts = F.sort_array(F.collect_list(F.struct("view_turn", "segment", "train_start", "train_end")))
    x = segments.groupBy("conv_id", "view").agg(parts.alias("p"))
    spans = F.transform(F.filter("p", lambda s: s["train_start"].isNotNull()), lambda s: F.struct(s["train_start"].alias("start"), s["train_end"].alias("end")))
    return x.select("conv_id", "view", F.concat_ws("", F.transform("p", lambda s: s["segment"])).alias("text"), spans.alias("train_spans"))


def op1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views(table(spark, sf_dir, "conversations"))


SQL = """
WITH x AS (
  SELECT CAST(conv_id AS BIGINT) AS conv_id, CAST(turn AS BIGINT) AS turn, coalesce(role, 'unknown') AS speaker,
         replace(coalesce(text, ''), '<|', '< |') AS words
  FROM conversations),
s AS (SELECT DISTINCT conv_id AS c, speaker AS view FROM x WHERE speaker <> 'system'),
e AS (
  SELECT x.*, s.view,
         CASE WHEN speaker = 'system' THEN '<|system|>' || chr(10) WHEN speaker = view THEN '<|assistant|>' || chr(10)
              ELSE '<|user ' || replace(speaker, '<|', '< |') || '|>' || chr(10) END AS head
  FROM x JOIN s ON x.conv_id IS NOT DISTINCT FROM s.c),
o AS (
  SELECT *, coalesce(sum(length(head) + length(words) + 8) OVER w, 0) AS start, row_number() OVER (PARTITION BY conv_id, view ORDER BY turn NULLS FIRST, speaker, words) - 1 AS k
  FROM e WINDOW w AS (PARTITION BY conv_id, view ORDER BY turn NULLS FIRST, speaker, words ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING))
SELECT conv_id, view, turn, speaker, head || words || '<|end|>' || chr(10) AS segment, CAST(start AS BIGINT) AS seg_start,
       CAST(CASE WHEN speaker = view THEN start + length(head) END AS BIGINT) AS train_start,
       CAST(CASE WHEN speaker = view THEN start + length(head) + length(words) + 7 END AS BIGINT) AS train_end,
       CAST(k AS BIGINT) AS view_turn
FROM o
"""
