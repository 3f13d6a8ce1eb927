"""Multi-party perspective rotation of dialogues.

For every participant of a conversation the dialogue is rendered with that speaker as assistant and
the others as named users; the mask covers what the assistant says. A rendering is kept as segments,
one row a turn, with character spans in the whole rendering, so a conversation of any length needs
no task that holds it.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.operators.prefix import prefix_sums
from kgfeat.llm.text import key_of
from kgfeat.plans.state import Workspace

END = "<|end|>\n"
ENTITIES = (("&", "&amp;"), ("<", "&lt;"), (">", "&gt;"), ("|", "&#124;"), ('"', "&quot;"), ("\n", "&#10;"))


def header(tag: Column, speaker: Column) -> Column:
    """The opening of a segment; users carry their name, with marks that could close it written as entities,
    so that different names stay different. A speaker without a name is called unknown."""
    name = F.coalesce(speaker, F.lit("unknown"))
    for mark, entity in ENTITIES:
        name = F.replace(name, F.lit(mark), F.lit(entity))
    return F.when(tag == "user", F.concat(F.lit('<|user name="'), name, F.lit('"|>\n'))).otherwise(F.concat(F.lit("<|"), tag, F.lit("|>\n")))


def rotate(spark: SparkSession, turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", speaker_col: str = "role", text_col: str = "text", fixed: tuple[str, ...] = ("system",), ws: Workspace | None = None) -> DataFrame:
    """(conv_id, perspective, turn, seq, speaker, tag, segment, start, end, mask_start, mask_end).

    Speakers in ``fixed`` keep their own tag and get no perspective; a conversation of such speakers
    alone has no rendering. A null speaker is one participant of its own, with a null perspective; a
    null text is empty, a null conversation is a conversation of its own. No turns: an empty result.
    Texts of any length are one segment each, and other columns play no part. Turns with equal numbers are ordered by speaker
    and text; repeated rows are rendered as often as they stand. Spans count code points; masks cover
    the assistant's text and its end mark, null elsewhere.
    """
    ws = ws or Workspace(spark, "chat")
    t = turns.select(F.col(conv_col).alias("conv_id"), key_of(F.col(conv_col)).alias("k"), F.col(turn_col).alias("turn"), F.col(speaker_col).alias("speaker"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    own = F.coalesce(F.col("speaker").isin(*fixed), F.lit(False))
    who = ws.save(t.filter(~own).select("k", F.col("speaker").alias("perspective")).distinct(), "participants")
    tag = F.when(own, F.col("speaker")).when(F.col("speaker").eqNullSafe(F.col("perspective")), F.lit("assistant")).otherwise(F.lit("user"))
    seg = t.join(who, "k").withColumn("tag", tag).withColumn("head", header(F.col("tag"), F.col("speaker")))
    seg = seg.select(F.concat("k", F.lit("\x00"), key_of(F.col("perspective"))).alias("g"), "conv_id", "perspective", "turn", "speaker", "tag", "text", F.length("head").cast("long").alias("n_head"), F.concat("head", "text", F.lit(END)).alias("segment"), F.lit(1).cast("long").alias("one")).withColumn("n", F.length("segment").cast("long"))
    run = prefix_sums(ws, seg, "g", ["turn", "speaker", "text"], ["n", "one"], "segments")
    mine = F.col("tag") == "assistant"
    end = F.col("before_n") + F.col("n")
    return run.select("conv_id", "perspective", "turn", F.col("before_one").alias("seq"), "speaker", "tag", "segment", F.col("before_n").alias("start"), end.alias("end"), F.when(mine, F.col("before_n") + F.col("n_head")).alias("mask_start"), F.when(mine, end - 1).alias("mask_end"))


def assemble(segments: DataFrame) -> DataFrame:
    """(conv_id, perspective, text, masks): whole renderings, for conversations that fit a row."""
    g = segments.groupBy("conv_id", "perspective").agg(F.array_sort(F.collect_list(F.struct("seq", "segment", "mask_start", "mask_end"))).alias("s"))
    return g.select("conv_id", "perspective", F.array_join(F.transform("s", lambda x: x["segment"]), "").alias("text"), F.transform(F.filter("s", lambda x: x["mask_start"].isNotNull()), lambda x: F.struct(x["mask_start"].alias("start"), x["mask_end"].alias("end"))).alias("masks"))
