"""Multi-party chat formatting: every participant's perspective of a dialogue, with training masks.

For each participant of a conversation the dialogue is rendered with that speaker as the assistant and every other one as
a named user; system turns stay system turns and are no perspective.  A segment is a header, the text and an end mark; the
mask is the part of the perspective's own segments that training counts: text and end mark.  Offsets are code points
within the rendered dialogue, end exclusive.  Marks inside of texts and names are escaped, so none can end a turn or start
one: a backslash is put into each ``<|`` (and in names into each ``|>``); where backslashes stand there already, one more
is added, so that taking one out gives back what was written.

The result has one row for each perspective and turn, in the order of turn, role and text, so no dialogue has to fit into
one row or task: offsets are running sums in two levels, within pieces of ``PIECE`` turn numbers and then over the pieces.
``whole_dialogues`` joins the segments where a dialogue is small enough for a row.

Defined results: a null text is empty; a null role is the speaker "unknown"; rows without a conversation or turn are left
out; rows equal in conversation, turn, role and text are one turn; roles are told apart as they are written; other columns
are ignored; no rows give no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

PIECE = 64
SYSTEM = "system"


def escaped(text: Column, name: bool = False) -> Column:
    """A text without marks; ``unescaped`` undoes it."""
    out = F.regexp_replace(text, r"<(\\*+)\|", r"<\\$1|")
    return F.regexp_replace(out, r"\|(\\*+)>", r"|\\$1>") if name else out


def unescaped(text: Column, name: bool = False) -> Column:
    out = F.regexp_replace(text, r"\|\\(\\*+)>", r"|$1>") if name else text
    return F.regexp_replace(out, r"<\\(\\*+)\|", r"<$1|")


def perspectives(turns: DataFrame) -> DataFrame:
    """``conv_id, perspective, turn, speaker, segment, start, end, mask_start, mask_end``; masks are null where training
    doesn't count the segment."""
    rows = turns.where("conv_id is not null and turn is not null").select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("unknown")).alias("speaker"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    rows = rows.distinct()
    own = F.col("perspective") == F.col("speaker")
    header = F.when(own, F.lit("<|assistant|>\n")).when(F.col("speaker") == SYSTEM, F.lit("<|system|>\n")).otherwise(F.concat(F.lit("<|user name="), escaped(F.col("speaker"), True), F.lit("|>\n")))
    speakers = rows.where(F.col("speaker") != SYSTEM).select("conv_id", F.col("speaker").alias("perspective")).distinct()
    seen = rows.join(speakers, "conv_id").withColumn("header", header).withColumn("segment", F.concat(F.col("header"), escaped(F.col("text")), F.lit("<|end|>\n")))
    seen = seen.withColumn("piece", F.floor(F.col("turn") / PIECE)).withColumn("size", F.length("segment").cast("long"))
    key = ["conv_id", "perspective"]
    inside = Window.partitionBy(*key, "piece").orderBy("turn", "speaker", "text").rowsBetween(Window.unboundedPreceding, -1)
    pieces = seen.groupBy(*key, "piece").agg(F.sum("size").alias("total"))
    before = Window.partitionBy(*key).orderBy("piece").rowsBetween(Window.unboundedPreceding, -1)
    pieces = pieces.select(*key, "piece", F.coalesce(F.sum("total").over(before), F.lit(0)).alias("base"))
    at = seen.withColumn("within", F.coalesce(F.sum("size").over(inside), F.lit(0))).join(pieces, [*key, "piece"])
    at = at.withColumn("start", F.col("base") + F.col("within")).withColumn("end", F.col("start") + F.col("size"))
    return at.select(*key, "turn", "speaker", "segment", "start", "end", F.when(own, F.col("start") + F.length("header")).alias("mask_start"), F.when(own, F.col("end")).alias("mask_end"))


def whole_dialogues(segments: DataFrame, most: int = 1 << 20) -> DataFrame:
    """``conv_id, perspective, rendered, masks`` of the perspectives with at most ``most`` code points; longer ones are
    null, and their segments are the result of ``perspectives``."""
    key = ["conv_id", "perspective"]
    length = segments.groupBy(*key).agg(F.max("end").alias("length"))
    small = segments.join(length.where(F.col("length") <= most), key)
    made = small.groupBy(*key).agg(F.array_sort(F.collect_list(F.struct("start", "segment", "mask_start", "mask_end"))).alias("s"))
    made = made.select(*key, F.array_join(F.transform("s", lambda x: x["segment"]), "").alias("rendered"), F.array_join(F.transform(F.filter("s", lambda x: x["mask_start"].isNotNull()), lambda x: F.concat_ws(":", x["mask_start"], x["mask_end"])), ",").alias("masks"))
    return length.select(*key).join(made, key, "left")
