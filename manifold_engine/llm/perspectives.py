"""Chat formatting with multi-party perspective rotation, in DataFrame functions.

For every participant of a conversation (every speaker but ``system``) the
whole dialogue is rendered with that speaker as the assistant and all others as
named users.  A mask lists the character spans a model is trained on: the
contents of that speaker and the end mark after each.

A conversation may hold any share of the table, so its rendering comes in
segments of ``block`` turn numbers: the segments of a participant, joined in
order, are the dialogue, and places (``begins``, ``mask``) count characters of
the whole.  They come from a running sum over one small row a segment.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# The marks of the rendered form.
OPEN, CLOSE, SYSTEM = "<|im_start|>", "<|im_end|>\n", "system"


def defused(text: Column) -> Column:
    """No mark of the form can stand in a message."""
    return F.replace(text, F.lit("<|"), F.lit("< |"))


def _head(who: Column, speaker: Column) -> Column:
    """The line that opens a message; a name holds no marks and no line ends, so it cannot forge a turn."""
    name = F.regexp_replace(defused(who), r"[\r\n]+", " ")
    return F.concat(F.lit(OPEN), F.when(who == speaker, F.lit("assistant")).when(who == SYSTEM, F.lit(SYSTEM)).otherwise(F.concat(F.lit("user name="), name)), F.lit("\n"))


def rotate(messages: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", block: int = 256) -> DataFrame:
    """``conv_id, speaker, segment, begins, n_messages, rendered, mask array<struct<start,end>>``.

    Messages are ordered by turn, then speaker, then text; a message repeated
    with the same turn, speaker and text counts once.  Null turns come after all
    others, in segments by hash of the text.  Null text is an empty message,
    null role the speaker ``unknown``.  Marks inside texts and names are defused
    with a space after ``<``, line ends in names become spaces.  A conversation
    of system messages alone has no participant and no row; nor has an empty
    table.  ``start`` counts characters of the dialogue from 0, ``end`` is
    excluded; ``begins`` is where the segment starts.  Other columns are not
    read.
    """
    who = F.coalesce(F.col(role), F.lit("unknown"))
    rows = messages.select(F.col(conv_id).alias("conv_id"), F.col(turn).cast("long").alias("turn"), who.alias("who"), defused(F.coalesce(F.col(text), F.lit(""))).alias("text")).distinct()
    late = F.lit(1 << 60) + F.pmod(F.xxhash64("text"), F.lit(4096))
    rows = rows.withColumn("segment", F.coalesce(F.floor(F.col("turn") / block), late).cast("long"))
    ms = F.array_sort(F.collect_list(F.struct(F.col("turn").isNull().alias("late"), "turn", "who", "text")))
    segments = rows.groupBy("conv_id", "segment").agg(ms.alias("ms"))

    # characters of each segment as each participant sees it: as named, less what the change to assistant saves
    named = F.length(_head(F.col("who"), F.lit(None).cast("string")))
    saved = F.when(F.col("who") == SYSTEM, F.lit(0)).otherwise(named - len(OPEN + "assistant\n"))
    own = rows.groupBy("conv_id", "segment", "who").agg(F.sum(named + F.length("text") + len(CLOSE)).alias("length"), F.sum(saved).alias("saved"))
    whole = own.groupBy("conv_id", "segment").agg(F.sum("length").alias("length"))
    people = own.where(F.col("who") != SYSTEM).select(F.col("conv_id").alias("c__"), F.col("who").alias("speaker")).distinct()
    mine = own.select(F.col("conv_id").alias("d__"), F.col("segment").alias("s__"), F.col("who").alias("w__"), "saved")
    grid = whole.join(people, F.col("conv_id").eqNullSafe(F.col("c__"))).join(mine, F.col("conv_id").eqNullSafe(F.col("d__")) & (F.col("segment") == F.col("s__")) & (F.col("speaker") == F.col("w__")), "left")
    before = Window.partitionBy("conv_id", "speaker").orderBy("segment").rowsBetween(Window.unboundedPreceding, -1)
    begins = F.coalesce(F.sum(F.col("length") - F.coalesce("saved", F.lit(0))).over(before), F.lit(0)).cast("long")
    grid = grid.select(F.col("conv_id").alias("c__"), F.col("segment").alias("s__"), "speaker", begins.alias("begins"))
    out = segments.join(grid, F.col("conv_id").eqNullSafe(F.col("c__")) & (F.col("segment") == F.col("s__"))).drop("c__", "s__")

    pieces = F.transform("ms", lambda m: F.struct(_head(m["who"], F.col("speaker")).alias("head"), F.concat(m["text"], F.lit(CLOSE)).alias("body"), (m["who"] == F.col("speaker")).alias("mine")))
    out = out.withColumn("ps", pieces)
    out = out.withColumn("ls", F.transform("ps", lambda p: F.length(p["head"]) + F.length(p["body"])))

    def span(p: Column, i: Column) -> Column:
        start = F.col("begins") + F.aggregate(F.slice("ls", F.lit(1), i), F.lit(0), lambda s, x: s + x) + F.length(p["head"])
        return F.when(p["mine"], F.struct(start.alias("start"), (start + F.length(p["body"])).alias("end")))

    return out.select(
        "conv_id",
        "speaker",
        "segment",
        "begins",
        F.size("ms").cast("long").alias("n_messages"),
        F.array_join(F.transform("ps", lambda p: F.concat(p["head"], p["body"])), "").alias("rendered"),
        F.filter(F.transform("ps", span), lambda s: s.isNotNull()).alias("mask"),
    )


def flat(views: DataFrame) -> DataFrame:
    """The mask as text (``0-5,9-12``) for comparison across engines."""
    return views.withColumn("mask", F.array_join(F.transform("mask", lambda s: F.concat(s["start"].cast("string"), F.lit("-"), s["end"].cast("string"))), ","))


ORACLE = r"""
with r as (select distinct conv_id, turn, coalesce(role, 'unknown') as who, replace(coalesce(text, ''), '<|', '< |') as text from conversations),
p as (select distinct conv_id, who as speaker from r where who <> 'system'),
m as (select r.conv_id, speaker, turn, who, text, who = speaker as mine,
             '<|im_start|>' || (case when who = speaker then 'assistant' when who = 'system' then 'system' else 'user name=' || regexp_replace(replace(who, '<|', '< |'), '[\r\n]+', ' ', 'g') end) || chr(10) as head,
             text || '<|im_end|>' || chr(10) as body from r join p on r.conv_id = p.conv_id),
s as (select *, coalesce(sum(length(head) + length(body)) over (partition by conv_id, speaker order by turn, who, text rows between unbounded preceding and 1 preceding), 0) as at from m)
select conv_id, speaker, cast(floor(turn / 256) as bigint) as segment, cast(min(at) as bigint) as begins, count(*) as n_messages, string_agg(head || body, '' order by turn, who, text) as rendered,
       coalesce(string_agg(cast(cast(at + length(head) as bigint) as varchar) || '-' || cast(cast(at + length(head) + length(body) as bigint) as varchar), ',' order by turn, who, text) filter (where mine), '') as mask
from s group by conv_id, speaker, segment
"""
