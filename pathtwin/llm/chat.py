"""Perspective rotation of dialogues, on DataFrame functions alone.

For every participant of a conversation the dialogue is rendered once more with that speaker as the
assistant and everyone else as a named user. A rendering is kept as one row a message, in order, with its
rendered text, the offset of that text in the whole rendering and the span that counts for the loss; so a
conversation of any length is never gathered in one task. ``render`` joins the rows of short ones.

Rendered message: ``<|role|>`` or ``<|role:name|>``, a line end, the text, ``<|end|>``, a line end. The
assistant's text with its end mark is unmasked, all else is masked. A text can't forge a mark: every ``<|`` in it
is written ``<||``, which no mark begins with. In names ``%``, ``|`` and line ends are written as ``%25``, ``%7C``, ``%0A``.

A null role is the speaker ``unknown``; a null text is empty; a message with a null conversation or turn
stays in a conversation or turn of its own null group, which sorts first. Messages of one turn are
ordered by role, then text; identical messages follow each other. An empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Turns that share a block of the two-level running sum.
BLOCK = 256
#: Signs of a name that could end its mark, and what is written for them, in this order.
NAME_MARKS = (("%", "%25"), ("|", "%7C"), ("\n", "%0A"))


def rotations(messages: DataFrame, block: int = BLOCK) -> DataFrame:
    """Rows ``conv_id, perspective, turn, nth, speaker, role, mask, start, length, loss_start, loss_length, rendered``.

    ``nth`` counts identical messages of a turn. Offsets are running sums in two levels: within blocks of
    turns, and over the blocks of a conversation, and messages meet their perspectives by block, so a conversation
    with a third of all rows is dealt over as many tasks as it has blocks. Identical messages are counted first
    and dealt out again at the end.
    """
    name = F.coalesce(F.col("role"), F.lit("unknown"))
    for sign, written in NAME_MARKS:
        name = F.replace(name, F.lit(sign), F.lit(written))
    m = messages.select(
        F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), name.alias("speaker"),
        F.replace(F.coalesce(F.col("text"), F.lit("")), F.lit("<|"), F.lit("<||")).alias("text"),
    )
    m = m.groupBy("conv_id", "turn", "speaker", "text").agg(F.count("*").alias("copies"))
    m = m.withColumn("block", F.floor(F.col("turn") / block))
    own, other = F.lit(len("<|assistant|>\n") + len("<|end|>\n")), F.lit(len("<|user:|>\n") + len("<|end|>\n"))
    m = m.withColumn("as_own", F.length("text") + own).withColumn("as_other", F.length("text") + F.length("speaker") + other)
    by_speaker = m.groupBy("conv_id", "block", "speaker").agg(F.sum(F.col("as_own") * F.col("copies")).alias("own"), F.sum(F.col("as_other") * F.col("copies")).alias("other"))
    speakers = by_speaker.select("conv_id", F.col("speaker").alias("perspective")).distinct()
    blocks = by_speaker.select("conv_id", "block").distinct()
    part = ["conv_id", "perspective", "block"]
    views = blocks.alias("m").join(speakers.alias("s"), F.col("m.conv_id").eqNullSafe(F.col("s.conv_id"))).select("m.*", "perspective")
    same_block = F.col("m.conv_id").eqNullSafe(F.col("s.conv_id")) & F.col("m.block").eqNullSafe(F.col("s.block"))
    named = m.alias("m").join(views.alias("s"), same_block).select("m.*", "perspective").withColumn("mine", F.col("speaker") == F.col("perspective"))
    named = named.withColumn("size", F.when(F.col("mine"), F.col("as_own")).otherwise(F.col("as_other")).cast("long"))
    sums = by_speaker.alias("m").join(views.alias("s"), same_block)
    seen_size = F.when(F.col("speaker") == F.col("perspective"), F.col("own")).otherwise(F.col("other"))
    sums = sums.select("m.*", "perspective").groupBy(*part).agg(F.sum(seen_size).alias("block_size"))
    before = F.sum("block_size").over(Window.partitionBy("conv_id", "perspective").orderBy("block").rowsBetween(Window.unboundedPreceding, -1))
    sums = sums.select(*[F.col(c).alias(f"_{c}") for c in part], F.coalesce(before, F.lit(0)).alias("block_start"))
    within = F.sum(F.col("size") * F.col("copies")).over(Window.partitionBy(*part).orderBy("turn", "speaker", "text").rowsBetween(Window.unboundedPreceding, -1))
    placed = named.withColumn("within", F.coalesce(within, F.lit(0)))
    on = [F.col(c).eqNullSafe(F.col(f"_{c}")) for c in part]
    placed = placed.join(sums, on).withColumn("nth", F.explode(F.sequence(F.lit(0), F.col("copies").cast("int") - 1)))
    head = F.when(F.col("mine"), F.lit("<|assistant|>\n")).otherwise(F.concat(F.lit("<|user:"), "speaker", F.lit("|>\n")))
    start = F.col("block_start") + F.col("within") + F.col("nth") * F.col("size")
    return placed.select(
        "conv_id", "perspective", "turn", F.col("nth").cast("long").alias("nth"), "speaker", F.when(F.col("mine"), F.lit("assistant")).otherwise(F.lit("user")).alias("role"),
        F.col("mine").alias("unmasked"), start.cast("long").alias("start"), F.col("size").alias("length"),
        F.when(F.col("mine"), start + F.length(head)).cast("long").alias("loss_start"), F.when(F.col("mine"), F.length("text") + len("<|end|>")).otherwise(0).cast("long").alias("loss_length"),
        F.concat(head, "text", F.lit("<|end|>\n")).alias("rendered"),
    )


def render(rotated: DataFrame) -> DataFrame:
    """Rows ``conv_id, perspective, dialogue``; for conversations that fit a row."""
    parts = F.array_sort(F.collect_list(F.struct("start", "rendered")))
    joined = rotated.groupBy("conv_id", "perspective").agg(parts.alias("p"))
    return joined.select("conv_id", "perspective", F.array_join(F.transform("p", lambda x: x["rendered"]), "").alias("dialogue"))


ORACLE = """
WITH m AS (SELECT conv_id, turn, replace(replace(replace(coalesce(role, 'unknown'), '%', '%25'), '|', '%7C'), chr(10), '%0A') AS speaker,
                  replace(coalesce(text, ''), '<|', '<||') AS text FROM conversations),
n AS (SELECT *, row_number() OVER (PARTITION BY conv_id, turn, speaker, text) - 1 AS nth FROM m),
p AS (SELECT DISTINCT conv_id, speaker AS perspective FROM m),
j AS (SELECT n.*, perspective, speaker = perspective AS mine,
             CASE WHEN speaker = perspective THEN '<|assistant|>' ELSE '<|user:' || speaker || '|>' END || chr(10) AS head
      FROM n JOIN p ON n.conv_id IS NOT DISTINCT FROM p.conv_id),
r AS (SELECT *, head || text || '<|end|>' || chr(10) AS rendered FROM j),
s AS (SELECT *, CAST(coalesce(sum(length(rendered)) OVER (PARTITION BY conv_id, perspective ORDER BY turn NULLS FIRST, speaker, text, nth
             ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS start FROM r)
SELECT conv_id, perspective, turn, nth, speaker, CASE WHEN mine THEN 'assistant' ELSE 'user' END AS role, mine AS unmasked, start,
       CAST(length(rendered) AS BIGINT) AS length, CASE WHEN mine THEN start + length(head) END AS loss_start,
       CAST(CASE WHEN mine THEN length(text) + 7 ELSE 0 END AS BIGINT) AS loss_length, rendered
FROM s
"""
