"""Chat formatting by perspective rotation: a dialogue is rendered once for each participant, with that speaker as the assistant, all
others as named users, and a loss mask over the assistant's words. Built-in functions only.

A rendering is cut into chunks by turn number (turns_per_chunk), so that no dialogue, however long, has to meet in one task; a chunk's
place in its dialogue is `chunk`, and chunks joined in that order are the whole. The mask is run lengths over the code points of a chunk.

Defined results: repeated rows (same dialogue, turn, speaker and text) are one turn. Turns of one number are ordered by speaker and then text,
null first. A null dialogue id is a dialogue of its own, a null turn comes first, a null speaker is called "unknown", a null text is empty. Speakers
in `narrators` are shown to everybody under their own name and are nobody's perspective; a dialogue of narrators alone has no rendering. The marks
of the format inside a text are broken by a blank, so that a text can't open or close a turn. Other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# fixed values: the marks of the chat format
OPEN, CLOSE = "<|im_start|>", "<|im_end|>"

SPREAD = 64


def rotate(df: DataFrame, dialogue: str = "conv_id", turn: str = "turn", speaker: str = "role", text: str = "text", narrators: tuple[str, ...] = ("system",), turns_per_chunk: int = 256) -> DataFrame:
    """dialogue, participant, chunk, n_turns, rendered, mask: array of (length, target)."""
    safe = F.regexp_replace(F.coalesce(F.col(text), F.lit("")), r"<\|(im_start|im_end)\|>", "<| $1|>")
    rows = df.select(F.col(dialogue).alias("d"), F.coalesce(F.floor(F.col(turn) / turns_per_chunk), F.lit(-1)).cast("bigint").alias("chunk"), F.col(turn).alias("turn"), F.coalesce(F.col(speaker).cast("string"), F.lit("unknown")).alias("who"), safe.alias("said"))
    people = rows.where(~F.col("who").isin(*narrators)).select("d", F.col("who").alias("participant")).distinct()
    # the participants are sent to each of the (at most SPREAD) parts that a dialogue's chunks fall in, so that chunks of one dialogue meet them in many tasks
    part = F.pmod(F.xxhash64("d", "chunk"), F.lit(SPREAD)).alias("part")
    parts = rows.select("d", part).distinct()
    people = people.join(parts, people["d"].eqNullSafe(parts["d"])).select(people["d"], "part", "participant")
    # collect_set meets repeats on every task already, and a chunk's turns are few
    chunks = rows.groupBy("d", "chunk").agg(F.sort_array(F.collect_set(F.struct("turn", "who", "said"))).alias("turns")).select("d", "chunk", "turns", part)
    both = chunks.join(people, chunks["d"].eqNullSafe(people["d"]) & (chunks["part"] == people["part"])).select(chunks["d"].alias("d"), "chunk", "turns", "participant")
    me = F.col("participant")

    def head(t):
        role = F.when(t["who"] == me, "assistant").when(t["who"].isin(*narrators), t["who"]).otherwise(F.concat(F.lit("user name="), t["who"]))
        return F.concat(F.lit(OPEN), role, F.lit("\n"))

    tail = CLOSE + "\n"
    rendered = F.array_join(F.transform("turns", lambda t: F.concat(head(t), t["said"], F.lit(tail))), "")
    # the closing mark is the assistant's to learn, the line end is not
    run = lambda n, target: F.struct(n.cast("int").alias("length"), F.lit(target).alias("target"))
    mine = lambda t: F.array(run(F.length(head(t)), False), run(F.length(t["said"]) + len(CLOSE), True), run(F.lit(1), False))
    other = lambda t: F.array(run(F.length(head(t)) + F.length(t["said"]) + len(tail), False))
    mask = F.flatten(F.transform("turns", lambda t: F.when(t["who"] == me, mine(t)).otherwise(other(t))))
    return both.select(F.col("d").alias(dialogue), "participant", "chunk", F.size("turns").alias("n_turns"), rendered.alias("rendered"), mask.alias("mask"))
