"""Multi-party dialogues rendered from every participant's seat, with DataFrame functions only.

For each participant the dialogue is written with that speaker as the assistant, everyone else as a user named after
their role, and system turns as they are. Training spans mark what the assistant says. A dialogue comes in parts of
``PART_TURNS`` turn numbers, so that a conversation of any length is bounded by part as far as its turn numbers differ; parts joined in order give the whole,
and ``char_start`` is a part's place there.

Rows that repeat conversation, turn, role and text are one message. Ties of a turn go by role, then text. Null conv_id: no
dialogue, left out. Null turn counts as 0, null role as ``unknown``, null text as empty. A conversation of system turns
alone has no participant and no row. Marks in texts and names are broken up by a space, so they can't be forged.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

PART_TURNS = 32


def _plain(c: Column) -> Column:
    return F.replace(c, F.lit("<|"), F.lit("< |"))


def rotate(turns: DataFrame, part_turns: int = PART_TURNS) -> DataFrame:
    """conv_id, perspective, part, n_messages, text, train_spans (``start-end`` in the part, by comma), char_start."""
    said = turns.where("conv_id is not null").select("conv_id", F.coalesce("turn", F.lit(0)).cast("long").alias("turn"), F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).distinct()
    seats = said.where("role <> 'system'").select("conv_id", F.col("role").alias("perspective")).distinct()
    own = F.col("role") == F.col("perspective")
    head = F.when(F.col("role") == "system", F.lit("<|system|>\n")).when(own, F.lit("<|assistant|>\n")).otherwise(F.concat(F.lit("<|user name="), _plain(F.col("role")), F.lit("|>\n")))
    body = F.concat(_plain(F.col("text")), F.lit("<|end|>\n"))
    line = F.struct("turn", "role", "text", head.alias("head"), body.alias("body"), own.alias("own"))
    said = said.withColumn("part", F.floor(F.col("turn") / part_turns))
    seated = said.select("conv_id", "part").distinct().join(seats, "conv_id")  # a long dialogue's turns meet its seats part by part
    grouped = said.join(seated, ["conv_id", "part"]).groupBy("conv_id", "perspective", "part").agg(F.array_sort(F.collect_list(line)).alias("m"))
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("spans"))

    def step(acc: Column, m: Column) -> Column:
        first = acc["at"] + F.length(m["head"])
        after = first + F.length(m["body"])
        span = F.concat_ws("-", first.cast("string"), (after - 1).cast("string"))
        return F.struct(after.cast("long").alias("at"), F.when(m["own"], F.concat(acc["spans"], F.array(span))).otherwise(acc["spans"]).alias("spans"))

    walked = grouped.select("conv_id", "perspective", "part", F.size("m").cast("long").alias("n_messages"), F.array_join(F.transform("m", lambda m: F.concat(m["head"], m["body"])), "").alias("text"), F.aggregate("m", start, step).alias("w"))
    before = W.partitionBy("conv_id", "perspective").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    return walked.select("conv_id", "perspective", "part", "n_messages", "text", F.array_join("w.spans", ",").alias("train_spans"), F.coalesce(F.sum("w.at").over(before), F.lit(0)).alias("char_start"))
