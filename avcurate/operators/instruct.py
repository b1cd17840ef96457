"""Instruction examples of two modes from turns of talk."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from avcurate.functions.text import asr_confidence
from avcurate.sources.fixtures import bucket100


def build_instructions(turns: DataFrame, form: str = "window") -> DataFrame:
    """translate: a user turn and its own text; chat: the same input and the assistant's next turn.

    ``form`` window uses lead; join meets turn with turn + 1. A user turn without reply gives no chat row.
    """
    if form == "window":
        w = Window.partitionBy("conv_id").orderBy("turn")
        x = turns.select("conv_id", "turn", "role", "text", F.lead(F.struct("turn", "role", "text")).over(w).alias("nxt"))
        x = x.where("role = 'user'").select("conv_id", "turn", "text", F.when(F.col("nxt.role") == "assistant", F.col("nxt.text")).alias("reply"))
    else:
        nxt = turns.where("role = 'assistant'").select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("text").alias("reply"))
        x = turns.where("role = 'user'").select("conv_id", "turn", "text").join(nxt, ["conv_id", "turn"], "left")
    both = F.array(F.struct(F.lit("translate").alias("mode"), F.col("text").alias("target")), F.struct(F.lit("chat").alias("mode"), F.col("reply").alias("target")))
    return (
        x.select("conv_id", "turn", "text", F.explode(both).alias("m")).where("m.target is not null")
        .select(F.concat_ws(":", "conv_id", "turn", "m.mode").alias("example_id"), "conv_id", "turn", "m.mode", F.concat(F.lit("/"), F.col("m.mode"), F.lit(" "), F.col("text")).alias("prompt"), "m.target")
    )


def mix_modes(examples: DataFrame, chat_share: float | None = None) -> DataFrame:
    """All examples, or as many chat rows by hash as give about the asked share of what is kept."""
    if chat_share is None:
        return examples
    counts = examples.agg(F.count_if(F.col("mode") == "chat").alias("c"), F.count_if(F.col("mode") != "chat").alias("t"))
    keep = F.least(F.lit(1.0), F.try_divide(F.col("t") * chat_share, F.col("c") * (1 - chat_share)))
    j = examples.crossJoin(F.broadcast(counts.select(keep.alias("keep"))))
    return j.where((F.col("mode") != "chat") | (bucket100(F.col("example_id")) < 100 * F.col("keep"))).drop("keep")


def translation_difficulty(examples: DataFrame, hyp: str = "hyp") -> DataFrame:
    """difficulty = 1 - consistency of a hypothesis with the target, for translate rows; null for chat rows."""
    return examples.withColumn("difficulty", F.when(F.col("mode") == "translate", 1 - asr_confidence(hyp, "target")))


def scheduled_examples(examples: DataFrame, hyp: str = "hyp", threshold: float = 0.55) -> DataFrame:
    """Examples of both modes with the difficulty of their input, and the split that a curriculum reads.

    A chat example is as hard as the translation of the same turn; easy are those whose hypothesis
    is consistent with the turn's text by at least ``threshold``.
    """
    of_turn = F.max("difficulty").over(Window.partitionBy("conv_id", "turn"))
    x = translation_difficulty(examples, hyp).withColumn("difficulty", of_turn)
    return x.withColumn("split", F.when(F.round(1 - F.col("difficulty"), 9) >= threshold, "accept").otherwise("reject"))
