"""Deterministic stand-ins for the transcribers that are compared; they say nothing of the real systems' quality."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from avcurate.functions.text import by_utterance
from avcurate.functions.udfs import letter_counts

#: What each stand-in makes of one utterance.
STAND_INS = {
    "sys01": lambda r: F.lower(r),
    "sys02": lambda r: F.regexp_replace(r, "[aeiou]", ""),
    "sys03": lambda r: F.left(r, F.floor(F.length(r) * F.lit(0.6)).cast("int")),
    "sys04": lambda r: F.replace(r, F.lit("th"), F.lit("t")),
    "sys05": lambda r: F.translate(r, "ea", "ae"),
    "sys06": lambda r: F.reverse(r),
    "sys07": lambda r: F.concat(r, r, r),
    "sys08": lambda r: F.replace(r, F.lit(" "), F.lit("")),
    "sys09": lambda r: F.replace(r, F.lit("n"), F.lit("")),
    "sys10": lambda r: F.replace(F.regexp_replace(r, "[.,]", ""), F.lit("o"), F.lit("u")),
    "sys11": lambda r: F.substr(r, F.lit(9)),
    "sys12": lambda r: F.left(r, F.length(r) - 1),
    "sys13": lambda r: F.regexp_replace(F.substr(r, F.lit(9)), "[ie]", ""),
}


TRANSCRIBERS = {name: lambda r, f=f: by_utterance(r, f) for name, f in STAND_INS.items()}


def register_transcriber(system_id: str, f) -> None:
    """Slot for a real transcriber: a function (or a pandas UDF) from the column of transcripts to its hypotheses, utterance by utterance."""
    TRANSCRIBERS[system_id] = f


def transcribe(refs: DataFrame, systems: list[str] | None = None, key: str = "clip_id", ref: str = "ref_text") -> DataFrame:
    """system_id, pair_id, ref, hyp for every text and system, by one narrow explode; ref_vec, the letters of ref, is counted once a text."""
    names = systems or sorted(TRANSCRIBERS)
    r: Column = F.col(ref)
    all_ = F.array(*[F.struct(F.lit(s).alias("system_id"), TRANSCRIBERS[s](r).alias("hyp")) for s in names])
    once = refs.withColumn("ref_vec", letter_counts(r))
    return once.select(F.col(key).alias("pair_id"), r.alias("ref"), "ref_vec", F.explode(all_).alias("s")).select("s.system_id", "pair_id", "ref", "s.hyp", "ref_vec")
