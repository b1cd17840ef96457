"""SQL functions over the same expressions; Catalyst inlines them, so nothing is paid for the call but for edit distances, which are an Arrow function."""

from __future__ import annotations

from pyspark.sql import SparkSession

from avcurate.functions.text import BREAK
from avcurate.functions.udfs import edit_distance

EACH = f"zip_with(split(hyp, '{BREAK}'), split(ref, '{BREAK}'), (h, r) -> {{}})"
SUM = "aggregate({}, 0L, (total, n) -> total + n)"
#: Distances of many transcripts at once, as the board's; Catalyst's ``levenshtein`` takes ten times as long for utterances.
EDITS = "transcript_edits(hyp, ref)"
LONGER = SUM.format(EACH.format("cast(greatest(length(coalesce(h, '')), length(coalesce(r, ''))) AS BIGINT)"))
HYP, REF = (f"length(replace({x}, '{BREAK}', ''))" for x in ("hyp", "ref"))

#: name, arguments, result, body; transcripts are sequences of utterances, as in functions/text.py
FUNCTIONS = (
    ("asr_confidence", "hyp STRING, ref STRING", "DOUBLE", f"CASE WHEN {LONGER} = 0 THEN 1D ELSE 1D - {EDITS} / {LONGER} END"),
    ("cer", "hyp STRING, ref STRING", "DOUBLE", f"CASE WHEN {HYP} = 0 AND {REF} = 0 THEN 0D WHEN {REF} > 0 THEN {EDITS} / {REF} END"),
    ("vec_dot", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)"),
    ("cosine", "a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", "vec_dot(a, b) / nullif(sqrt(vec_dot(a, a)) * sqrt(vec_dot(b, b)), 0D)"),
    ("comprehensive_score", "cer DOUBLE, sim DOUBLE, alpha DOUBLE", "DOUBLE", "(1D - alpha) * (1D - cer) + alpha * sim"),
)


def register(spark: SparkSession) -> None:
    spark.udf.register("transcript_edits", edit_distance)
    for name, args, result, body in FUNCTIONS:
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {result} RETURN {body}")
