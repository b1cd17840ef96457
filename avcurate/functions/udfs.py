"""Python surfaces: Arrow scalar functions, a grouped aggregate, grouped maps and a table function."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import zip_longest

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import arrow_udtf, pandas_udf, udtf

from avcurate.functions import edits
from avcurate.functions.text import BREAK

COUNTS = T.StructType([T.StructField(k, T.IntegerType()) for k in ("sub", "del", "ins", "hit")])
ROWS = T.StructType([T.StructField("at", T.IntegerType()), T.StructField("op", T.StringType()), T.StructField("hyp_at", T.IntegerType()), T.StructField("ref_at", T.IntegerType())])


def align(hyp, ref) -> list[tuple[str, int, int]]:
    """Edit operations (op, position in hyp, position in ref) of a shortest alignment.

    hyp is what came out, ref what was meant: ``del`` is a part of ref that hyp lacks, ``ins`` one
    that hyp adds. Among equals a match goes first, then sub, del, ins, from the end backwards.
    """
    n, m = len(hyp), len(ref)
    d = np.zeros((n + 1, m + 1), dtype=np.int32)
    d[:, 0], d[0, :] = np.arange(n + 1), np.arange(m + 1)
    r = np.array([hash(x) for x in ref], dtype=np.int64) if m else np.empty(0, np.int64)
    for i in range(1, n + 1):
        diag = d[i - 1, :-1] + (r != hash(hyp[i - 1]))
        best = np.minimum(diag, d[i - 1, 1:] + 1)
        row = np.r_[i, best] - np.arange(m + 1)
        d[i] = np.minimum.accumulate(row) + np.arange(m + 1)
    out, i, j = [], n, m
    while i or j:
        if i and j and hyp[i - 1] == ref[j - 1] and d[i, j] == d[i - 1, j - 1]:
            op, i, j = "hit", i - 1, j - 1
        elif i and j and d[i, j] == d[i - 1, j - 1] + 1:
            op, i, j = "sub", i - 1, j - 1
        elif j and d[i, j] == d[i, j - 1] + 1:
            op, j = "del", j - 1
        else:
            op, i = "ins", i - 1
        out.append((op, i, j))
    return out[::-1]


def answers(hyp: str, ref: str) -> Iterator[tuple[str, str]]:
    """Utterances that answer each other; one without an answer meets the empty one."""
    return zip_longest(hyp.split(BREAK), ref.split(BREAK), fillvalue="")


def _known(hyp: pd.Series, ref: pd.Series, f) -> list:
    """``f`` of the pairs in which neither side is null, None for the others."""
    at = [i for i, (h, r) in enumerate(zip(hyp, ref)) if h is not None and r is not None]
    out = [None] * len(hyp)
    for i, v in zip(at, f([hyp.iloc[i] for i in at], [ref.iloc[i] for i in at]).tolist() if at else ()):
        out[i] = v
    return out


@pandas_udf(T.LongType())
def edit_distance(hyp: pd.Series, ref: pd.Series) -> pd.Series:
    """Edit distance, as ``text.distance`` gives it, of many pairs at once; null in, null out."""
    return pd.Series(_known(hyp, ref, edits.distances), dtype="Int64")


@pandas_udf(COUNTS)
def edit_ops(hyp: pd.Series, ref: pd.Series) -> pd.DataFrame:
    """Substitutions, deletions, insertions and matches of characters, over all utterances; null in, null out."""
    rows = [c or [None] * 4 for c in _known(hyp, ref, edits.operation_counts)]
    return pd.DataFrame(rows, columns=["hit", "sub", "del", "ins"])[["sub", "del", "ins", "hit"]].astype("Int32")


@pandas_udf(T.ArrayType(T.DoubleType()))
def letter_counts(text: pd.Series) -> pd.Series:
    """``text.letter_vector`` of texts that go to Python anyway: one count of bytes a text in place of 26 searches; a null text has 26 nulls."""
    def counts(t: str) -> np.ndarray:
        n = np.bincount(np.frombuffer(t.encode("utf-8", "surrogatepass"), dtype=np.uint8), minlength=256).astype(np.float64)
        out = n[97:123] + n[65:91]
        if not t.isascii():  # the only others whose lower case has one of the letters
            out[8] += t.count("\u0130")
            out[10] += t.count("\u212a")
        return out
    return pd.Series([[None] * 26 if t is None else counts(t) for t in text], dtype=object)


def _words(hyp: str, ref: str) -> tuple[str, str]:
    """Both with one character for each word, for each utterance; equal words of an utterance and its answer, equal characters."""
    out = []
    for h, r in answers(hyp, ref):
        number: dict[str, int] = {}
        out.append(["".join(chr(ord(BREAK) + 1 + number.setdefault(w, len(number))) for w in side.split()) for side in (h, r)])
    return BREAK.join(h for h, _ in out), BREAK.join(r for _, r in out)


@pandas_udf(T.DoubleType())
def wer(hyp: pd.Series, ref: pd.Series) -> pd.Series:
    """Word error rate; 0 where both are empty, null where the reference alone is."""
    def rates(hyps, refs):
        words = [_words(h, r) for h, r in zip(hyps, refs)]
        d = edits.distances([h for h, _ in words], [r for _, r in words])
        n = np.array([len(r.split()) for r in refs])
        none = np.array([not h.split() for h in hyps])
        return np.where(n > 0, d / np.maximum(n, 1), np.where(none, 0.0, np.nan))
    return pd.Series([None if x is None or np.isnan(x) else x for x in _known(hyp, ref, rates)], dtype="Float64")


@pandas_udf(T.DoubleType())
def snr_udaf(clean: pd.Series, noisy: pd.Series) -> float:
    """Grouped aggregate; the built-in sums are the fast way, this one checks them."""
    residual = float(((clean - noisy) ** 2).sum())
    signal = float((clean**2).sum())
    return 10 * np.log10(signal / residual) if signal > 0 and residual > 0 else None


@arrow_udtf(returnType=T.StructType([T.StructField("pair_id", T.LongType()), *ROWS]))
class AlignmentRows:
    """One row for each edit operation of the alignments of a table's pairs (pair_id, hyp, ref), utterance by utterance; places count characters without breaks.

    A pair without operations gives one row of its id alone.
    """

    def eval(self, pairs: pa.RecordBatch):
        names = pa.array(["hit", "sub", "del", "ins"])
        key, hyps, refs = (pairs.column(c) for c in ("pair_id", "hyp", "ref"))
        hyps, refs = ([t or "" for t in c.to_pylist()] for c in (hyps, refs))
        some = np.zeros(len(hyps), dtype=bool)
        for row, at, op, hyp_at, ref_at in edits.operation_rows(hyps, refs):
            some[row] = True
            columns = [key.take(pa.array(row)), pa.array(at, pa.int32()), names.take(pa.array(op)), pa.array(hyp_at, pa.int32()), pa.array(ref_at, pa.int32())]
            yield pa.table(columns, names=["pair_id", "at", "op", "hyp_at", "ref_at"])
        left = key.filter(pa.array(~some))
        if len(left):
            yield pa.table([left, *(pa.nulls(len(left), t) for t in (pa.int32(), pa.string(), pa.int32(), pa.int32()))], names=["pair_id", "at", "op", "hyp_at", "ref_at"])


@udtf(returnType=T.StructType([T.StructField("frame_no", T.LongType()), T.StructField("x", T.IntegerType()), T.StructField("y", T.IntegerType()), T.StructField("value", T.DoubleType())]))
class CropRows:
    """One row for each pixel of a window of a frame; places outside the frame are 0."""

    def eval(self, frame_no: int, pixels: list, height: int, width: int, x0: int, y0: int, crop: int):
        if None in (pixels, height, width, x0, y0, crop):
            return
        for y in range(crop):
            for x in range(crop):
                inside = 0 <= x0 + x < width and 0 <= y0 + y < height
                yield frame_no, x, y, float(pixels[(y0 + y) * width + x0 + x]) if inside else 0.0


def cogroup_scores(audio: DataFrame, frames: DataFrame) -> DataFrame:
    """SNR and motion of each clip in one cogrouped map; the built-in plan is the fast way."""
    def both(a: pd.DataFrame, f: pd.DataFrame) -> pd.DataFrame:
        clip = (a if len(a) else f).clip_id.iloc[0]
        r, s = float(((a.clean - a.noisy) ** 2).sum()), float((a.clean**2).sum())
        f = f.sort_values("frame_no")
        px = [np.asarray(p, dtype=np.float64) for p in f.pixels]
        m = [np.abs(y - x).mean() for x, y in zip(px, px[1:])]
        return pd.DataFrame({"clip_id": [clip], "snr_db": [10 * np.log10(s / r) if s > 0 and r > 0 else None], "motion": [float(np.mean(m)) if m else None]})

    return audio.groupBy("clip_id").cogroup(frames.select("clip_id", "frame_no", "pixels").groupBy("clip_id")).applyInPandas(both, "clip_id long, snr_db double, motion double")


def interpolate_np(cents: DataFrame) -> DataFrame:
    """Gaps filled by numpy.interp for each clip; checks the window form."""
    def fill(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("frame_no").reset_index(drop=True)
        ok = g.cx.notna()
        filled = ~ok
        if ok.any():
            for c in ("cx", "cy"):
                g[c] = np.interp(g.frame_no, g.frame_no[ok], g[c][ok])
        return g.assign(filled=filled)[["clip_id", "frame_no", "cx", "cy", "filled"]]

    return cents.groupBy("clip_id").applyInPandas(fill, "clip_id int, frame_no long, cx double, cy double, filled boolean")


def hashed_ngrams(df: DataFrame, text: str, out: str, n: int = 3, dims: int = 256, key: str = "clip_id") -> DataFrame:
    """Richer text vectors: counts of hashed character n-grams, as a dense array column (JVM only); ``key`` names the rows.

    Grams are counted as rows, partially before they are dealt, and only the counts become a vector.
    """
    padded = F.concat(F.lit(" "), F.lower(F.replace(text, F.lit(BREAK), F.lit(""))), F.lit(" "))
    chars = F.regexp_extract_all(padded, F.lit("(?s)."), F.lit(0))
    grams = chars
    for j in range(1, n):
        grams = F.zip_with(grams, F.slice(chars, j + 1, F.size(chars)), lambda a, b: F.concat(a, b))
    grams = F.filter(grams, lambda g: g.isNotNull())
    place = F.conv(F.substring(F.md5(F.col("_gram").cast("binary")), 1, 8), 16, 10).cast("bigint") % dims
    rows = df.select(key, padded.alias("_p"), grams.alias("_g")).select(key, F.explode(F.when(F.size("_g") > 0, F.col("_g")).otherwise(F.array("_p"))).alias("_gram"))
    counts = rows.groupBy(key, place.alias("_at")).agg(F.count("*").cast("double").alias("_n")).groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("_at", "_n"))).alias("_m"))
    vector = F.transform(F.sequence(F.lit(0).cast("bigint"), F.lit(dims - 1).cast("bigint")), lambda i: F.coalesce(F.try_element_at(F.col("_m"), i), F.lit(0.0)))
    return df.join(counts, key, "left").withColumn(out, F.when(F.col(text).isNotNull(), vector)).drop("_m")
