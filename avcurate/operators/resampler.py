"""Patch tokens and their compression by cross-attention with a fixed set of queries."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


#: More queries than this are refused: a task holds a state for each.
MOST_QUERIES = 4096


def patch_tokens(frames: DataFrame, patch: int = 4, projector: np.ndarray | None = None) -> DataFrame:
    """Non-overlapping patches of patch x patch pixels, row by row; token_no counts over a clip's frames. ``projector`` maps their vectors."""
    per_row, per_frame = F.floor(F.col("width") / patch), F.floor(F.col("width") / patch) * F.floor(F.col("height") / patch)
    ok = (F.col("width") % patch == 0) & (F.col("height") % patch == 0)
    f = frames.withColumn("pixels", F.when(ok, F.col("pixels")).otherwise(F.raise_error(F.lit("the patch doesn't divide the image")).cast("array<float>")))
    f = f.withColumn("p", F.explode(F.sequence(F.lit(0).cast("bigint"), per_frame - 1)))
    x0, y0 = (F.col("p") % per_row) * patch, F.floor(F.col("p") / per_row) * patch
    vec = F.transform(
        F.sequence(F.lit(0), F.lit(patch * patch - 1)),
        lambda i: F.element_at("pixels", ((y0 + F.floor(i / patch)) * F.col("width") + x0 + i % patch + 1).cast("int")).cast("double"),
    )
    tokens = f.select("clip_id", (F.col("frame_no") * per_frame + F.col("p")).cast("bigint").alias("token_no"), vec.alias("vec"))
    return tokens if projector is None else project(tokens, projector)


def project(tokens: DataFrame, matrix: np.ndarray) -> DataFrame:
    """The tokens' vectors mapped by a fixed linear map (out x in), for instance to a language model's width."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                yield b.assign(vec=list(np.stack(b.vec.to_numpy()) @ matrix.T))

    return tokens.mapInPandas(run, tokens.schema)


def subsample_frames(frames: DataFrame, every: int = 2, max_fps: int | None = None, fps: int = 25) -> DataFrame:
    """Every n-th frame; or, with ``max_fps``, evenly so many of each ``fps`` frames, all where that is no fewer."""
    if max_fps is None:
        return frames.where(F.col("frame_no") % every == 0)
    if max_fps >= fps:
        return frames
    tick = lambda no: F.floor(no * max_fps / fps)
    return frames.where(tick(F.col("frame_no")) > tick(F.col("frame_no") - 1))


def resample_by_rows(tokens: DataFrame, queries: DataFrame, scale: float | None = None, heads: int = 1) -> DataFrame:
    """What ``resample`` gives, by DataFrame operators alone: a row for each token, query and position, as a check.

    Queries (64 x D) are broadcast. Logits are shifted by their maximum within (clip, query), so
    that large gains don't overflow. Weighted vectors are summed by position.
    """
    from avcurate.functions.vectors import dot

    t = tokens
    q = F.broadcast(queries.withColumnRenamed("vec", "q"))
    if heads > 1:
        def cut(df: DataFrame, c: str) -> DataFrame:
            width = F.floor(F.size(c) / heads).cast("int")
            return df.withColumn("head", F.explode(F.sequence(F.lit(0), F.lit(heads - 1)))).withColumn(c, F.slice(c, F.col("head") * width + 1, width))
        t, q = cut(t, "vec"), F.broadcast(cut(queries.withColumnRenamed("vec", "q"), "q"))
        pairs = t.join(q, "head")
        keys = ["clip_id", "query_no", "head"]
    else:
        pairs, keys = t.crossJoin(q), ["clip_id", "query_no"]
    root = F.sqrt(F.size("vec")) if scale is None else F.lit(scale)
    w = Window.partitionBy(*keys)
    logits = pairs.select(*keys, "token_no", "vec", (dot("q", "vec") / root).alias("logit"))
    weights = logits.withColumn("e", F.exp(F.col("logit") - F.max("logit").over(w))).withColumn("a", F.col("e") / F.sum("e").over(w))
    parts = weights.select(*keys, "a", F.posexplode("vec").alias("i", "v")).groupBy(*keys, "i").agg(F.sum(F.col("a") * F.col("v")).alias("v"))
    ordered = (["head"] if heads > 1 else []) + ["i", "v"]
    vec = F.transform(F.sort_array(F.collect_list(F.struct(*ordered))), lambda s: s["v"])
    return parts.groupBy("clip_id", "query_no").agg(vec.alias("vec"))


def resample(tokens: DataFrame, queries: DataFrame, scale: float | None = None, heads: int = 1, group_tokens: int | None = None) -> DataFrame:
    """clip_id, query_no, vec: softmax-weighted sums of a clip's tokens, in one pass with mergeable state.

    For each task, clip, query and head a maximum, a sum and a weighted sum: only these states are
    dealt, whatever the number of tokens. With ``group_tokens`` every so many consecutive tokens are
    compressed by themselves, and query_no counts on from group to group.
    """
    q = queries.orderBy("query_no").limit(MOST_QUERIES + 1).collect()  # learnable queries: a fixed, small set
    if len(q) > MOST_QUERIES:
        raise ValueError(f"there are more than {MOST_QUERIES} queries")
    if not q:
        return tokens.sparkSession.createDataFrame([], "clip_id long, query_no long, vec array<double>")
    numbers, matrix = [int(r.query_no) for r in q], np.array([r.vec for r in q], dtype=np.float64)
    width = matrix.shape[1] // heads
    root, step = np.sqrt(width) if scale is None else scale, max(numbers) + 1
    state = "clip_id long, query_no long, head int, top double, total double, acc array<double>"

    def partial(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            out = []
            for (clip, group), g in b.groupby(["clip_id", "grp"], sort=False):
                v = np.stack(g.vec.to_numpy()).astype(np.float64)
                for head in range(heads):
                    cut = slice(head * width, (head + 1) * width)
                    logits = matrix[:, cut] @ v[:, cut].T / root
                    top = logits.max(axis=1)
                    e = np.exp(logits - top[:, None])
                    out += [(clip, int(group) * step + n, head, t, s, a) for n, t, s, a in zip(numbers, top, e.sum(axis=1), e @ v[:, cut])]
            yield pd.DataFrame(out, columns=["clip_id", "query_no", "head", "top", "total", "acc"])

    group = F.floor(F.col("token_no") / group_tokens) if group_tokens else F.lit(0)
    merged = tokens.select("clip_id", group.cast("bigint").alias("grp"), "vec").mapInPandas(partial, state)
    w = Window.partitionBy("clip_id", "query_no", "head")
    shifted = merged.withColumn("f", F.exp(F.col("top") - F.max("top").over(w)))
    sums = shifted.select("clip_id", "query_no", "head", (F.col("f") * F.col("total")).alias("t"), F.col("f"), F.posexplode("acc").alias("i", "v"))
    parts = sums.groupBy("clip_id", "query_no", "head", "i").agg((F.sum(F.col("f") * F.col("v")) / F.sum("t")).alias("v"))
    return parts.groupBy("clip_id", "query_no").agg(F.transform(F.sort_array(F.collect_list(F.struct("head", "i", "v"))), lambda s: s["v"]).alias("vec"))


def mean_pool(tokens: DataFrame) -> DataFrame:
    """Baseline: the plain mean of a clip's tokens, as query 0."""
    parts = tokens.select("clip_id", F.posexplode("vec").alias("i", "v")).groupBy("clip_id", "i").agg(F.avg("v").alias("v"))
    vec = F.transform(F.sort_array(F.collect_list(F.struct("i", "v"))), lambda s: s["v"])
    return parts.groupBy("clip_id").agg(vec.alias("vec")).select("clip_id", F.lit(0).cast("bigint").alias("query_no"), "vec")


def fuse_tokens(audio: DataFrame, visual: DataFrame, prompt: DataFrame) -> DataFrame:
    """One ordered sequence for each clip: audio tokens, fused visual tokens, prompt tokens (clip_id, token_no, vec each)."""
    kinds = [(0, "audio", audio), (1, "visual", visual), (2, "prompt", prompt)]
    parts = [df.select("clip_id", F.lit(rank).alias("rank"), F.lit(name).alias("modality"), "token_no", "vec") for rank, name, df in kinds]
    w = Window.partitionBy("clip_id").orderBy("rank", "token_no")
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).select("clip_id", (F.row_number().over(w) - 1).cast("bigint").alias("pos"), "modality", "vec")


def compression_report(tokens: DataFrame, fused: DataFrame) -> DataFrame:
    i = tokens.groupBy("clip_id").agg(F.count("*").alias("tokens_in"))
    o = fused.groupBy("clip_id").agg(F.count("*").alias("tokens_out"))
    return i.join(o, "clip_id", "left").select("clip_id", "tokens_in", F.coalesce("tokens_out", F.lit(0)).cast("bigint").alias("tokens_out")).withColumn("ratio", F.try_divide(F.col("tokens_in"), F.col("tokens_out")))
