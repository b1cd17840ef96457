"""Softmax regression over vectors, trained by schedules of easy and hard examples.

One pass over the data for each step: tasks send one gradient each (classes x (dims + 1)
numbers), the driver steps, and the next pass reads the new weights. Rows of a phase are a filter,
not a copy for each epoch; schedules that are compared share their passes. The lineage doesn't
grow, since weights live on the driver.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from avcurate.operators.curriculum import MODES, expected_ce
from avcurate.operators.normalise import exact_quantile


def _probs(x: np.ndarray, w: np.ndarray) -> np.ndarray:
    z = x @ w.T
    z -= z.max(axis=1, keepdims=True)
    e = np.exp(z)
    return e / e.sum(axis=1, keepdims=True)


def _matrix(vecs) -> np.ndarray:
    v = np.stack(vecs.to_numpy()).astype(np.float64)
    return np.hstack([v, np.ones((len(v), 1))])


def gradients(rows: DataFrame, ws: list[np.ndarray]) -> list[tuple[np.ndarray, float, int]]:
    """Summed gradient, summed loss, rows of each of ``ws`` over the rows that its column (``_0``, ``_1``, ...) marks, by one pass for all."""
    def part(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        g, loss, n = [np.zeros_like(w) for w in ws], [0.0] * len(ws), [0] * len(ws)
        for b in batches:
            if not len(b):
                continue
            all_x, all_y = _matrix(b.vec), b.y.to_numpy()
            for k, w in enumerate(ws):
                reads = b[f"_{k}"].to_numpy(dtype=bool)
                x, y = all_x[reads], all_y[reads]
                p = _probs(x, w)
                loss[k] -= float(np.log(np.maximum(p[np.arange(len(y)), y], 1e-12)).sum())
                p[np.arange(len(y)), y] -= 1
                g[k], n[k] = g[k] + p.T @ x, n[k] + len(y)
        yield pd.DataFrame({"k": range(len(ws)), "g": [x.ravel().tolist() for x in g], "loss": loss, "n": n})

    parts = rows.mapInPandas(part, "k int, g array<double>, loss double, n long").select("k", F.posexplode("g").alias("i", "v"), "loss", "n")
    sums = parts.groupBy("k", "i").agg(F.sum("v").alias("v"), F.sum("loss").alias("loss"), F.sum("n").alias("n")).collect()  # as many rows as weights
    out = [[np.zeros(w.size), 0.0, 0] for w in ws]
    for r in sums:
        out[r.k][0][r.i], out[r.k][1], out[r.k][2] = r.v, r.loss, r.n
    return [(g.reshape(w.shape), loss, n) for (g, loss, n), w in zip(out, ws)]


def passes(mode: str, easy_epochs: int, hard_epochs: int) -> list[tuple[int, int, Column]]:
    """(phase, epoch, which rows it reads) of a schedule; ranked adds one bucket of difficulty an epoch."""
    if mode == "ranked":
        return [(1, e, F.col("bucket") <= e) for e in range(1, easy_epochs + hard_epochs + 1)]
    return [(p, e, F.col("split").isin(*splits)) for p, splits, epochs in MODES[mode](easy_epochs, hard_epochs) for e in range(1, epochs + 1)]


def fit_schedules(train: DataFrame, modes: tuple[str, ...], classes: int = 10, dims: int = 64, easy_epochs: int = 3, hard_epochs: int = 5, steps: int = 4, lr: float = 4.0, frozen: list[int] | None = None) -> dict[str, tuple[np.ndarray, list[tuple]]]:
    """(weights, history of (phase, epoch, loss)) of each mode; train has vec, y, split, and bucket for ``ranked``. ``frozen`` classes keep their weights.

    The n-th epochs of all schedules are one set of passes, in which each schedule sees its own rows.
    """
    ws, history = {m: np.zeros((classes, dims + 1)) for m in modes}, {m: [] for m in modes}
    plans = {m: passes(m, easy_epochs, hard_epochs) for m in modes}
    train = train.select("vec", "y", "split", *["bucket"] * ("ranked" in modes)).persist()
    for at in range(max(map(len, plans.values()))):
        live = [m for m in modes if at < len(plans[m])]
        marks = [F.coalesce(plans[m][at][2], F.lit(False)).alias(f"_{k}") for k, m in enumerate(live)]
        rows = train.select("vec", "y", *marks).where(F.greatest(*[F.col(f"_{k}") for k in range(len(live))]) if len(live) > 1 else F.col("_0"))
        last = {}
        for _ in range(steps):
            for m, (g, loss, n) in zip(live, gradients(rows, [ws[m] for m in live])):
                last[m] = loss / n if n else None
                if frozen:
                    g[frozen] = 0
                if n:
                    ws[m] = ws[m] - lr * g / n
        for m in live:
            history[m].append((*plans[m][at][:2], last.get(m)))
    train.unpersist()
    return {m: (ws[m], history[m]) for m in modes}


def fit_curriculum(train: DataFrame, mode: str = "two_phase", **fit) -> tuple[np.ndarray, list[tuple]]:
    """Weights and history of one schedule."""
    return fit_schedules(train, (mode,), **fit)[mode]


def evaluate_each(rows: DataFrame, ws: dict[str, np.ndarray], by: tuple[str, ...] = ("part", "split")) -> DataFrame:
    """schedule, *by, n, loss and accuracy of each of the weights, by groups; one pass for all."""
    keys, weights = list(by), list(ws.values())
    schema = ", ".join([f"{k} string" for k in keys] + [f"loss{k} double, hit{k} int" for k in range(len(weights))])

    def part(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                x, y, out = _matrix(b.vec), b.y.to_numpy(), b[keys]
                for k, w in enumerate(weights):
                    p = _probs(x, w)
                    out = out.assign(**{f"loss{k}": -np.log(np.maximum(p[np.arange(len(y)), y], 1e-12)), f"hit{k}": (p.argmax(axis=1) == y).astype("int32")})
                yield out

    means = [F.struct(F.lit(name).alias("schedule"), F.avg(f"loss{k}").alias("loss"), F.avg(f"hit{k}").alias("accuracy")) for k, name in enumerate(ws)]
    g = rows.select(*keys, "vec", "y").mapInPandas(part, schema).groupBy(*keys).agg(F.count("*").alias("n"), F.array(*means).alias("_each"))
    return g.select(*keys, "n", F.inline("_each")).select("schedule", *keys, "n", "loss", "accuracy")


def evaluate(rows: DataFrame, w: np.ndarray, by: tuple[str, ...] = ("part", "split")) -> DataFrame:
    """n, loss and accuracy of the weights, by groups."""
    return evaluate_each(rows, {"": w}, by).drop("schedule")


def with_quality(df: DataFrame, reject_share: float = 0.39) -> DataFrame:
    """quality: cosine to the mean of the own class in the training part; the lowest share of it is the hard split."""
    from avcurate.functions.vectors import cosine

    parts = df.where("part = 'train'").select("y", F.posexplode("vec").alias("i", "v")).groupBy("y", "i").agg(F.avg("v").alias("v"))
    centre = parts.groupBy("y").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "v"))), lambda s: s["v"]).alias("c"))
    q = df.join(F.broadcast(centre), "y").withColumn("quality", cosine("vec", "c")).drop("c")
    cut = exact_quantile(q.where("part = 'train'"), "quality", reject_share, "cut")
    return q.crossJoin(F.broadcast(cut)).withColumn("split", F.when(F.round("quality", 9) >= F.round("cut", 9), "accept").otherwise("reject")).drop("cut")


def probabilities(rows: DataFrame, w: np.ndarray, keep: tuple[str, ...] = ("split",)) -> DataFrame:
    """*keep, y and p, the probabilities of the classes under the weights."""
    schema = ", ".join(f"{k} string" for k in keep) + ", y int, p array<double>"

    def part(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                yield b[list(keep)].assign(y=b.y.astype("int32"), p=list(_probs(_matrix(b.vec), w)))

    return rows.select(*keep, "vec", "y").mapInPandas(part, schema)


def phase_losses(train: DataFrame, mode: str = "two_phase", **fit) -> DataFrame:
    """phase, n, loss: cross-entropy of the fitted weights over the rows that each phase of the schedule reads."""
    w, _ = fit_curriculum(train, mode, **fit)
    phases = [(p, s) for p, splits, _ in MODES[mode](1, 1) for s in splits]
    of = train.sparkSession.createDataFrame(phases, "phase int, split string")
    return expected_ce(probabilities(train, w).join(F.broadcast(of), "split"))


ALL_MODES = (*MODES, "ranked")


def compare_schedules(df: DataFrame, modes: tuple[str, ...] = ALL_MODES, **fit) -> DataFrame:
    """schedule, part, split, n, loss, accuracy of one fit for each schedule; ``ranked`` reads the column ``bucket``. Store a costly df before: training and the result each read it."""
    fits = fit_schedules(df.where("part = 'train'"), modes, **fit)
    return evaluate_each(df, {m: w for m, (w, _) in fits.items()})
