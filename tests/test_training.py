"""Splits, schedules, resampling and the trainer against NumPy."""

import numpy as np
from pyspark.sql import functions as F

from avcurate.operators import curriculum, resampler, trainer
from avcurate.sources import fixtures as fx
from compare import SMALL


def rows(spark):
    return spark.createDataFrame([(1, "accept", 0.9), (2, "accept", 0.7), (3, "reject", 0.1)], "clip_id long, split string, s_comp double")


def test_exposures(spark):
    n = lambda mode: curriculum.curriculum_schedule(rows(spark), mode).count()
    assert (n("two_phase"), n("cumulative"), n("none"), n("reverse"), n("easy_only")) == (11, 21, 24, 11, 16)
    ranked = curriculum.rank_difficulty(rows(spark), buckets=3)
    assert [r.clip_id for r in ranked.orderBy("rank").collect()] == [1, 2, 3]
    assert curriculum.curriculum_schedule(ranked, "ranked", buckets=3).where("epoch = 1").count() == 1


def test_splits_cover(spark):
    clips = fx.clip_text(spark, SMALL)
    for method in ("hash", "exact", "stratified"):
        parts = {r.part: r["count"] for r in curriculum.split_dataset(clips, method).groupBy("part").count().collect()}
        assert sum(parts.values()) == 200
    assert {r.part: r["count"] for r in curriculum.split_dataset(clips, "exact").groupBy("part").count().collect()} == {"train": 160, "test": 40}


def test_resample_worked(spark):
    t = spark.createDataFrame([(1, 0, [1.0, 0.0]), (1, 1, [0.0, 1.0])], "clip_id long, token_no long, vec array<double>")
    q = spark.createDataFrame([(0, [1.0, 0.0])], "query_no long, vec array<double>")
    for f in (resampler.resample, resampler.resample_by_rows):
        assert np.allclose(f(t, q).first().vec, [0.669762, 0.330238], atol=1e-6)
    assert resampler.resample(t.where("false"), q).count() == 0


def test_resample_is_convex_and_matters(spark):
    t, q = fx.tokens(spark, SMALL), fx.queries(spark, SMALL, 4, 64.0)
    out = {(r.clip_id, r.query_no): np.array(r.vec) for r in resampler.resample(t, q).collect()}
    mean = {r.clip_id: np.array(r.vec) for r in resampler.mean_pool(t).collect()}
    by = {}
    for r in t.collect():
        by.setdefault(r.clip_id, []).append(r.vec)
    for (c, _), v in out.items():
        x = np.array(by[c])
        assert (v >= x.min(0) - 1e-9).all() and (v <= x.max(0) + 1e-9).all()
        assert np.abs(v - mean[c]).max() > 1e-3


def test_trainer_equals_numpy(spark):
    df = trainer.with_quality(fx.trainable(spark, SMALL)).where("part = 'train'")
    w, history = trainer.fit_curriculum(df, "two_phase", easy_epochs=2, hard_epochs=1, steps=2, lr=1.0)
    data = df.select("vec", "y", "split").collect()
    v = np.zeros((10, 65))
    for split, epochs in (("accept", 2), ("reject", 1)):
        x = np.array([[*r.vec, 1.0] for r in data if r.split == split])
        y = np.array([r.y for r in data if r.split == split])
        for _ in range(2 * epochs):
            z = x @ v.T
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(y)), y] -= 1
            v -= p.T @ x / len(y)
    assert np.abs(w - v).max() < 1e-8
    assert history[1][2] <= history[0][2]


def test_loss(spark):
    df = spark.createDataFrame([(1, [0.75, 0.25], 1)], "phase int, p array<double>, y int")
    assert round(curriculum.expected_ce(df).first().loss, 6) == 1.386294
    zero = df.withColumn("p", F.array(F.lit(1.0), F.lit(0.0)))
    assert 27 < curriculum.expected_ce(zero).first().loss < 28


def test_ranked_trainer_equals_numpy(spark):
    df = curriculum.rank_difficulty(trainer.with_quality(fx.trainable(spark, SMALL)), "quality", buckets=3, key="vec_id").where("part = 'train'")
    w, history = trainer.fit_curriculum(df, "ranked", easy_epochs=2, hard_epochs=1, steps=2, lr=1.0)
    data, v = df.select("vec", "y", "bucket").collect(), np.zeros((10, 65))
    for epoch in (1, 2, 3):
        x = np.array([[*r.vec, 1.0] for r in data if r.bucket <= epoch])
        y = np.array([r.y for r in data if r.bucket <= epoch])
        for _ in range(2):
            z = x @ v.T
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            p[np.arange(len(y)), y] -= 1
            v -= p.T @ x / len(y)
    assert np.abs(w - v).max() < 1e-8 and [h[1] for h in history] == [1, 2, 3]


def test_schedules_are_compared(spark):
    """All six, each on train and test and on both splits; the losses of phases are those of the weights."""
    df = curriculum.rank_difficulty(trainer.with_quality(fx.trainable(spark, SMALL)), "quality", key="vec_id")
    got = trainer.compare_schedules(df, easy_epochs=1, hard_epochs=1, steps=1).collect()
    assert {r.schedule for r in got} == set(trainer.ALL_MODES) and len(got) == 24
    w, _ = trainer.fit_curriculum(df.where("part = 'train'"), "none", easy_epochs=1, hard_epochs=1, steps=1)
    data = df.where("part = 'test' and split = 'reject'").collect()
    z = np.array([[*r.vec, 1.0] for r in data]) @ w.T
    p = np.exp(z) / np.exp(z).sum(1, keepdims=True)
    own = -np.log(p[np.arange(len(data)), [r.y for r in data]])
    r = next(r for r in got if (r.schedule, r.part, r.split) == ("none", "test", "reject"))
    assert r.n == len(data) and abs(r.loss - own.mean()) < 1e-9
    losses = {r.phase: r.loss for r in trainer.phase_losses(df.where("part = 'train'"), easy_epochs=1, hard_epochs=1, steps=1).collect()}
    assert set(losses) == {1, 2} and all(x > 0 for x in losses.values())


def test_ranks_of_many_equal_scores(spark):
    rows_ = [(i, None if i % 3 == 0 else (i * 7 % 5) / 5) for i in range(3000)]
    df = spark.createDataFrame(rows_, "clip_id long, s_comp double").repartition(3)
    want = [i for i, s in sorted(rows_, key=lambda r: (-r[1] if r[1] is not None else 9, r[0]))]
    got = curriculum.rank_difficulty(df).collect()
    assert [r.clip_id for r in sorted(got, key=lambda r: r["rank"])] == want and sorted(r["rank"] for r in got) == list(range(1, 3001))


def test_exposures_from_counts(spark):
    for mode in (*curriculum.MODES, "ranked"):
        x = curriculum.rank_difficulty(rows(spark), buckets=3)
        made = curriculum.curriculum_schedule(x, mode, buckets=3).collect()
        got = {r.split: (r.samples, r.exposures) for r in curriculum.exposure_report(x, mode, buckets=3).collect()}
        assert got == {s: (len({r.clip_id for r in made if r.split == s}), sum(r.split == s for r in made)) for s in {r.split for r in made}}


def test_resampling_forms_agree(spark):
    t, q = fx.tokens(spark, SMALL), fx.queries(spark, SMALL, 4, 64.0)
    for heads in (1, 4):
        a = {(r.clip_id, r.query_no): np.array(r.vec) for r in resampler.resample(t, q, heads=heads).collect()}
        b = {(r.clip_id, r.query_no): np.array(r.vec) for r in resampler.resample_by_rows(t, q, heads=heads).collect()}
        assert set(a) == set(b) and all(np.abs(a[k] - b[k]).max() < 1e-9 for k in a)
