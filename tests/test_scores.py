"""Worked values, edge rows and properties of scores and measures."""

from decimal import Decimal

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from avcurate.functions.text import asr_confidence, cer, comprehensive_score, letter_vector, route_mode
from avcurate.functions.udfs import align
from avcurate.functions.vectors import cosine
from avcurate.operators import curation, evaluate, lips, motion, normalise, signal
from avcurate.operators.curation import CurationPolicy
from avcurate.sources import fixtures as fx
from compare import SMALL


def one(df):
    return df.first()[0]


@pytest.mark.parametrize("hyp, ref, s, c", [
    ("kitten", "sitting", 0.571429, 0.428571), ("", "", 1.0, 0.0), ("a", "", 0.0, None), (None, "a", None, None),
    ("abab", "ab", 0.5, 1.0), ("xyz", "a", 0.0, 3.0), ("e", "é", 0.0, 1.0), ("same", "same", 1.0, 0.0),
])
def test_text(spark, hyp, ref, s, c):
    r = spark.createDataFrame([(hyp, ref)], "h string, r string").select(F.round(asr_confidence("h", "r"), 6), F.round(cer("h", "r"), 6)).first()
    assert tuple(r) == (s, c)


def distance(a, b):
    d = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        before, d[0] = d[0], i
        for j, y in enumerate(b, 1):
            before, d[j] = d[j], min(d[j] + 1, d[j - 1] + 1, before + (x != y))
    return d[-1]


@settings(max_examples=150, deadline=None)
@given(st.text("abé", max_size=12), st.text("abé", max_size=12))
def test_alignment_is_a_shortest_one(a, b):
    ops = [o for o, _, _ in align(a, b)]
    assert len(ops) - ops.count("hit") == distance(a, b)
    assert ops.count("ins") - ops.count("del") == len(a) - len(b)
    assert distance(a, b) == distance(b, a) and abs(len(a) - len(b)) <= distance(a, b) <= max(len(a), len(b))


def test_alignment_worked():
    ops = [o for o, _, _ in align("kitten", "sitting")]
    assert (ops.count("sub"), ops.count("del"), ops.count("ins")) == (2, 1, 0)


@pytest.mark.parametrize("clean, noisy, db, kind", [
    ([3.0, 4.0], [3.0, 3.0], 13.9794, "finite"), ([3.0, 4.0], [3.0, 3.9], 33.9794, "finite"), ([1.0], [1.0], None, "pos_inf"), ([0.0], [1.0], None, "neg_inf"), ([0.0], [0.0], None, "none"),
])
def test_snr(spark, clean, noisy, db, kind):
    rows = spark.createDataFrame([(1, t, c, n) for t, (c, n) in enumerate(zip(clean, noisy))], "clip_id long, t int, clean double, noisy double")
    r = signal.snr_db(rows).select(F.round("snr_db", 4), "snr_kind").first()
    assert tuple(r) == (db, kind)


def test_minmax(spark):
    df = spark.createDataFrame([(10.0,), (20.0,), (40.0,), (None,)], "v double")
    out = normalise.apply_minmax(df, normalise.fit_minmax(df, "v"), "v", "n").orderBy("v").collect()
    assert [r.n and round(r.n, 6) for r in out] == [None, 0.0, 0.333333, 1.0]
    flat = spark.createDataFrame([(5.0,), (5.0,)], "v double")
    assert [r.n for r in normalise.apply_minmax(flat, normalise.fit_minmax(flat, "v"), "v", "n").collect()] == [0.0, 0.0]


def test_crop_size_rounds_up_to_even(spark):
    v = spark.createDataFrame([(120.24,), (120.0,), (1.2 * 55,), (121.0,)], "v double")
    assert [r[0] for r in v.select(lips.even_ceil(F.col("v"))).collect()] == [122, 120, 66, 122]


def test_interpolation(spark):
    rows = [(1, 0, 10.0, 20.0), (1, 1, None, None), (1, 2, None, None), (1, 3, 40.0, 50.0), (1, 4, None, None), (2, 0, None, None)]
    df = spark.createDataFrame(rows, "clip_id int, frame_no long, cx double, cy double")
    got = {(r.clip_id, r.frame_no): (r.cx, r.cy) for r in lips.interpolate(df).collect()}
    assert got[1, 1] == (20, 30) and got[1, 2] == (30, 40) and got[1, 4] == (40, 50) and got[2, 0] == (None, None)
    assert {(r.clip_id, r.frame_no): r.cx for r in lips.interpolate(df, "null").collect()}[1, 4] is None


def test_motion(spark):
    rows = [(1, 0, [0.0, 0.0]), (1, 1, [1.0, 3.0]), (1, 2, [1.0, 3.0]), (2, 0, [1.0, 1.0])]
    df = spark.createDataFrame(rows, "clip_id long, frame_no int, pixels array<double>")
    for f in (motion.motion_magnitude, motion.motion_by_chunks):
        assert {r.clip_id: r.motion for r in f(df).collect()} == {1: 1.0, 2: None}
    assert round({r.clip_id: r.motion for r in motion.motion_magnitude(df, "l2").collect()}[1], 6) == 1.118034
    caps = spark.createDataFrame([(float(i),) for i in range(1, 12)], "motion double")
    assert one(motion.motion_cap(caps)) == 10
    v = spark.createDataFrame([(2.0, 4.0), (9.0, 4.0), (0.0, 0.0), (None, 4.0)], "m double, c double")
    assert [r[0] for r in v.select(motion.video_score("m", "c")).collect()] == [0.5, 1.0, 0.0, None]


def test_threshold_counts_decimals_as_written(spark):
    rows = [(1, 0.75, 0.25), (2, 0.77, 0.22), (3, 0.83, 0.13), (4, 0.5, 0.6), (5, 0.5, 0.7), (6, None, 0.5)]
    df = spark.createDataFrame(rows, "clip_id long, a double, v double").withColumn("s_comp", curation.composite_score(F.col("a"), F.col("v")))
    got = {r.clip_id: (r.split, r.reason) for r in curation.partition(df).collect()}
    assert [got[i][0] for i in range(1, 7)] == ["accept", "accept", "accept", "reject", "accept", "reject"]
    assert got[6][1] == "missing_modality"


def test_curation_keeps_every_clip_and_bounded_agrees(spark):
    args = fx.clip_text(spark, SMALL), fx.clip_audio(spark, SMALL), fx.clip_frames(spark, SMALL)
    full = {r.clip_id: r.split for r in curation.curate(*args).collect()}
    assert len(full) == 200 and sum(v == "accept" for v in full.values()) == 55
    for policy in (CurationPolicy(), CurationPolicy(threshold=0.5), CurationPolicy(w_asr=0.7, w_snr=0.3)):
        want = {r.clip_id: r.split for r in curation.curate(*args, policy).collect()}
        assert {r.clip_id: r.split for r in curation.curate_bounded(*args, policy).collect()} == want


def test_measures(spark):
    df = spark.createDataFrame([([1.0, 2.0], [2.0, 1.0]), ([0.0, 0.0], [1.0, 1.0])], "a array<double>, b array<double>")
    assert [r[0] and round(r[0], 9) for r in df.select(cosine("a", "b")).collect()] == [0.8, None]
    half = F.lit(Decimal("0.5"))
    g = spark.createDataFrame([(Decimal("0.27"), Decimal("0.84"))], "c decimal(5,3), s decimal(5,3)")
    assert one(g.select(F.round(comprehensive_score("c", "s", half), 2).cast("string"))).startswith("0.79")
    t = spark.createDataFrame([("Abba z",)], "t string").select(letter_vector("t").alias("v")).first().v
    assert t[0] == 2 and t[1] == 2 and t[25] == 1 and sum(t) == 5


def test_routes(spark):
    mode, payload = route_mode("p")
    df = spark.createDataFrame([("/chat hello",), ("/translate a b",), ("/sing x",), ("/chatter",)], "p string")
    assert [tuple(r) for r in df.select(mode, payload).collect()][:2] == [("chat", "hello"), ("translate", "a b")]
    assert [r[0] for r in df.select(mode).collect()][2:] == ["error", "error"]


def test_printed_results(spark):
    g = fx.golden(spark)
    plane = {r.system_id: r.on_frontier for r in evaluate.cs_plane(g.where("system_id <> 'sys13'")).collect()}
    assert [k for k, v in plane.items() if v] == ["sys12"]
    d = {r.metric: round(r.delta, 2) for r in evaluate.ablation_delta(g, "sys11", "sys12").collect()}
    assert d["cer"] == -0.10 and d["cs"] == 0.09
    d = {r.metric: round(r.delta, 2) for r in evaluate.ablation_delta(g, "sys11", "sys13").collect()}
    assert d["cer"] == 0.09 and d["cs"] == -0.06


def test_hashed_ngrams_see_whole_texts(spark):
    """Against pairs made here from whole texts: every fifth hypothesis is the first three fifths of each of its text's utterances."""
    from avcurate.functions.udfs import hashed_ngrams
    from avcurate.queries import QUERIES

    text = {r.doc_id: r.text for r in spark.read.parquet(f"{SMALL}/documents.parquet").collect() if r.text and r.doc_id % 5 == 2}
    pairs = spark.createDataFrame([(i, t, "".join(u[: int(len(u) * 0.6)] for u in (t[j : j + 160] for j in range(0, len(t), 160)))) for i, t in text.items()], "clip_id long, r string, h string")
    want = hashed_ngrams(hashed_ngrams(pairs, "h", "vh", 3, 64), "r", "vr", 3, 64).select("clip_id", cosine("vh", "vr").alias("sim"))
    got = {r.clip_id: r.sim for r in QUERIES["e2_hashed_ngrams"](spark, SMALL).collect()}
    assert max(map(len, text.values())) > 1000
    for r in want.collect():
        assert got[r.clip_id] == pytest.approx(r.sim, abs=1e-5)


@settings(max_examples=15, deadline=None)
@given(st.lists(st.sampled_from([0.0, 0.1, 0.5, 0.7, 1.5, -2.0, 3.25]), min_size=1, max_size=30), st.sampled_from([0.0, 0.1, 0.388, 0.5, 0.9, 1.0]))
def test_exact_quantile(spark, values, q):
    df = spark.createDataFrame([(v,) for v in values] + [(None,)], "v double")
    got = one(normalise.exact_quantile(df, "v", q, "x", buckets=4))
    assert got == pytest.approx(one(df.agg(F.percentile("v", q))), abs=1e-12)


def test_transcripts_of_many_utterances(spark):
    """Measures are sums over utterances that answer each other, whole texts are covered, and bounds agree."""
    import random

    from avcurate.functions.text import BREAK, asr_confidence_bounded, utterances

    rng = random.Random(1)
    text = "".join(rng.choices("abc é", k=1000))
    cut = spark.createDataFrame([(text,), ("",)], "t string").select(utterances("t", 160).alias("u")).collect()
    assert cut[0].u.split(BREAK) == [text[i : i + 160] for i in range(0, 1000, 160)] and cut[1].u == ""
    pairs = [([rng.choice(["", "ab", "abc", "bcaé"]) for _ in range(rng.randint(1, 4))], [rng.choice(["", "ba", "abc", "cab"]) for _ in range(rng.randint(1, 4))]) for _ in range(40)]
    df = spark.createDataFrame([(i, BREAK.join(h), BREAK.join(r)) for i, (h, r) in enumerate(pairs)], "i long, h string, r string")
    got = df.select("i", asr_confidence("h", "r").alias("s"), cer("h", "r").alias("c"), *[asr_confidence_bounded("h", "r", F.lit(k)).alias(f"b{k}") for k in (0, 2, 5)]).collect()
    for r in got:
        h, ref = pairs[r.i]
        both = [(a, b) for a, b in zip(h + [""] * (len(ref) - len(h)), ref + [""] * (len(h) - len(ref)))]
        d, longer, n = sum(distance(a, b) for a, b in both), sum(max(len(a), len(b)) for a, b in both), sum(map(len, ref))
        s = 1.0 if not longer else 1 - d / longer
        assert r.s == pytest.approx(s) and (r.c == pytest.approx(d / n) if n else r.c == (0.0 if not sum(map(len, h)) else None))
        assert [r.b0, r.b2, r.b5] == [pytest.approx(s) if d <= k else None for k in (0, 2, 5)]


def test_clips_that_a_sketch_leaves_open(spark):
    """Splits under the exact cap and under a sketch's differ at most for the clips that are listed."""
    args = fx.clip_text(spark, SMALL), fx.clip_audio(spark, SMALL), fx.clip_frames(spark, SMALL)
    policy = CurationPolicy(cap_method="kll")
    signals = curation.clip_signals(*args).persist()
    listed = {r.clip_id for r in curation.uncertain(signals, policy).collect()}
    split = lambda p: {r.clip_id: r.split for r in curation.score(signals, curation.fit_stats(signals, p), p).collect()}
    a, b = split(CurationPolicy()), split(policy)
    assert {k for k in a if a[k] != b[k]} <= listed and len(listed) < 20
    assert not curation.uncertain(signals, CurationPolicy()).count()


def test_gaps_close_after_time():
    """A clip that ends, or stays silent, gives its open gap and loses its state."""
    import pandas as pd

    from avcurate.streaming import online

    class State:
        def __init__(self):
            self.value, self.hasTimedOut = None, False

        exists = property(lambda self: self.value is not None)
        get = property(lambda self: self.value)

        def update(self, value):
            self.value = value

        def remove(self):
            self.value = None

        def setTimeoutDuration(self, ms):
            self.ms = ms

    frame = lambda rows: iter([pd.DataFrame(rows, columns=["clip_id", "frame_no", "cx", "cy", "closes"])])
    run = lambda rows, s: [tuple(r) for b in online.fill_gaps((1,), frame(rows), s) for r in b.itertuples(index=False)]
    s = State()
    assert run([(1, 0, 2.0, 4.0, False), (1, 1, None, None, False)], s) == [(1, 0, 2.0, 4.0, False)] and s.exists and s.ms == online.IDLE_MS
    s.hasTimedOut = True
    assert run([], s) == [(1, 1, 2.0, 4.0, True)] and not s.exists
    s = State()
    assert run([(1, 0, 2.0, 4.0, False), (1, 1, None, None, False), (1, 1, None, None, True)], s) == [(1, 0, 2.0, 4.0, False), (1, 1, 2.0, 4.0, True)] and not s.exists
