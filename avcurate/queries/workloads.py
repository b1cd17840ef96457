"""The experiment workloads on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from avcurate.functions.text import asr_confidence, asr_confidence_bounded, by_utterance, cer, comprehensive_score, letter_vector, longer_length, route_mode, utterances
from avcurate.functions.vectors import cosine
from avcurate.operators import alignment, baselines, curation, curriculum, evaluate, instruct, lips, motion, normalise, resampler, signal, trainer
from avcurate.operators.curation import CurationPolicy
from avcurate.queries import twins as T
from avcurate.queries.registry import query, r6, rounded
from avcurate.sources import fixtures as fx
from avcurate.session import shared_path
from avcurate.sources.tables import load, write_scores_once

SCORES = ("s_asr", "snr_db", "snr_norm", "s_audio", "motion", "s_video", "s_comp")
SCORE_SQL = ", ".join(f"{T.r6(c)} AS {c}" for c in SCORES)


def curated(spark: SparkSession, d: str, policy: CurationPolicy = CurationPolicy(), **more) -> DataFrame:
    return curation.curate(fx.clip_text(spark, d), fx.clip_audio(spark, d), fx.clip_frames(spark, d), policy, **more)


def train_ids(spark: SparkSession, d: str) -> DataFrame:
    return curriculum.split_dataset(fx.clip_text(spark, d)).where("part = 'train'").select("clip_id")


# --- W1, W2: the corpus, screening and splits ---------------------------------------------------


@query(f"""WITH {T.curated()}, p AS (SELECT split, CASE WHEN {T.bucket100('clip_id')} < 80 THEN 'train' ELSE 'test' END AS part FROM curated)
SELECT part, split, (2 * grouping(part) + grouping(split))::BIGINT AS level, count(*) AS n FROM p GROUP BY ROLLUP (part, split)""")
def w1_dataset_card(spark, d):
    return evaluate.dataset_card(curriculum.split_dataset(curated(spark, d)))


@query(f"""WITH {T.CLIPS}, lm AS (SELECT label AS l, count(*) FILTER (vec_id % 7 <> 3)::DOUBLE / count(*) AS coverage FROM embeddings GROUP BY label),
x AS (SELECT c.clip_id, coverage, {T.asr('hyp_text', 'ref_text')} AS s_asr FROM clips c LEFT JOIN lm ON l = clip_id % 10)
SELECT clip_id, coalesce(round(coverage, 9) >= 0.85, false) AND coalesce(round(s_asr, 9) >= 0.2, false) AS keep,
    CASE WHEN NOT coalesce(round(coverage, 9) >= 0.85, false) THEN 'occluded' WHEN NOT coalesce(round(s_asr, 9) >= 0.2, false) THEN 'mismatched' ELSE 'ok' END AS reason FROM x""")
def w1_screening(spark, d):
    cov = lips.coverage(lips.select_lips(fx.landmark_frames(spark, d), fx.LIP_INDICES)).select(F.col("clip_id").alias("track"), "coverage")
    clips = fx.clip_text(spark, d).select("clip_id", (F.col("clip_id") % 10).cast("int").alias("track"), asr_confidence("hyp_text", "ref_text").alias("s_asr"))
    return lips.screen(clips.join(cov, "track", "left"), 0.85, 0.2)


@query(f"SELECT doc_id AS clip_id, CASE WHEN {T.bucket100('doc_id')} < 80 THEN 'train' ELSE 'test' END AS part FROM documents")
def w2_split_hash(spark, d):
    return curriculum.split_dataset(fx.clip_text(spark, d)).select("clip_id", "part")


@query("""SELECT doc_id AS clip_id, CASE WHEN row_number() OVER (ORDER BY md5(doc_id::VARCHAR), doc_id) <= floor(0.8 * count(*) OVER ()) THEN 'train' ELSE 'test' END AS part FROM documents""")
def w2_split_exact(spark, d):
    return curriculum.split_dataset(fx.clip_text(spark, d), "exact").select("clip_id", "part")


@query("""SELECT doc_id AS clip_id, CASE WHEN row_number() OVER (PARTITION BY source ORDER BY md5(doc_id::VARCHAR), doc_id) <= floor(0.8 * count(*) OVER (PARTITION BY source)) THEN 'train' ELSE 'test' END AS part FROM documents""")
def w2_split_stratified(spark, d):
    return curriculum.split_dataset(fx.clip_text(spark, d), "stratified").select("clip_id", "part")


# --- W3: curation --------------------------------------------------------------------------------

CURATED_SQL = f"SELECT clip_id, speaker, category, {SCORE_SQL}, split, reason FROM curated"


def curated_columns(df: DataFrame) -> DataFrame:
    return rounded(df, *SCORES).select("clip_id", "speaker", "category", *SCORES, "split", "reason")


@query(f"WITH {T.curated()} {CURATED_SQL}")
def w3_curate(spark, d):
    return curated_columns(curated(spark, d))


@query(f"WITH {T.curated(fit=f'(SELECT * FROM signals WHERE {T.bucket100("clip_id")} < 80)')} {CURATED_SQL}")
def w3_curate_train_fit(spark, d):
    return curated_columns(curated(spark, d, fit_on=train_ids(spark, d)))


@query(f"WITH {T.curated(snr_by='speaker')} {CURATED_SQL}")
def w3_curate_per_speaker(spark, d):
    return curated_columns(curated(spark, d, CurationPolicy(scope="speaker")))


@query(f"WITH {T.curated()} SELECT clip_id, split FROM curated")
def w3_curate_bounded(spark, d):
    return curation.curate_bounded(fx.clip_text(spark, d), fx.clip_audio(spark, d), fx.clip_frames(spark, d)).select("clip_id", "split")


@query(f"""WITH {T.curated()} SELECT split, speaker, (2 * grouping(split) + grouping(speaker))::BIGINT AS level, count(*) AS n, {T.mean9('s_asr')} AS mean_asr,
{T.mean9('snr_db')} AS mean_snr, {T.mean9('motion')} AS mean_motion, {T.mean9('s_comp')} AS mean_comp FROM curated GROUP BY ROLLUP (split, speaker)""")
def w3_report(spark, d):
    return rounded(curation.curation_report(curated(spark, d)), "mean_asr", "mean_snr", "mean_motion", "mean_comp")


THRESHOLDS = [0.3, 0.4, 0.45, 0.5, 0.55, 0.6, 0.65, 0.7, 0.8]


@query(f"""WITH {T.curated()} SELECT t.t::DOUBLE AS threshold, count(*) FILTER (round(s_comp, 9) >= t.t) AS accepted,
{T.r6('count(*) FILTER (round(s_comp, 9) >= t.t)::DOUBLE / count(*)')} AS rate FROM curated, (SELECT unnest({THRESHOLDS}::DOUBLE[]) AS t) t GROUP BY t.t""")
def w3_accept_curve(spark, d):
    return rounded(curation.accept_curve(curated(spark, d), THRESHOLDS), "rate")


@query(f"WITH {T.curated()} SELECT {T.r6('quantile_cont(s_comp, 1 - 0.612)')} AS threshold FROM curated")
def w3_threshold_for_rate(spark, d):
    return rounded(curation.threshold_for_rate(curated(spark, d), 0.612), "threshold")


@query(f"""WITH {T.curated()} SELECT clip_id, CASE WHEN (('0x' || substr(md5(clip_id::VARCHAR), 1, 8))::BIGINT)::DOUBLE / 4294967296.0 < least(1.0, round(s_comp, 9) / 0.55) THEN 'accept' ELSE 'reject' END AS split FROM curated""")
def w3_curate_stochastic(spark, d):
    return curated(spark, d, CurationPolicy(mode="stochastic")).select("clip_id", "split")


@query(f"WITH {T.curated()} SELECT clip_id, {T.r6('s_comp')} AS s_comp FROM curated WHERE split = 'reject'")
def w3_hard_examples(spark, d):
    return rounded(curation.hard_examples(curated(spark, d)), "s_comp").select("clip_id", "s_comp")


@query(f"WITH {T.CLIPS} SELECT clip_id, {T.r6(T.asr('hyp_text', 'ref_text'))} AS s_asr FROM clips")
def m12_asr_confidence(spark, d):
    return fx.clip_text(spark, d).select("clip_id", r6(asr_confidence("hyp_text", "ref_text")).alias("s_asr"))


@query(f"""WITH {T.CLIPS}, x AS (SELECT *, {T.lev('hyp_text', 'ref_text')} AS dd, floor(0.3 * {T.longer('hyp_text', 'ref_text')})::INT AS k FROM clips)
SELECT clip_id, CASE WHEN dd <= k THEN {T.r6(T.asr('hyp_text', 'ref_text'))} END AS s_asr FROM x""")
def m12_asr_bounded(spark, d):
    k = F.floor(longer_length("hyp_text", "ref_text") * F.lit(0.3)).cast("int")
    return fx.clip_text(spark, d).select("clip_id", r6(asr_confidence_bounded("hyp_text", "ref_text", k)).alias("s_asr"))


@query(f"WITH {T.AUDIO}, {T.SNR} SELECT clip_id, n, {T.r6('snr_db')} AS snr_db, snr_kind FROM snrdb")
def m13_snr(spark, d):
    return rounded(signal.snr_db(fx.clip_audio(spark, d)), "snr_db").select("clip_id", "n", "snr_db", "snr_kind")


@query(f"WITH {T.AUDIO}, {T.SNR} SELECT clip_id, {T.r6('snr_db')} AS snr_db, snr_kind FROM snrdb")
def m13_snr_packed(spark, d):
    packed = fx.clip_audio(spark, d).groupBy("clip_id").agg(F.sort_array(F.collect_list(F.struct("t", "clean", "noisy"))).alias("s"))
    db, kind = signal.snr_db_arrays(F.col("s.clean"), F.col("s.noisy"))
    return packed.select("clip_id", r6(db).alias("snr_db"), kind.alias("snr_kind"))


def _motion_query(name: str, norm: str, sql: str):
    def f(spark, d):
        return rounded(motion.motion_magnitude(fx.clip_frames(spark, d), norm), "motion").select("clip_id", "pairs", "motion")
    query(f"WITH {T.FRAMES}, {sql} SELECT clip_id, pairs, {T.r6('motion')} AS motion FROM motion", name)(f)


_motion_query("m16_motion", "l1", T.motion())
_motion_query("m16_motion_l2", "l2", T.motion("(x[2] - x[1]) * (x[2] - x[1])", "sqrt({})"))
_motion_query("m16_motion_signed", "signed", T.motion("x[2] - x[1]"))


@query(f"WITH {T.FRAMES}, {T.motion()} SELECT clip_id, pairs, {T.r6('motion')} AS motion FROM motion")
def m16_motion_chunked(spark, d):
    return rounded(motion.motion_by_chunks(fx.clip_frames(spark, d), 3), "motion")


@query(f"WITH {T.FRAMES}, {T.motion()} SELECT {T.r6('quantile_cont(motion, 0.9)')} AS motion_cap FROM motion")
def m17_motion_cap(spark, d):
    return rounded(motion.motion_cap(motion.motion_magnitude(fx.clip_frames(spark, d))), "motion_cap").select("motion_cap")


@query()
def m17_uncertain(spark, d):
    """Clips whose split a cap within the sketch's rank error could change."""
    policy = CurationPolicy(cap_method="kll")
    signals = write_scores_once(curation.clip_signals(fx.clip_text(spark, d), fx.clip_audio(spark, d), fx.clip_frames(spark, d)), shared_path(spark, "signals"))
    return rounded(curation.uncertain(signals, policy), "low", "high")


@query()
def m17_motion_cap_sketches(spark, d):
    """Caps by sketches, and how many clips' splits each would change."""
    m = motion.motion_magnitude(fx.clip_frames(spark, d)).select("motion")
    out = [motion.motion_cap(m, method=k).withColumn("method", F.lit(k)) for k in ("exact", "approx", "kll")]
    return out[0].unionByName(out[1]).unionByName(out[2])


@query(f"WITH {T.FRAMES}, {T.motion()}, c AS (SELECT quantile_cont(motion, 0.9) AS cap FROM motion) SELECT clip_id, {T.r6('CASE WHEN cap = 0 THEN 0.0 ELSE least(motion / cap, 1.0) END')} AS s_video FROM motion, c WHERE motion IS NOT NULL")
def m18_video_score(spark, d):
    m = motion.motion_magnitude(fx.clip_frames(spark, d)).where("motion is not null")
    return m.crossJoin(F.broadcast(motion.motion_cap(m).select("motion_cap"))).select("clip_id", r6(motion.video_score("motion", "motion_cap")).alias("s_video"))


@query(f"""WITH {T.curated()} SELECT clip_id, {T.r6('s_asr')} AS asr_only, {T.r6('snr_norm')} AS snr_only FROM curated""")
def m15_audio_ablations(spark, d):
    c = curated(spark, d)
    return c.select("clip_id", r6(curation.audio_score(F.col("s_asr"), F.col("snr_norm"), (1, 0))).alias("asr_only"), r6(curation.audio_score(F.col("s_asr"), F.col("snr_norm"), (0, 1))).alias("snr_only"))


# --- W4: lips ------------------------------------------------------------------------------------


def lip_frames(spark, d):
    return lips.select_lips(fx.landmark_frames(spark, d), fx.LIP_INDICES)


@query(f"WITH {T.LANDMARKS} SELECT clip_id, frame_no, idx::INT AS idx, {T.r6('x')} AS x, {T.r6('y')} AS y FROM pts")
def w4_points(spark, d):
    return rounded(lips.lip_track(lip_frames(spark, d)), "x", "y")


BOX_SQL = f"WITH {T.LANDMARKS} SELECT clip_id, frame_no, {', '.join(f'{T.r6(c)} AS {c}' for c in ('x0', 'y0', 'x1', 'y1', 'w', 'h'))} FROM boxes"


@query(BOX_SQL)
def w4_boxes(spark, d):
    return rounded(lips.bounding_boxes(lip_frames(spark, d)), "x0", "y0", "x1", "y1", "w", "h")


@query(BOX_SQL)
def w4_boxes_long(spark, d):
    return rounded(lips.bounding_boxes(lip_frames(spark, d), "long"), "x0", "y0", "x1", "y1", "w", "h")


@query(f"WITH {T.LANDMARKS} SELECT clip_id, {T.r6('mean_w')} AS mean_w, {T.r6('mean_h')} AS mean_h, crop FROM sizes")
def w4_crop_size(spark, d):
    return rounded(lips.crop_size(lips.bounding_boxes(lip_frames(spark, d))), "mean_w", "mean_h")


@query(f"WITH {T.LANDMARKS}, s AS (SELECT (2 * ceil(round(1.2 * greatest(avg(w), avg(h)), 9) / 2))::BIGINT AS crop FROM boxes) SELECT DISTINCT clip_id, crop FROM boxes, s")
def w4_crop_size_dataset(spark, d):
    return lips.crop_size(lips.bounding_boxes(lip_frames(spark, d)), scope="dataset").select("clip_id", "crop")


@query(f"WITH {T.LANDMARKS} SELECT clip_id, g.g::DOUBLE AS gamma, (2 * ceil(round(g.g * greatest(mean_w, mean_h), 9) / 2))::BIGINT AS crop FROM sizes, (SELECT unnest([1.0, 1.1, 1.2, 1.5, 2.0]::DOUBLE[]) AS g) g")
def w4_crop_size_sweep(spark, d):
    return lips.crop_size_sweep(lips.bounding_boxes(lip_frames(spark, d)), [1.0, 1.1, 1.2, 1.5, 2.0]).select("clip_id", "gamma", "crop")


@query(f"WITH {T.LANDMARKS} SELECT clip_id, frame_no, {T.r6('cx')} AS cx, {T.r6('cy')} AS cy FROM cents")
def w4_centroids(spark, d):
    return rounded(lips.centroids(lip_frames(spark, d)), "cx", "cy")


LANDMARKS_SQL = f"WITH {T.LANDMARKS} SELECT clip_id, frame_no, {T.r6('cx')} AS cx, {T.r6('cy')} AS cy, filled FROM interp"


@query(LANDMARKS_SQL)
def w4_interp(spark, d):
    return rounded(lips.interpolate(lips.centroids(lip_frames(spark, d))), "cx", "cy")


@query(f"WITH {T.LANDMARKS} SELECT i.clip_id, i.frame_no, CASE WHEN bf IS NULL OR af IS NULL THEN NULL ELSE {T.r6('i.cx')} END AS cx, CASE WHEN bf IS NULL OR af IS NULL THEN NULL ELSE {T.r6('i.cy')} END AS cy FROM interp i JOIN near n USING (clip_id, frame_no)")
def w4_interp_null_edges(spark, d):
    return rounded(lips.interpolate(lips.centroids(lip_frames(spark, d)), "null"), "cx", "cy").select("clip_id", "frame_no", "cx", "cy")


def lip_windows(spark, d):
    f = lip_frames(spark, d)
    cents = lips.interpolate(lips.centroids(f))
    return cents, lips.crop_windows(cents, lips.crop_size(lips.bounding_boxes(f)))


@query(f"WITH {T.LANDMARKS} SELECT clip_id, frame_no, crop, {', '.join(f'{T.r6(c)} AS {c}' for c in ('x0', 'y0', 'x1', 'y1'))} FROM windows")
def w4_windows(spark, d):
    return rounded(lip_windows(spark, d)[1], "x0", "y0", "x1", "y1")


@query("""WITH f AS (SELECT label AS clip_id, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS frame_no, embedding::DOUBLE[] AS px FROM embeddings),
w AS (SELECT *, (frame_no % 5 - 1) AS x0, (frame_no % 7 - 1) AS y0 FROM f)
SELECT clip_id, frame_no, i.i AS at, round(CASE WHEN x0 + i.i % 4 BETWEEN 0 AND 7 AND y0 + i.i // 4 BETWEEN 0 AND 7 THEN px[(y0 + i.i // 4) * 8 + x0 + i.i % 4 + 1] ELSE 0.0 END, 6) + 0.0 AS value FROM w, range(0, 16) i(i)""")
def w4_pixels(spark, d):
    f = fx.landmark_frames(spark, d).select("clip_id", "frame_no")
    px = load(spark, d, "embeddings").select(F.col("label").alias("clip_id"), "vec_id", F.col("embedding").alias("pixels"))
    from pyspark.sql import Window
    w = Window.partitionBy("clip_id").orderBy("vec_id")
    frames = px.select("clip_id", (F.row_number().over(w) - 1).cast("bigint").alias("frame_no"), "pixels", F.lit(8).alias("height"), F.lit(8).alias("width"))
    win = f.select("clip_id", "frame_no", (F.col("frame_no") % 5 - 1).alias("x0"), (F.col("frame_no") % 7 - 1).alias("y0"), F.lit(4).cast("bigint").alias("crop"))
    return lips.crop_pixels(frames, win).select("clip_id", "frame_no", F.posexplode("pixels").alias("at", "v")).select("clip_id", "frame_no", F.col("at").cast("bigint").alias("at"), r6("v").alias("value"))


@query(f"""WITH {T.LANDMARKS}, j AS (SELECT i.clip_id, i.frame_no, i.cx, i.cy, i.cx - w.x0 AS rx, i.cy - w.y0 AS ry FROM interp i JOIN windows w USING (clip_id, frame_no)),
s AS (SELECT clip_id, sqrt((cx - lag(cx) OVER o) ** 2 + (cy - lag(cy) OVER o) ** 2) AS a, sqrt((rx - lag(rx) OVER o) ** 2 + (ry - lag(ry) OVER o) ** 2) AS b FROM j WINDOW o AS (PARTITION BY clip_id ORDER BY frame_no))
SELECT clip_id, {T.r6('avg(a)')} AS jitter_raw, {T.r6('avg(b)')} AS jitter_crop FROM s GROUP BY clip_id""")
def w4_jitter(spark, d):
    return rounded(lips.track_jitter(*lip_windows(spark, d)), "jitter_raw", "jitter_crop")


# --- W5, W6, W8: systems -------------------------------------------------------------------------


def pairs(spark, d):
    return baselines.transcribe(fx.clip_text(spark, d))


def board(spark, d):
    return evaluate.board_of(evaluate.measured(pairs(spark, d)))


@query(f"WITH {T.MEASURED} SELECT system_id, count(*) AS n, count(*) FILTER (cer IS NULL) AS undefined, {T.r6('avg(cer)')} AS macro, {T.r6('sum(dist)::DOUBLE / sum(ref_len)')} AS micro FROM meas GROUP BY system_id")
def w5_cer(spark, d):
    return rounded(evaluate.corpus_cers(pairs(spark, d)), "macro", "micro")


@query(f"WITH {T.MEASURED} SELECT system_id, {T.r6('avg(sim)')} AS emb_sim, count(*) FILTER (sim IS NULL) AS undefined FROM meas GROUP BY system_id")
def w5_embsim(spark, d):
    m = evaluate.measured(pairs(spark, d))
    return rounded(m.groupBy("system_id").agg(F.avg("sim").alias("emb_sim"), F.count_if(F.col("sim").isNull()).alias("undefined")), "emb_sim")


LEADER_SQL = f"""SELECT system_id, n, {T.r6('emb_sim')} AS emb_sim, {T.r6('cer')} AS cer, {T.r6('cer_micro')} AS cer_micro, {T.r6('cs')} AS cs, rank() OVER (ORDER BY round(cs, 9) DESC)::INT AS rank_cs,
round(emb_sim, 9) = round(max(emb_sim) OVER (), 9) AS best_emb_sim, round(cer, 9) = round(min(cer) OVER (), 9) AS best_cer, round(cs, 9) = round(max(cs) OVER (), 9) AS best_cs FROM board"""


@query(f"WITH {T.BOARD} {LEADER_SQL}")
def w5_leaderboard(spark, d):
    return rounded(evaluate.leaderboard(board(spark, d)), "emb_sim", "cer", "cer_micro", "cs")


@query(f"WITH {T.BOARD} {LEADER_SQL}")
def w5_leaderboard_distinct(spark, d):
    """The same, with equal pairs measured once."""
    return rounded(evaluate.leaderboard(evaluate.board_of(evaluate.measured_once(fx.clip_text(spark, d, dealt=False), baselines.transcribe))), "emb_sim", "cer", "cer_micro", "cs")


GOLD = T.golden_cte(fx.PRINTED)
LINES = f"""{GOLD}, pairs_ AS (SELECT 'sys' || lpad((l_suppkey % 13 + 1)::VARCHAR, 2, '0') AS system_id, l_discount::DECIMAL(4,2) AS e, 1 - l_tax::DECIMAL(4,2) AS s FROM lineitem),
lines AS (SELECT system_id, family, params_b, m.emb_sim, m.cer, m.cs FROM gold JOIN (SELECT system_id, round(sum(s)::DOUBLE / count(*), 6)::DECIMAL(9,6) AS emb_sim, round(sum(e)::DOUBLE / count(*), 6)::DECIMAL(9,6) AS cer,
    round(sum(0.5 * (1 - e) + 0.5 * s)::DOUBLE / count(*), 6)::DECIMAL(9,6) AS cs FROM pairs_ GROUP BY system_id) m USING (system_id))"""
FAMILY_SQL = "count(*) AS n, {es} AS emb_sim, {c} AS cer, {cs} AS cs, max_by(system_id, (round(cs, 9), system_id)) AS best".format(es=T.r6("avg(emb_sim)"), c=T.r6("avg(cer)"), cs=T.r6("avg(cs)"))


def families(spark):
    return fx.golden(spark).select("system_id", "family", "params_b")


@query(f"WITH {T.BOARD}, {GOLD} SELECT family, {FAMILY_SQL} FROM (SELECT b.*, g.family FROM board b JOIN gold g USING (system_id)) GROUP BY family")
def w5_family(spark, d):
    return rounded(evaluate.family_report(board(spark, d).join(F.broadcast(families(spark)), "system_id")), "emb_sim", "cer", "cs")


DOMINATED = "EXISTS (SELECT 1 FROM {t} o WHERE {a} AND {b})"


def frontier_sql(t: str, lit: str = "round(1 - {x}.cer, 9)", sem: str = "round({x}.emb_sim, 9)") -> str:
    o, s = lit.format(x="o"), lit.format(x="b")
    p, q = sem.format(x="o"), sem.format(x="b")
    return f"NOT EXISTS (SELECT 1 FROM {t} o WHERE {o} >= {s} AND {p} >= {q} AND ({o} > {s} OR {p} > {q}))"


@query(f"WITH {T.BOARD} SELECT system_id, {T.r6('1 - cer')} AS literal, {T.r6('emb_sim')} AS semantic, {frontier_sql('board')} AS on_frontier FROM board b")
def w5_frontier(spark, d):
    return rounded(evaluate.cs_plane(board(spark, d)), "literal", "semantic")


@query(f"WITH {T.BOARD}, {GOLD}, f AS (SELECT b.*, g.params_b FROM board b JOIN gold g USING (system_id) WHERE g.params_b IS NOT NULL) SELECT system_id, params_b, {T.r6('cs')} AS cs FROM f b WHERE {frontier_sql('f', '-{x}.params_b', 'round({x}.cs, 9)')}")
def w5_params_frontier(spark, d):
    b = board(spark, d).join(F.broadcast(families(spark)), "system_id")
    return rounded(evaluate.params_frontier(b), "cs").select("system_id", "params_b", "cs")


def delta_sql(board_: str, base: str, variant: str) -> str:
    parts = " UNION ALL ".join(f"SELECT '{m}' AS metric, max({m}::DOUBLE) FILTER (system_id = '{base}') AS base, max({m}::DOUBLE) FILTER (system_id = '{variant}') AS variant FROM {board_}" for m in ("emb_sim", "cer", "cs"))
    return f"SELECT metric, {T.r6('base')} AS base, {T.r6('variant')} AS variant, {T.r6('variant - base')} AS delta, {T.r6('(variant - base) / nullif(base, 0)')} AS rel FROM ({parts})"


def _delta_query(name: str, base: str, variant: str, golden: bool):
    def f(spark, d):
        return rounded(evaluate.ablation_delta(fx.line_board(spark, d) if golden else board(spark, d), base, variant), "base", "variant", "delta", "rel")
    query(f"WITH {LINES if golden else T.BOARD} {delta_sql('lines' if golden else 'board', base, variant)}", name)(f)


_delta_query("w6_ablation", "sys11", "sys13", False)
_delta_query("w7_curriculum_delta", "sys11", "sys12", False)
_delta_query("g_video_ablation", "sys11", "sys13", True)
_delta_query("g_curriculum_delta", "sys11", "sys12", True)
_delta_query("g_generic_delta", "sys10", "sys12", True)
_delta_query("g_size_delta", "sys10", "sys11", True)


@query(f"WITH {T.curated(comp='s_audio')} SELECT clip_id, {T.r6('s_comp')} AS s_comp, split FROM curated")
def w6_audio_only_split(spark, d):
    return rounded(curated(spark, d, CurationPolicy(modalities="audio")), "s_comp").select("clip_id", "s_comp", "split")


@query(f"WITH {T.curated(comp='s_video')} SELECT clip_id, {T.r6('s_comp')} AS s_comp, split FROM curated")
def w6_video_only_split(spark, d):
    return rounded(curated(spark, d, CurationPolicy(modalities="video")), "s_comp").select("clip_id", "s_comp", "split")


@query(f"WITH {T.curated(comp='coalesce(0.6 * s_audio + 0.4 * s_video, s_audio, s_video)')} SELECT clip_id, {T.r6('s_comp')} AS s_comp, split FROM curated")
def w6_renormalised_split(spark, d):
    return rounded(curated(spark, d, CurationPolicy(renormalise=True)), "s_comp").select("clip_id", "s_comp", "split")


@query(f"WITH {LINES} SELECT system_id, cs, round(0.5 * (1 - cer) + 0.5 * emb_sim, 2)::DECIMAL(5,2) AS recomputed, round(0.5 * (1 - cer) + 0.5 * emb_sim, 2) = round(cs, 2) AS equal FROM lines WHERE system_id <> 'sys13'")
def g_tab1_cs(spark, d):
    return _recomputed_cs(spark, d).where("system_id <> 'sys13'")


@query(f"WITH {LINES} SELECT system_id, cs, round(0.5 * (1 - cer) + 0.5 * emb_sim, 2)::DECIMAL(5,2) AS recomputed, round(0.5 * (1 - cer) + 0.5 * emb_sim, 2) = round(cs, 2) AS equal FROM lines WHERE system_id IN ('sys11', 'sys13')")
def g_tab2_cs(spark, d):
    return _recomputed_cs(spark, d).where("system_id in ('sys11', 'sys13')")


def _recomputed_cs(spark, d):
    """Scores of systems from their mean error rates and similarities, against the means of their lines' scores; on decimals, where halves round up."""
    half = F.lit("0.5").cast("decimal(2,1)")
    cs = F.round(half * (1 - F.col("cer")) + half * F.col("emb_sim"), 2).cast("decimal(5,2)")
    return fx.line_board(spark, d).select("system_id", "cs", cs.alias("recomputed")).withColumn("equal", F.col("recomputed") == F.round("cs", 2))


@query(f"WITH {LINES} SELECT system_id, {T.r6('1 - cer')} AS literal, {T.r6('emb_sim')} AS semantic, {frontier_sql('lines')} AS on_frontier FROM lines b")
def g_frontier(spark, d):
    return rounded(evaluate.cs_plane(fx.line_board(spark, d)), "literal", "semantic")


@query(f"WITH {LINES}, f AS (SELECT * FROM lines WHERE params_b IS NOT NULL) SELECT system_id, params_b, cs FROM f b WHERE {frontier_sql('f', '-{x}.params_b', 'round({x}.cs, 9)')}")
def g_params_frontier(spark, d):
    return evaluate.params_frontier(fx.line_board(spark, d)).select("system_id", "params_b", "cs")


@query(f"WITH {LINES} SELECT family, {FAMILY_SQL} FROM lines GROUP BY family")
def g_family(spark, d):
    return rounded(evaluate.family_report(fx.line_board(spark, d)), "emb_sim", "cer", "cs")


@query(f"""WITH o AS (SELECT {T.bucket100('o_orderkey')} < 80 AS tr, o_orderstatus = 'F' AS ok FROM orders),
n AS (SELECT count(*) FILTER (tr AND ok) AS accepted, count(*) FILTER (tr AND NOT ok) AS rejected, count(*) FILTER (NOT tr) AS test FROM o)
SELECT accepted + rejected + test AS total, accepted + rejected AS train, test, accepted, rejected, accepted * 3 AS easy_exposures, rejected * 5 AS hard_exposures, {T.r6('(rejected * 5)::DOUBLE / nullif(accepted * 3 + rejected * 5, 0)')} AS hard_share FROM n""")
def g_dataset_counts(spark, d):
    """From the counts of accepted (finished) and rejected orders, and of the test part, all other figures follow."""
    train, accepted = fx.bucket100(F.col("o_orderkey")) < 80, F.col("o_orderstatus") == "F"
    n = load(spark, d, "orders").agg(F.count_if(train & accepted).alias("accepted"), F.count_if(train & ~accepted).alias("rejected"), F.count_if(~train).alias("test"))
    return n.select((F.col("accepted") + F.col("rejected") + F.col("test")).alias("total"), (F.col("accepted") + F.col("rejected")).alias("train"), "test", "accepted", "rejected",
                    (F.col("accepted") * 3).alias("easy_exposures"), (F.col("rejected") * 5).alias("hard_exposures"), r6(F.try_divide(F.col("rejected") * 5, F.col("accepted") * 3 + F.col("rejected") * 5)).alias("hard_share"))


@query(f"WITH {GOLD} SELECT system_id, {T.r6('1 - cer')} AS literal, {T.r6('emb_sim')} AS semantic, {T.r6('cs')} AS cs FROM gold")
def w8_plane(spark, d):
    return rounded(fx.golden(spark).select("system_id", (1 - F.col("cer")).alias("literal"), F.col("emb_sim").alias("semantic"), "cs"), "literal", "semantic", "cs")


@query(f"""WITH {T.BOARD}, s AS (SELECT a.a AS alpha, system_id, (1 - a.a) * (1 - cer) + a.a * emb_sim AS cs FROM board, (SELECT unnest([0, 0.25, 0.5, 0.75, 1]::DOUBLE[]) AS a) a)
SELECT alpha, system_id, {T.r6('cs')} AS cs, rank() OVER (PARTITION BY alpha ORDER BY round(cs, 9) DESC)::INT AS rank_cs FROM s""")
def w8_alpha_sweep(spark, d):
    return rounded(evaluate.cs_alpha_sweep(board(spark, d), [0, 0.25, 0.5, 0.75, 1]), "cs")


# --- W7: curriculum --------------------------------------------------------------------------------


def train_split(spark, d):
    return curriculum.split_dataset(curated(spark, d)).where("part = 'train'").select("clip_id", "split", "s_comp")


TRAIN_SQL = f"{T.curated()}, tr AS (SELECT clip_id, split, s_comp FROM curated WHERE {T.bucket100('clip_id')} < 80)"


def _schedule_query(name: str, mode: str, sql: str):
    def f(spark, d):
        x = train_split(spark, d)
        if mode == "ranked":
            x = curriculum.rank_difficulty(x)
        return curriculum.curriculum_schedule(x, mode)
    query(f"WITH {TRAIN_SQL}, s AS ({sql}) SELECT phase::INT AS phase, epoch::INT AS epoch, clip_id, split, md5(phase || ':' || epoch || ':' || clip_id) AS \"order\" FROM s", name)(f)


def _phases(*parts: tuple[int, str, int]) -> str:
    return " UNION ALL ".join(f"SELECT {p} AS phase, e.e AS epoch, clip_id, split FROM tr, range(1, {n + 1}) e(e) WHERE {where}" for p, where, n in parts)


EASY, HARD = "split = 'accept'", "split = 'reject'"
_schedule_query("w7_schedule", "two_phase", _phases((1, EASY, 3), (2, HARD, 5)))
_schedule_query("w7_schedule_cumulative", "cumulative", _phases((1, EASY, 3), (2, "true", 5)))
_schedule_query("w7_schedule_none", "none", _phases((1, "true", 8)))
_schedule_query("w7_schedule_reverse", "reverse", _phases((1, HARD, 5), (2, EASY, 3)))
_schedule_query("w7_schedule_easy_only", "easy_only", _phases((1, EASY, 8)))
_schedule_query("w7_schedule_ranked", "ranked", "SELECT 1 AS phase, e.e AS epoch, clip_id, split FROM (SELECT *, ntile(8) OVER (ORDER BY coalesce(-round(s_comp, 9), 'inf'::DOUBLE), clip_id) AS bucket FROM tr), range(1, 9) e(e) WHERE e.e >= bucket")


@query(f"""WITH {TRAIN_SQL}, x AS (SELECT clip_id, coalesce(-round(s_comp, 9), 'inf'::DOUBLE) AS o FROM tr)
SELECT clip_id, row_number() OVER w AS rank, {T.r6('CASE WHEN count(*) OVER () > 1 THEN (row_number() OVER w - 1)::DOUBLE / (count(*) OVER () - 1) ELSE 0.0 END')} AS pct, ntile(8) OVER w::INT AS bucket FROM x WINDOW w AS (ORDER BY o, clip_id)""".replace("ntile(8) OVER w::INT AS", "(ntile(8) OVER w)::INT AS"))
def w7_difficulty(spark, d):
    return rounded(curriculum.rank_difficulty(train_split(spark, d)).select("clip_id", "rank", "pct", "bucket"), "pct")


@query(f"""WITH {TRAIN_SQL}, s AS ({_phases((1, EASY, 3), (2, HARD, 5))}) SELECT split, count(DISTINCT clip_id) AS samples, count(*) AS exposures, {T.r6('count(*)::DOUBLE / (SELECT count(*) FROM s)')} AS share FROM s GROUP BY split""")
def w7_exposure(spark, d):
    return rounded(curriculum.exposure_report(train_split(spark, d)), "share")


@query(f"""WITH {TRAIN_SQL}, q AS (SELECT CASE WHEN split = 'accept' THEN 1 ELSE 2 END AS phase, greatest(clip_id % 100 / 100.0::DOUBLE, 1e-12) AS p FROM tr)
SELECT phase::INT AS phase, count(*) AS n, {T.r6('avg(-ln(p))')} AS loss FROM q GROUP BY phase""")
def w7_losses(spark, d):
    """Phase losses of given probabilities: the second class gets clip_id mod 100 hundredths."""
    p = (F.col("clip_id") % 100) / 100.0
    x = train_split(spark, d).select(F.when(F.col("split") == "accept", 1).otherwise(2).alias("phase"), F.array(1 - p, p).alias("p"), F.lit(1).alias("y"))
    return rounded(curriculum.expected_ce(x), "loss")


def ranked_trainable(spark, d):
    """Vectors with their quality, split and bucket of difficulty."""
    x = trainer.with_quality(fx.trainable(spark, d))
    return curriculum.rank_difficulty(x, "quality", key="vec_id").drop("rank", "pct")


@query()
def w7_compare(spark, d):
    """Loss and accuracy of a softmax regression under all six schedules."""
    x = write_scores_once(ranked_trainable(spark, d).select("vec", "y", "part", "split", "bucket"), shared_path(spark, "ranked-vectors"))
    return rounded(trainer.compare_schedules(x, steps=2), "loss", "accuracy")


@query()
def w7_compare_curated(spark, d):
    """The same on the curated corpus: a clip's vector and class are those of its first frame, its split is the curation's."""
    emb = load(spark, d, "embeddings")
    n = emb.agg(F.count("*").alias("n_emb"))
    vecs = emb.select("vec_id", F.col("embedding").cast("array<double>").alias("vec"), F.col("label").alias("y"))
    clips = curriculum.split_dataset(curated(spark, d)).select("clip_id", "part", "split", "s_comp").crossJoin(F.broadcast(n))
    x = clips.withColumn("vec_id", F.col("clip_id") % F.col("n_emb")).join(vecs, "vec_id")
    x = write_scores_once(curriculum.rank_difficulty(x).select("clip_id", "vec", "y", "part", "split", "bucket"), shared_path(spark, "curated-vectors"))
    return rounded(trainer.compare_schedules(x, steps=1), "loss", "accuracy")


@query()
def w7_phase_losses(spark, d):
    """Cross-entropy of the weights that the two-phase schedule leaves, over each phase's rows."""
    return rounded(trainer.phase_losses(trainer.with_quality(fx.trainable(spark, d)).where("part = 'train'"), steps=2), "loss")


@query(f"""WITH t AS (SELECT vec_id, label AS y, embedding::DOUBLE[] AS vec, {T.bucket100('vec_id')} < 80 AS tr FROM embeddings),
c AS (SELECT y, i.i AS i, avg(vec[i.i]) AS v FROM t, range(1, 65) i(i) WHERE tr GROUP BY ALL), cv AS (SELECT y, list(v ORDER BY i) AS c FROM c GROUP BY y),
q AS (SELECT vec_id, tr, list_inner_product(vec, c) / (sqrt(list_inner_product(vec, vec)) * sqrt(list_inner_product(c, c))) AS quality FROM t JOIN cv USING (y)),
k AS (SELECT quantile_cont(quality, 0.39) AS cut FROM q WHERE tr)
SELECT vec_id, {T.r6('quality')} AS quality, CASE WHEN round(quality, 9) >= round(cut, 9) THEN 'accept' ELSE 'reject' END AS split FROM q, k""")
def w7_trainable_quality(spark, d):
    return rounded(trainer.with_quality(fx.trainable(spark, d)), "quality").select("vec_id", "quality", "split")


# --- W9, W10, W11: instructions, stages, resampling -----------------------------------------------

EXAMPLES = """n AS (SELECT *, lead(role) OVER w AS nrole, lead(text) OVER w AS ntext FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
ex AS (SELECT conv_id || ':' || turn || ':translate' AS example_id, conv_id, turn, 'translate' AS mode, '/translate ' || text AS prompt, text AS target FROM n WHERE role = 'user'
UNION ALL SELECT conv_id || ':' || turn || ':chat', conv_id, turn, 'chat', '/chat ' || text, ntext FROM n WHERE role = 'user' AND nrole = 'assistant')"""


@query(f"WITH {EXAMPLES} SELECT * FROM ex")
def w10_mixed_instructions(spark, d):
    return instruct.mix_modes(instruct.build_instructions(fx.turns(spark, d)))


@query(f"WITH {EXAMPLES} SELECT * FROM ex")
def w10_instructions_by_join(spark, d):
    return instruct.build_instructions(fx.turns(spark, d), "join")


@query(f"""WITH {EXAMPLES}, k AS (SELECT least(1.0, count(*) FILTER (mode <> 'chat') * 0.25::DOUBLE / nullif(count(*) FILTER (mode = 'chat') * 0.75::DOUBLE, 0)) AS keep FROM ex)
SELECT ex.* FROM ex, k WHERE mode <> 'chat' OR {T.bucket100('example_id')} < 100 * keep""")
def w10_mix_by_ratio(spark, d):
    return instruct.mix_modes(instruct.build_instructions(fx.turns(spark, d)), 0.25)


@query(f"""WITH {EXAMPLES} SELECT example_id, CASE WHEN regexp_matches(prompt, '^/translate\\b') THEN 'translate' ELSE 'chat' END AS routed, trim(regexp_replace(prompt, '^/(translate|chat)\\b', ''), ' ') AS payload FROM ex""")
def w10_route_mode(spark, d):
    mode, payload = route_mode("prompt")
    return instruct.build_instructions(fx.turns(spark, d)).select("example_id", mode.alias("routed"), payload.alias("payload"))


@query(f"""WITH {EXAMPLES}, u AS (SELECT *, {T.pieces('target')} AS t FROM ex), h AS (SELECT *, list_transform(t, lambda r: regexp_replace(r, '[aeiou]', '', 'g')) AS hyp FROM u)
SELECT example_id, CASE WHEN mode = 'translate' THEN {T.r6('1 - (' + T.asr('hyp', 't') + ')')} END AS difficulty FROM h""")
def w10_translation_difficulty(spark, d):
    x = instruct.build_instructions(fx.turns(spark, d)).withColumn("target", utterances("target"))
    x = x.withColumn("hyp", F.regexp_replace("target", "[aeiou]", ""))
    return rounded(instruct.translation_difficulty(x), "difficulty").select("example_id", "difficulty")


@query(f"""WITH {EXAMPLES}, u AS (SELECT conv_id, turn, {T.pieces('target')} AS u FROM ex WHERE mode = 'translate'),
h AS (SELECT *, list_transform(u, lambda r: CASE (conv_id + turn) % 3 WHEN 0 THEN r WHEN 1 THEN regexp_replace(r, '[aeiou]', '', 'g') ELSE reverse(r) END) AS h FROM u),
q AS (SELECT conv_id, turn, max(1 - ({T.asr('h', 'u')})) AS difficulty FROM h GROUP BY ALL),
tr AS (SELECT example_id AS clip_id, mode, CASE WHEN round(1 - difficulty, 9) >= 0.55 THEN 'accept' ELSE 'reject' END AS split FROM ex JOIN q USING (conv_id, turn)),
s AS (SELECT 1 AS phase, e.e AS epoch, * FROM tr, range(1, 4) e(e) WHERE split = 'accept' UNION ALL SELECT 2, e.e, * FROM tr, range(1, 6) e(e) WHERE split = 'reject')
SELECT phase::INT AS phase, epoch::INT AS epoch, clip_id AS example_id, split, md5(phase || ':' || epoch || ':' || clip_id) AS "order" FROM s""")
def w10_stage3_schedule(spark, d):
    """Instruction examples of both modes under the curriculum: how well a turn is translated says how hard it is."""
    x = instruct.build_instructions(fx.turns(spark, d)).withColumn("target", F.when(F.col("mode") == "translate", utterances("target")).otherwise(F.col("target")))
    way = (F.col("conv_id") + F.col("turn")) % 3
    hyp = F.when(way == 0, F.col("target")).when(way == 1, F.regexp_replace("target", "[aeiou]", "")).otherwise(by_utterance("target", F.reverse))
    x = instruct.scheduled_examples(x.withColumn("hyp", hyp))
    return curriculum.curriculum_schedule(x.withColumn("clip_id", F.col("example_id"))).withColumnRenamed("clip_id", "example_id")


@query("""SELECT * FROM (VALUES ('1a', 1, 'pages', 1.0::DOUBLE, 'resampler'), ('1b', 2, 'embeddings', 0.3::DOUBLE, 'resampler'), ('2', 3, 'documents', 1.0::DOUBLE, 'resampler'), ('2', 3, 'documents', 1.0::DOUBLE, 'audio_encoder'),
('3', 4, 'conversations', 1.0::DOUBLE, 'resampler'), ('3', 4, 'conversations', 1.0::DOUBLE, 'audio_encoder'), ('3', 4, 'conversations', 1.0::DOUBLE, 'vision_encoder'), ('3', 4, 'conversations', 1.0::DOUBLE, 'language_model')) t(stage, step, corpus, fraction, module)""")
def w10_stage_plan(spark, d):
    return alignment.stage_plan(spark).select("stage", "step", "corpus", "fraction", F.explode("trainable").alias("module"))


@query(f"SELECT vec_id, label FROM embeddings WHERE {T.bucket100('vec_id')} < 30")
def w10_fraction(spark, d):
    return alignment.fraction_sample(load(spark, d, "embeddings"), 0.3, "vec_id").select("vec_id", "label")


@query(f"""WITH {T.MEASURED}, s AS (SELECT system_id, pair_id, ref, hyp, round(0.5 * (1 - cer) + 0.5 * sim, 9) AS cs FROM meas WHERE cer IS NOT NULL AND sim IS NOT NULL),
r AS (SELECT *, 'good' AS kind, row_number() OVER (PARTITION BY system_id ORDER BY cs DESC, pair_id) AS rank FROM s UNION ALL SELECT *, 'bad', row_number() OVER (PARTITION BY system_id ORDER BY cs, pair_id) FROM s)
SELECT system_id, kind, rank::INT AS rank, pair_id, array_to_string(ref, chr(30)) AS ref, array_to_string(hyp, chr(30)) AS hyp, {T.r6('cs')} AS cs FROM r WHERE rank <= 2""")
def w9_cases(spark, d):
    return rounded(evaluate.mine_cases(evaluate.measured(pairs(spark, d)), 2), "cs")


V_TURN = T.VEC26.format


@query(f"""WITH {EXAMPLES}, t AS (SELECT conv_id, turn, target AS u FROM ex WHERE mode = 'translate'), c AS (SELECT conv_id, turn, target AS a FROM ex WHERE mode = 'chat'),
p AS (SELECT conv_id, turn, {T.pieces('u')} AS u, lower(u) AS lu, lower(a) AS la FROM t JOIN c USING (conv_id, turn)),
b AS (SELECT *, list_transform(u, lambda r: CASE (conv_id + turn) % 3 WHEN 0 THEN r WHEN 1 THEN regexp_replace(r, '[aeiou]', '', 'g') ELSE reverse(r) END) AS h FROM p),
w AS (SELECT *, lower(array_to_string(h, '')) AS lh FROM b),
v AS (SELECT *, {T.lev('h', 'u')}::DOUBLE / nullif({T.chars('u')}, 0) AS cer, {T.VEC26.format(t='lh')} AS vh, {T.VEC26.format(t='lu')} AS vu, {T.VEC26.format(t='la')} AS va FROM w),
s AS (SELECT 0.5 * (1 - cer) + 0.5 * list_inner_product(vh, vu) / nullif(sqrt(list_inner_product(vh, vh)) * sqrt(list_inner_product(vu, vu)), 0) AS cs, list_inner_product(vh, va) / nullif(sqrt(list_inner_product(vh, vh)) * sqrt(list_inner_product(va, va)), 0) AS relevance FROM v),
k AS (SELECT * FROM s WHERE cs IS NOT NULL AND relevance IS NOT NULL)
SELECT least(5, greatest(1, floor(round(cs, 9) * 5) + 1))::INT AS bucket, count(*) AS n, {T.r6('avg(cs)')} AS mean_cs, {T.r6('avg(relevance)')} AS mean_relevance, (SELECT {T.r6('corr(cs, relevance)')} FROM k) AS corr FROM k GROUP BY 1""")
def w9_comprehension_first(spark, d):
    x = instruct.build_instructions(fx.turns(spark, d))
    t = x.where("mode = 'translate'").select("conv_id", "turn", utterances("target").alias("u"))
    c = x.where("mode = 'chat'").select("conv_id", "turn", F.col("target").alias("a"))
    way = (F.col("conv_id") + F.col("turn")) % 3
    b = t.join(c, ["conv_id", "turn"]).withColumn("h", F.when(way == 0, F.col("u")).when(way == 1, F.regexp_replace("u", "[aeiou]", "")).otherwise(by_utterance("u", F.reverse)))
    s = b.select(comprehensive_score(cer("h", "u"), cosine(letter_vector("h"), letter_vector("u"))).alias("cs"), cosine(letter_vector("h"), letter_vector("a")).alias("relevance"))
    return rounded(evaluate.comprehension_first(s.where("cs is not null and relevance is not null")), "mean_cs", "mean_relevance", "corr")


def flat(df: DataFrame) -> DataFrame:
    return df.select("clip_id", "query_no", F.posexplode("vec").alias("dim", "v")).select("clip_id", "query_no", F.col("dim").cast("bigint").alias("dim"), r6("v").alias("value"))


OUT_SQL = f"SELECT clip_id, query_no, dim, {T.r6('value')} AS value FROM outs"


@query(f"WITH {T.softmax_resample()} {OUT_SQL}")
def w11_resample(spark, d):
    return flat(resampler.resample_by_rows(fx.tokens(spark, d), fx.queries(spark, d)))


@query(f"WITH {T.softmax_resample(64.0)} {OUT_SQL}")
def w11_resample_gain64(spark, d):
    return flat(resampler.resample(fx.tokens(spark, d), fx.queries(spark, d, gain=64.0)))


@query(f"WITH {T.softmax_resample(64.0)} {OUT_SQL}")
def w11_resample_streamed(spark, d):
    return flat(resampler.resample(fx.tokens(spark, d), fx.queries(spark, d, gain=64.0)))


@query(f"WITH {T.softmax_resample(1.0, 16)} {OUT_SQL}")
def w11_resample_16(spark, d):
    return flat(resampler.resample(fx.tokens(spark, d), fx.queries(spark, d, 16)))


@query("""WITH h AS (SELECT h.h AS head FROM range(0, 4) h(h)),
tok AS (SELECT label AS clip_id, vec_id AS token_no, head, list_slice(embedding::DOUBLE[], head * 16 + 1, head * 16 + 16) AS vec FROM embeddings, h),
qry AS (SELECT vec_id AS query_no, head, list_transform(list_slice(embedding::DOUBLE[], head * 16 + 1, head * 16 + 16), lambda x: x * 64) AS q FROM embeddings, h WHERE vec_id < 16),
l AS (SELECT clip_id, query_no, head, token_no, vec, list_inner_product(q, vec) / sqrt(16) AS l FROM tok JOIN qry USING (head)),
e AS (SELECT *, exp(l - max(l) OVER w) AS e FROM l WINDOW w AS (PARTITION BY clip_id, query_no, head)), a AS (SELECT *, e / sum(e) OVER (PARTITION BY clip_id, query_no, head) AS a FROM e)
SELECT clip_id, query_no, head * 16 + i.i AS dim, round(sum(a * vec[i.i + 1]), 6) + 0.0 AS value FROM a, range(0, 16) i(i) GROUP BY ALL""")
def w11_resample_heads(spark, d):
    return flat(resampler.resample(fx.tokens(spark, d), fx.queries(spark, d, 16, 64.0), heads=4))


@query("""WITH tok AS (SELECT label AS clip_id, vec_id // 100 AS grp, vec_id AS token_no, embedding::DOUBLE[] AS vec FROM embeddings),
qry AS (SELECT vec_id AS query_no, list_transform(embedding::DOUBLE[], lambda x: x * 64) AS q FROM embeddings WHERE vec_id < 16),
l AS (SELECT clip_id, grp, query_no, vec, list_inner_product(q, vec) / sqrt(64) AS l FROM tok, qry),
e AS (SELECT *, exp(l - max(l) OVER w) AS e FROM l WINDOW w AS (PARTITION BY clip_id, grp, query_no)), a AS (SELECT *, e / sum(e) OVER (PARTITION BY clip_id, grp, query_no) AS a FROM e)
SELECT clip_id, grp * 16 + query_no AS query_no, i.i AS dim, round(sum(a * vec[i.i + 1]), 6) + 0.0 AS value FROM a, range(0, 64) i(i) GROUP BY ALL""")
def w11_resample_groups(spark, d):
    """Every hundred consecutive tokens compressed by themselves."""
    return flat(resampler.resample(fx.tokens(spark, d), fx.queries(spark, d, 16, 64.0), group_tokens=100))


@query(f"SELECT label AS clip_id, 0::BIGINT AS query_no, i.i AS dim, {T.r6('avg((embedding::DOUBLE[])[i.i + 1])')} AS value FROM embeddings, range(0, 64) i(i) GROUP BY ALL")
def w11_meanpool(spark, d):
    return flat(resampler.mean_pool(fx.tokens(spark, d)))


@query(f"SELECT label AS clip_id, count(*) AS tokens_in, 64::BIGINT AS tokens_out, {T.r6('count(*) / 64.0')} AS ratio FROM embeddings GROUP BY label")
def w11_compression(spark, d):
    t = fx.tokens(spark, d)
    return rounded(resampler.compression_report(t, resampler.resample(t, fx.queries(spark, d))), "ratio")


@query("""SELECT clip_id, frame_no * 4 + p.p AS token_no, i.i AS dim, round(pixels[((p.p // 2) * 4 + i.i // 4) * 8 + (p.p % 2) * 4 + i.i % 4 + 1], 6) + 0.0 AS value
FROM (SELECT d.doc_id AS clip_id, j.j AS frame_no, e.embedding::DOUBLE[] AS pixels FROM documents d, range(0, 6) j(j), embeddings e WHERE e.vec_id = (d.doc_id + (j.j * (d.doc_id % 6)) // 5) % (SELECT count(*) FROM embeddings)), range(0, 4) p(p), range(0, 16) i(i)""")
def w11_patch_tokens(spark, d):
    """Patches of 4 x 4 pixels of all frames."""
    t = resampler.patch_tokens(fx.clip_frames(spark, d), 4)
    return t.select("clip_id", "token_no", F.posexplode("vec").alias("dim", "v")).select("clip_id", "token_no", F.col("dim").cast("bigint").alias("dim"), r6("v").alias("value"))


@query("""SELECT clip_id, row_number() OVER (PARTITION BY clip_id ORDER BY rank, token_no) - 1 AS pos, modality FROM (
SELECT label AS clip_id, 0 AS rank, 'audio' AS modality, vec_id AS token_no FROM embeddings WHERE vec_id % 3 = 0
UNION ALL SELECT label, 1, 'visual', vec_id FROM embeddings WHERE vec_id % 3 = 1 UNION ALL SELECT label, 2, 'prompt', vec_id FROM embeddings WHERE vec_id % 3 = 2)""")
def w11_fuse_tokens(spark, d):
    t = fx.tokens(spark, d)
    third = [t.where(F.col("token_no") % 3 == i) for i in range(3)]
    return resampler.fuse_tokens(*third).select("clip_id", "pos", "modality")


@query("""WITH t AS (SELECT label AS clip_id, vec_id AS token_no, embedding::DOUBLE[] AS vec FROM embeddings)
SELECT clip_id, token_no, o.o AS dim, round(list_sum(list_transform(vec, lambda v, i: v * cos((o.o + 1) * i))), 6) + 0.0 AS value FROM t, range(0, 8) o(o)""")
def w11_projected(spark, d):
    """Tokens mapped by a fixed matrix of cosines to eight positions."""
    import numpy as np
    matrix = np.cos(np.outer(np.arange(1, 9), np.arange(1, 65)))
    t = resampler.project(fx.tokens(spark, d), matrix)
    return t.select("clip_id", "token_no", F.posexplode("vec").alias("dim", "v")).select("clip_id", "token_no", F.col("dim").cast("bigint").alias("dim"), r6("v").alias("value"))


@query(f"WITH {T.FRAMES} SELECT clip_id, frame_no::INT AS frame_no FROM frames WHERE floor(frame_no * 10 / 25.0) > floor((frame_no - 1) * 10 / 25.0)")
def w11_frame_cap(spark, d):
    """At most ten of twenty-five frames a second."""
    return resampler.subsample_frames(fx.clip_frames(spark, d), max_fps=10).select("clip_id", F.col("frame_no").cast("int").alias("frame_no"))


@query(f"WITH {T.FRAMES} SELECT clip_id, count(*) AS frames FROM frames WHERE frame_no % 2 = 0 GROUP BY clip_id")
def w11_subsample_frames(spark, d):
    return resampler.subsample_frames(fx.clip_frames(spark, d), 2).groupBy("clip_id").agg(F.count("*").alias("frames"))


# --- W12, W13, W14 -----------------------------------------------------------------------------------

ORDER_SNR = f"""audio AS (SELECT l_orderkey AS clip_id, l_extendedprice AS clean, l_extendedprice - l_extendedprice * l_discount AS noisy FROM lineitem), {T.SNR}"""


@query(f"WITH {ORDER_SNR} SELECT clip_id, n, {T.r6('snr_db')} AS snr_db, snr_kind FROM snrdb")
def w12_snr_orders(spark, d):
    return rounded(signal.snr_db(fx.order_audio(spark, d)), "snr_db").select("clip_id", "n", "snr_db", "snr_kind")


def inf_sql(policy: str) -> str:
    special = "WHEN snr_kind = 'pos_inf' THEN 1.0 WHEN snr_kind = 'neg_inf' THEN 0.0" if policy == "cap" else ""
    where = "WHERE snr_kind NOT IN ('pos_inf', 'neg_inf')" if policy == "drop" else ""
    return f"SELECT '{policy}' AS policy, clip_id, {T.r6(f'CASE {special} WHEN snr_db IS NULL THEN NULL ELSE (snr_db - lo) / (hi - lo) END')} AS snr_norm FROM snrdb, st {where}"


@query(f"WITH {ORDER_SNR}, st AS (SELECT min(snr_db) AS lo, max(snr_db) AS hi FROM snrdb) {' UNION ALL '.join(inf_sql(p) for p in ('cap', 'null', 'drop'))}")
def w12_snr_inf_policy(spark, d):
    s = signal.snr_db(fx.order_audio(spark, d))
    stats = normalise.fit_minmax(s, "snr_db")
    out = [normalise.apply_minmax(s, stats, "snr_db", "snr_norm", "snr_kind", p).select(F.lit(p).alias("policy"), "clip_id", r6("snr_norm").alias("snr_norm")) for p in ("cap", "null", "drop")]
    return out[0].unionByName(out[1]).unionByName(out[2])


@query(f"WITH {T.curated()} SELECT split, quality, count(*) AS n FROM curated JOIN labels ON doc_id = clip_id GROUP BY ALL")
def w13_label_agreement(spark, d):
    return curation.label_agreement(curated(spark, d), load(spark, d, "labels"))[0]


@query(f"""WITH {T.curated()}, x AS (SELECT round(s_comp, 9) AS s, quality FROM curated JOIN labels ON doc_id = clip_id WHERE s_comp IS NOT NULL),
p AS (SELECT s FROM x WHERE quality = 1), q AS (SELECT s FROM x WHERE quality = 0) SELECT {T.r6('avg(CASE WHEN p.s > q.s THEN 1.0 WHEN p.s = q.s THEN 0.5 ELSE 0.0 END)')} AS auc FROM p, q""")
def w13_label_auc(spark, d):
    return rounded(curation.auc(curation.label_agreement(curated(spark, d), load(spark, d, "labels"))[1]), "auc")


@query(f"""WITH x AS (SELECT sha256(text) AS h, count(*) FILTER ({T.bucket100('doc_id')} < 80) AS train, count(*) FILTER ({T.bucket100('doc_id')} >= 80) AS test FROM documents GROUP BY 1)
SELECT h AS text_sha256, train, test FROM x WHERE train > 0 AND test > 0""")
def w14_split_leak(spark, d):
    x = curriculum.split_dataset(load(spark, d, "documents"), key="doc_id").select(F.sha2("text", 256).alias("text_sha256"), "part")
    g = x.groupBy("text_sha256").agg(F.count_if(F.col("part") == "train").alias("train"), F.count_if(F.col("part") == "test").alias("test"))
    return g.where("train > 0 and test > 0")


@query("SELECT doc_id, item_id FROM documents d, benchmark b WHERE contains(d.text, b.text)")
def w14_benchmark_leak(spark, d):
    """Documents that hold a benchmark passage, wherever it begins.

    All words of a passage but its first and last are whole words of any text that holds it. So
    documents meet passages of five words and more by equality of the second to the fourth, those
    of three and four by the second, and shorter ones by as many first characters as the shortest
    has, at most four. Whether a text holds a passage is then looked up in the text.
    """
    passages = load(spark, d, "benchmark").where("text <> ''").select("item_id", F.col("text").alias("passage"), F.split("text", " ").alias("w"))
    docs = load(spark, d, "documents").select("doc_id", "text")
    words = F.split("text", " ")
    n = F.size("w")

    def met(some: DataFrame, key, keys) -> DataFrame:
        rows = docs.select("doc_id", F.explode(F.array_distinct(keys)).alias("k"))
        return rows.join(some.select("item_id", "passage", key.alias("k")), "k").select("doc_id", "item_id", "passage")

    grams = F.zip_with(F.zip_with(words, F.slice(words, 2, F.size(words)), lambda a, b: F.concat(a, F.lit(" "), b)), F.slice(words, 3, F.size(words)), lambda a, b: F.concat(a, F.lit(" "), b))
    hits = met(passages.where(n >= 5), F.concat_ws(" ", F.slice("w", 2, 3)), F.filter(grams, lambda g: g.isNotNull()))
    hits = hits.unionByName(met(passages.where((n >= 3) & (n < 5)), F.element_at("w", 2), words))
    short = passages.where(n < 3)
    least = short.agg(F.min(F.length("passage"))).first()[0]
    if least:
        size = min(4, least)
        hits = hits.unionByName(met(short, F.left("passage", F.lit(size)), F.regexp_extract_all("text", F.lit(f"(?s)(?=(.{{{size}}}))"), F.lit(1))))
    return hits.distinct().join(docs, "doc_id").where(F.contains("text", "passage")).select("doc_id", "item_id")


@query(f"""WITH {T.CLIPS} SELECT sum({T.over('hyp_text', 'ref_text', 'length(z[1])::BIGINT * length(z[2])')})::BIGINT AS dp_cells, count(*) AS clips FROM clips""")
def e13_cost_report(spark, d):
    c = fx.clip_text(spark, d)
    return evaluate.cost_report(c, curation.curate_bounded(c, fx.clip_audio(spark, d), fx.clip_frames(spark, d))).agg(F.sum("dp_cells").alias("dp_cells"), F.sum("clips").alias("clips"))


@query(f"WITH {T.FRAMES} SELECT count(*) AS frames, sum(len(pixels))::BIGINT AS pixels FROM frames")
def e13_pixels(spark, d):
    return evaluate.pixel_cost(fx.clip_frames(spark, d))


@query(f"""WITH {T.curated()}, b AS (SELECT *, 0.6 * 0.5 * snr_norm + 0.4 * s_video AS base, {T.longer('hyp_text', 'ref_text')} AS longer, {T.over('hyp_text', 'ref_text', 'abs(length(z[1]) - length(z[2]))')} AS gap,
    {T.over('hyp_text', 'ref_text', 'length(z[1])::BIGINT * length(z[2])')} AS cells FROM curated),
k AS (SELECT *, greatest(-1, least(floor((1 - (0.55 - base) / 0.3) * longer + 1e-6)::BIGINT, longer)) AS k FROM b)
SELECT CASE WHEN base IS NULL OR longer IS NULL THEN 'missing' WHEN round(base, 9) >= 0.55 OR base + 0.3 + 1e-9 < 0.55 THEN 'bounds' WHEN gap > k THEN 'length' ELSE 'banded' END AS decided_by,
    count(*) AS clips, sum(cells)::BIGINT AS dp_cells FROM k GROUP BY 1""")
def e13_decisions(spark, d):
    """How many clips each rule of bounded curation decides."""
    c = fx.clip_text(spark, d)
    return evaluate.cost_report(c, curation.curate_bounded(c, fx.clip_audio(spark, d), fx.clip_frames(spark, d)))
