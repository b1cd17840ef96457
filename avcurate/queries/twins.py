"""Pieces of the DuckDB twins: the fixtures as common table expressions, and measures."""

from __future__ import annotations

#: The corpus' letters beyond ASCII, mapped to control characters before a distance of bytes is taken.
LETTERS = "éóèñüçêäößíÉÈÑÓÇÄÜÊÖÍ"
STAND_INS = "||".join(f"chr({i})" for i in [*range(1, 9), *range(14, 27)])


def pieces(text: str) -> str:
    """The utterances of a whole text, as a list."""
    return f"(CASE WHEN length({text}) = 0 THEN [''] ELSE regexp_extract_all({text}, '(?s).{{1,160}}') END)"


def over(a: str, b: str, f: str) -> str:
    """Sum of f over the utterances z[1], z[2] that answer each other."""
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda z: {f}))::BIGINT"


def lev(a: str, b: str) -> str:
    return over(a, b, f"levenshtein(translate(z[1], '{LETTERS}', {STAND_INS}), translate(z[2], '{LETTERS}', {STAND_INS}))")


def longer(a: str, b: str) -> str:
    return over(a, b, "greatest(length(z[1]), length(z[2]))")


def chars(x: str) -> str:
    return f"list_sum(list_transform({x}, lambda p: length(p)))::BIGINT"


def asr(h: str, r: str) -> str:
    return f"CASE WHEN {longer(h, r)} = 0 THEN 1.0 ELSE 1.0 - {lev(h, r)}::DOUBLE / {longer(h, r)} END"


def r6(x: str) -> str:
    return f"round(({x})::DOUBLE, 6) + 0.0"


def mean9(x: str) -> str:
    """Mean of values of nine places, summed as decimals."""
    return r6(f"sum(round({x}, 9)::DECIMAL(28,9))::DOUBLE / count({x})")


def bucket100(x: str) -> str:
    return f"(('0x' || substr(md5({x}::VARCHAR), 1, 8))::BIGINT % 100)"


CLIPS = f"""clips AS (
    SELECT clip_id, speaker, category, ref_text, list_transform(ref_text, lambda r: CASE clip_id % 5 WHEN 0 THEN r WHEN 1 THEN regexp_replace(r, '[aeiou]', '', 'g')
            WHEN 2 THEN left(r, floor(0.6 * length(r))::INT) WHEN 3 THEN replace(r, 'th', 't') ELSE reverse(r) END) AS hyp_text
    FROM (SELECT doc_id AS clip_id, source AS speaker, lang AS category, {pieces("text")} AS ref_text FROM documents))"""
AUDIO = """audio AS (
    SELECT event_id // 10 AS clip_id, value AS clean, value + ((props->>'$.k')::INT / 10.0::DOUBLE - 4.95::DOUBLE) AS noisy FROM events)"""
SNR = """snr AS (
    SELECT clip_id, count(*) AS n, sum(clean * clean) AS signal, sum((clean - noisy) * (clean - noisy)) AS residual FROM audio GROUP BY clip_id),
snrdb AS (
    SELECT *, CASE WHEN signal > 0 AND residual > 0 THEN 10 * log10(signal / residual) END AS snr_db,
        CASE WHEN residual = 0 AND signal = 0 THEN 'none' WHEN residual = 0 THEN 'pos_inf' WHEN signal = 0 THEN 'neg_inf' ELSE 'finite' END AS snr_kind
    FROM snr)"""
FRAMES = """frames AS (
    SELECT d.doc_id AS clip_id, j.j AS frame_no, e.embedding::DOUBLE[] AS pixels
    FROM documents d, range(0, 6) j(j), embeddings e
    WHERE e.vec_id = (d.doc_id + (j.j * (d.doc_id % 6)) // 5) % (SELECT count(*) FROM embeddings))"""


def motion(diff: str = "abs(x[2] - x[1])", wrap: str = "{}") -> str:
    inner = wrap.format(f"list_avg(list_transform(list_zip(before, pixels), lambda x: {diff}))")
    return f"""pairs AS (SELECT clip_id, pixels, lag(pixels) OVER (PARTITION BY clip_id ORDER BY frame_no) AS before FROM frames),
motion AS (SELECT clip_id, count(before) AS pairs, avg(CASE WHEN before IS NOT NULL THEN {inner} END) AS motion FROM pairs GROUP BY clip_id)"""


SIGNALS = f"""{CLIPS}, {AUDIO}, {SNR}, {FRAMES}, {motion()},
signals AS (
    SELECT c.clip_id, c.speaker, c.category, c.ref_text, c.hyp_text, {asr("c.hyp_text", "c.ref_text")} AS s_asr, s.snr_db, coalesce(s.snr_kind, 'none') AS snr_kind, m.motion
    FROM clips c LEFT JOIN snrdb s USING (clip_id) LEFT JOIN motion m USING (clip_id))"""


def curated(fit: str = "signals", comp: str = "0.6 * s_audio + 0.4 * s_video", snr_by: str | None = None) -> str:
    """CTEs up to ``curated``."""
    stats = f"""stats AS (SELECT min(snr_db) AS lo, max(snr_db) AS hi, quantile_cont(motion, 0.9) AS cap FROM {fit})"""
    lo, hi, more = ("lo", "hi", "")
    if snr_by:
        more = f", spk AS (SELECT {snr_by}, min(snr_db) AS slo, max(snr_db) AS shi FROM signals GROUP BY {snr_by})"
        lo, hi = "slo", "shi"
    source = f"signals, stats{f' , spk' if snr_by else ''}" if not snr_by else f"signals JOIN spk USING ({snr_by}), stats"
    return f"""{SIGNALS}, {stats}{more},
normed AS (
    SELECT *, CASE WHEN snr_kind = 'pos_inf' THEN 1.0 WHEN snr_kind = 'neg_inf' THEN 0.0 WHEN snr_db IS NULL THEN NULL
        WHEN {hi} = {lo} THEN 0.0 ELSE greatest(0.0, least(1.0, (snr_db - {lo}) / ({hi} - {lo}))) END AS snr_norm,
        CASE WHEN motion IS NULL OR cap IS NULL THEN NULL WHEN cap = 0 THEN 0.0 ELSE least(motion / cap, 1.0) END AS s_video
    FROM {source}),
audios AS (SELECT *, 0.5 * s_asr + 0.5 * snr_norm AS s_audio FROM normed),
comps AS (SELECT *, {comp} AS s_comp FROM audios),
curated AS (
    SELECT *, CASE WHEN round(s_comp, 9) >= 0.55 THEN 'accept' ELSE 'reject' END AS split,
        CASE WHEN s_comp IS NULL THEN 'missing_modality' WHEN round(s_comp, 9) >= 0.55 THEN 'score' ELSE 'low_score' END AS reason
    FROM comps)"""


LANDMARKS = """lm AS (
    SELECT label AS clip_id, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS frame_no, vec_id % 7 <> 3 AS valid, embedding::DOUBLE[] AS e FROM embeddings),
pts AS (
    SELECT clip_id, frame_no, i.i AS idx, 256 + 512 * e[2 * i.i + 1] AS x, 256 + 512 * e[2 * i.i + 2] AS y FROM lm, range(20, 32) i(i) WHERE valid),
boxes AS (
    SELECT clip_id, frame_no, min(x) AS x0, min(y) AS y0, max(x) AS x1, max(y) AS y1, max(x) - min(x) AS w, max(y) - min(y) AS h FROM pts GROUP BY ALL),
sizes AS (
    SELECT clip_id, avg(w) AS mean_w, avg(h) AS mean_h, (2 * ceil(round(1.2 * greatest(avg(w), avg(h)), 9) / 2))::BIGINT AS crop FROM boxes GROUP BY clip_id),
cents AS (
    SELECT l.clip_id, l.frame_no, p.cx, p.cy FROM lm l LEFT JOIN (SELECT clip_id, frame_no, avg(x) AS cx, avg(y) AS cy FROM pts GROUP BY ALL) p USING (clip_id, frame_no)),
near AS (
    SELECT c.clip_id, c.frame_no, c.cx, c.cy,
        (SELECT max(b.frame_no) FROM cents b WHERE b.clip_id = c.clip_id AND b.cx IS NOT NULL AND b.frame_no <= c.frame_no) AS bf,
        (SELECT min(a.frame_no) FROM cents a WHERE a.clip_id = c.clip_id AND a.cx IS NOT NULL AND a.frame_no >= c.frame_no) AS af
    FROM cents c),
interp AS (
    SELECT n.clip_id, n.frame_no, n.cx IS NULL AS filled,
        CASE WHEN n.cx IS NOT NULL THEN n.cx WHEN b.cx IS NOT NULL AND a.cx IS NOT NULL THEN b.cx + (a.cx - b.cx) * (n.frame_no - bf) / (af - bf) ELSE coalesce(b.cx, a.cx) END AS cx,
        CASE WHEN n.cy IS NOT NULL THEN n.cy WHEN b.cy IS NOT NULL AND a.cy IS NOT NULL THEN b.cy + (a.cy - b.cy) * (n.frame_no - bf) / (af - bf) ELSE coalesce(b.cy, a.cy) END AS cy
    FROM near n LEFT JOIN cents b ON b.clip_id = n.clip_id AND b.frame_no = n.bf LEFT JOIN cents a ON a.clip_id = n.clip_id AND a.frame_no = n.af),
windows AS (
    SELECT clip_id, frame_no, crop, cx - crop / 2.0::DOUBLE AS x0, cy - crop / 2.0::DOUBLE AS y0, cx - crop / 2.0::DOUBLE + crop AS x1, cy - crop / 2.0::DOUBLE + crop AS y1
    FROM interp JOIN sizes USING (clip_id))"""

VEC26 = "[" + ", ".join(f"(length({{t}}) - length(replace({{t}}, '{c}', '')))::DOUBLE" for c in "abcdefghijklmnopqrstuvwxyz") + "]"
SYSTEMS = {
    "sys01": "lower(r)", "sys02": "regexp_replace(r, '[aeiou]', '', 'g')", "sys03": "left(r, floor(0.6 * length(r))::INT)", "sys04": "replace(r, 'th', 't')",
    "sys05": "translate(r, 'ea', 'ae')", "sys06": "reverse(r)", "sys07": "r || r || r", "sys08": "replace(r, ' ', '')", "sys09": "replace(r, 'n', '')",
    "sys10": "replace(regexp_replace(r, '[.,]', '', 'g'), 'o', 'u')", "sys11": "substr(r, 9)", "sys12": "left(r, length(r) - 1)", "sys13": "regexp_replace(substr(r, 9), '[ie]', '', 'g')",
}
PAIRS = f"refs AS (SELECT doc_id AS pair_id, {pieces('text')} AS ref FROM documents), pairs_ AS (" + " UNION ALL ".join(f"SELECT '{s}' AS system_id, pair_id, ref, list_transform(ref, lambda r: {e}) AS hyp FROM refs" for s, e in SYSTEMS.items()) + ")"
MEASURED = f"""{PAIRS},
lows AS (SELECT *, lower(array_to_string(hyp, '')) AS lh, lower(array_to_string(ref, '')) AS lr FROM pairs_),
vecs AS (SELECT *, {VEC26.format(t="lh")} AS vh, {VEC26.format(t="lr")} AS vr, {lev("hyp", "ref")} AS dist, {chars("hyp")} AS hyp_len, {chars("ref")} AS ref_len FROM lows),
meas AS (
    SELECT system_id, pair_id, ref, hyp, dist, hyp_len, ref_len,
        CASE WHEN hyp_len = 0 AND ref_len = 0 THEN 0.0 WHEN ref_len > 0 THEN dist::DOUBLE / ref_len END AS cer,
        CASE WHEN list_inner_product(vh, vh) > 0 AND list_inner_product(vr, vr) > 0 THEN list_inner_product(vh, vr) / (sqrt(list_inner_product(vh, vh)) * sqrt(list_inner_product(vr, vr))) END AS sim
    FROM vecs)"""
BOARD = f"{MEASURED}, board0 AS (SELECT system_id, count(*) AS n, avg(sim) AS emb_sim, avg(cer) AS cer, sum(dist)::DOUBLE / sum(ref_len) AS cer_micro FROM meas GROUP BY system_id), board AS (SELECT *, 0.5 * (1 - cer) + 0.5 * emb_sim AS cs FROM board0)"


def golden_cte(rows) -> str:
    v = lambda x: "NULL" if x is None else str(x).lower() if isinstance(x, bool) else f"'{x}'"
    body = ", ".join("(" + ", ".join(v(x) for x in r) + ")" for r in rows)
    return f"""gold AS (
    SELECT a AS system_id, b AS family, c::DECIMAL(4,1) AS params_b, d::BOOLEAN AS has_audio, e::BOOLEAN AS has_video, f::DECIMAL(5,3) AS emb_sim, g::DECIMAL(5,3) AS cer, h::DECIMAL(5,3) AS cs
    FROM (VALUES {body}) t(a, b, c, d, e, f, g, h))"""


def softmax_resample(gain: float = 1.0, n_queries: int = 64) -> str:
    return f"""tok AS (SELECT label AS clip_id, vec_id AS token_no, embedding::DOUBLE[] AS vec FROM embeddings),
qry AS (SELECT vec_id AS query_no, list_transform(embedding::DOUBLE[], lambda x: x * {gain}) AS q FROM embeddings WHERE vec_id < {n_queries}),
logits AS (SELECT clip_id, query_no, token_no, vec, list_inner_product(q, vec) / sqrt(64) AS l FROM tok, qry),
es AS (SELECT *, exp(l - max(l) OVER (PARTITION BY clip_id, query_no)) AS e FROM logits),
wts AS (SELECT *, e / sum(e) OVER (PARTITION BY clip_id, query_no) AS a FROM es),
outs AS (SELECT clip_id, query_no, i.i AS dim, sum(a * vec[i.i + 1]) AS value FROM wts, range(0, 64) i(i) GROUP BY ALL)"""
