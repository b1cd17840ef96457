"""Relational operators, functions and user-defined surfaces on the given tables."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from avcurate.functions import sql as sqlf
from avcurate.functions import udfs
from avcurate.functions.text import letter_vector, strip_html
from avcurate.functions.vectors import cosine
from avcurate.operators import baselines, lips, signal
from avcurate.operators.relational import asof_join, interval_join, sessions
from avcurate.queries import twins as T
from avcurate.queries.registry import query, r6, rounded
from avcurate.queries.workloads import GOLD, LINES, LANDMARKS_SQL, curated, lip_frames
from avcurate.sources import fixtures as fx
from avcurate.sources.tables import load, with_k


def seconds(col: str = "ts"):
    return (F.unix_micros(F.col(col).cast("timestamp")) / 1e6).cast("double")


SEC = "(epoch_us(ts) / 1000000.0::DOUBLE)"


@query("SELECT lang, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents GROUP BY lang")
def o_scan_prune(spark, d):
    return load(spark, d, "documents").groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("""SELECT event_id, event_type, value FROM events WHERE event_type IN ('click', 'error') AND value BETWEEN 20 AND 80 AND regexp_matches(props, '"k": 7[0-9]?[^0-9]') AND event_type IS NOT DISTINCT FROM 'click' AND props LIKE '{%' AND NOT (user_id IS NULL)""")
def o_filters(spark, d):
    e = load(spark, d, "events")
    return e.where(F.col("event_type").isin("click", "error") & F.col("value").between(20, 80) & F.col("props").rlike('"k": 7[0-9]?[^0-9]') & F.col("event_type").eqNullSafe("click") & F.col("props").like("{%") & ~F.col("user_id").isNull()).select("event_id", "event_type", "value")


@query("SELECT n_name, r_name, count(*) AS suppliers FROM nation JOIN region ON n_regionkey = r_regionkey JOIN supplier ON s_nationkey = n_nationkey GROUP BY ALL")
def o_broadcast_join(spark, d):
    n, r, s = (load(spark, d, t) for t in ("nation", "region", "supplier"))
    small = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)  # 25 and 5 rows at any scale
    return s.join(F.broadcast(small), s.s_nationkey == small.n_nationkey).groupBy("n_name", "r_name").agg(F.count("*").alias("suppliers"))


JOIN_SQL = "SELECT o_orderstatus, count(*) AS n, round(sum(l_quantity), 2) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY 1"


def _hinted(spark, d, hint):
    li, o = load(spark, d, "lineitem"), load(spark, d, "orders")
    return li.join(o.hint(hint), li.l_orderkey == o.o_orderkey).groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query(JOIN_SQL)
def o_sortmerge_join(spark, d):
    return _hinted(spark, d, "merge")


@query(JOIN_SQL)
def o_shufflehash_join(spark, d):
    return _hinted(spark, d, "shuffle_hash")


@query(f"WITH {GOLD} SELECT a.system_id AS worse, b.system_id AS better FROM gold a JOIN gold b ON b.cer <= a.cer AND b.emb_sim >= a.emb_sim AND (b.cer < a.cer OR b.emb_sim > a.emb_sim)")
def o_theta_join(spark, d):
    g = fx.golden(spark).select("system_id", "cer", "emb_sim")
    a, b = g.select(F.col("system_id").alias("worse"), F.col("cer").alias("c1"), F.col("emb_sim").alias("s1")), g.select(F.col("system_id").alias("better"), F.col("cer").alias("c2"), F.col("emb_sim").alias("s2"))
    return a.join(F.broadcast(b), F.expr("c2 <= c1 AND s2 >= s1 AND (c2 < c1 OR s2 > s1)")).select("worse", "better")  # 13 rows


def clicks_errors(spark, d):
    e = load(spark, d, "events").withColumn("t", seconds())
    return (e.where(f"event_type = '{k}'").select(F.col("event_id").alias(f"{k}_id"), "user_id", F.col("t").alias(f"{k}_t")) for k in ("click", "error"))


INTERVAL_SQL = f"""WITH c AS (SELECT event_id AS click_id, user_id, {SEC} AS ct FROM events WHERE event_type = 'click'), e AS (SELECT event_id AS error_id, user_id, {SEC} AS et FROM events WHERE event_type = 'error')
SELECT click_id, error_id, user_id FROM c JOIN e USING (user_id) WHERE et - ct BETWEEN 0 AND {{gap}}"""


@query(INTERVAL_SQL.format(gap=3600))
def o_interval_join(spark, d):
    c, e = clicks_errors(spark, d)
    return interval_join(c, e, "user_id", "click_t", "error_t", 3600).select("click_id", "error_id", "user_id")


@query(f"""WITH p AS (SELECT event_id, user_id, {SEC} AS t FROM events WHERE event_type = 'purchase'), c AS (SELECT event_id AS click_id, user_id, {SEC} AS t FROM events WHERE event_type = 'click')
SELECT p.event_id, p.user_id, c.click_id AS last_click_id FROM p ASOF LEFT JOIN c ON p.user_id = c.user_id AND p.t >= c.t""")
def o_asof_join(spark, d):
    e = load(spark, d, "events").withColumn("t", seconds())
    p = e.where("event_type = 'purchase'").select("event_id", "user_id", "t")
    c = e.where("event_type = 'click'").select("user_id", "t", F.col("event_id").alias("click_id"))
    return asof_join(p, c, "user_id", "t", "click_id").select("event_id", "user_id", "last_click_id")


@query("SELECT coalesce(d.doc_id, l.doc_id + 7) AS doc_id, l.quality, d.lang FROM documents d FULL JOIN (SELECT doc_id + 7 AS id2, * FROM labels) l ON d.doc_id = l.id2")
def o_outer_joins(spark, d):
    lab = load(spark, d, "labels").select((F.col("doc_id") + 7).alias("id2"), "quality")
    docs = load(spark, d, "documents").select("doc_id", "lang")
    return docs.join(lab, docs.doc_id == lab.id2, "full").select(F.coalesce("doc_id", "id2").alias("doc_id"), "quality", "lang")


@query("SELECT doc_id, lang FROM documents d LEFT JOIN labels l USING (doc_id) WHERE l.quality IS NULL OR l.quality = 0")
def o_left_join(spark, d):
    return load(spark, d, "documents").select("doc_id", "lang").join(load(spark, d, "labels"), "doc_id", "left").where("quality is null or quality = 0").select("doc_id", "lang")


@query("SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def o_semi(spark, d):
    return load(spark, d, "documents").select("doc_id").join(load(spark, d, "labels"), "doc_id", "left_semi")


@query("SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def o_anti(spark, d):
    return load(spark, d, "documents").select("doc_id").join(load(spark, d, "labels"), "doc_id", "left_anti")


@query("SELECT a.conv_id, a.turn, a.role AS role, b.role AS next_role FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1")
def o_self_join(spark, d):
    c = load(spark, d, "conversations").select("conv_id", "turn", "role")
    return c.join(c.select("conv_id", (F.col("turn") - 1).alias("turn"), F.col("role").alias("next_role")), ["conv_id", "turn"])


@query(f"SELECT vec_id, i.i::INT AS idx, {T.r6('256 + 512 * embedding[2 * i.i + 1]::DOUBLE')} AS x, {T.r6('256 + 512 * embedding[2 * i.i + 2]::DOUBLE')} AS y FROM embeddings, range(0, 32) i(i)")
def o_lateral_points(spark, d):
    return rounded(load(spark, d, "embeddings").select("vec_id", F.inline(lips.unpack_points(F.col("embedding")))), "x", "y")


@query(f"""WITH audio AS (SELECT l_orderkey AS clip_id, l_extendedprice AS clean, l_extendedprice - l_extendedprice * l_discount AS noisy FROM lineitem), {T.SNR}, m AS (SELECT quantile_cont(snr_db, 0.5) AS med FROM snrdb)
SELECT r_name, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM snrdb, m, lineitem, orders, customer, nation, region
WHERE snr_db > med AND l_orderkey = clip_id AND o_orderkey = l_orderkey AND c_custkey = o_custkey AND n_nationkey = c_nationkey AND r_regionkey = n_regionkey GROUP BY r_name""")
def o_star(spark, d):
    s = signal.snr_db(fx.order_audio(spark, d)).select("clip_id", "snr_db")
    loud = s.crossJoin(F.broadcast(s.agg(F.percentile("snr_db", 0.5).alias("med")))).where("snr_db > med").select(F.col("clip_id").alias("l_orderkey"))
    o, c, n, r = (load(spark, d, t) for t in ("orders", "customer", "nation", "region"))
    x = load(spark, d, "lineitem").join(loud, "l_orderkey", "left_semi")
    x = x.join(o, x.l_orderkey == o.o_orderkey).join(c, F.col("o_custkey") == c.c_custkey).join(n, F.col("c_nationkey") == n.n_nationkey).join(r, F.col("n_regionkey") == r.r_regionkey)
    return x.groupBy("r_name").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


K = "(props->>'$.k')::INT"


@query(f"SELECT event_type, count(*) AS n, {T.r6('sum(value)')} AS total, {T.r6('avg(value)')} AS mean, {T.r6('min(value)')} AS low, {T.r6('max(value)')} AS high, {T.r6('stddev_samp(value)')} AS sd, {T.r6('var_pop(value)')} AS var, {T.r6(f'corr(value, {K})')} AS corr, {T.r6(f'covar_pop(value, {K})')} AS cov FROM events GROUP BY 1")
def o_agg_basic(spark, d):
    g = with_k(load(spark, d, "events")).groupBy("event_type").agg(
        F.count("*").alias("n"), F.sum("value").alias("total"), F.avg("value").alias("mean"), F.min("value").alias("low"), F.max("value").alias("high"),
        F.stddev_samp("value").alias("sd"), F.var_pop("value").alias("var"), F.corr("value", "k").alias("corr"), F.covar_pop("value", "k").alias("cov"))
    return rounded(g, "total", "mean", "low", "high", "sd", "var", "corr", "cov")


@query("SELECT conv_id, string_agg(role || ': ' || text, ' | ' ORDER BY turn) AS talk FROM conversations GROUP BY conv_id")
def o_agg_ordered_list(spark, d):
    turn = F.struct("turn", F.concat_ws(": ", "role", "text").alias("s"))
    return load(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(F.sort_array(F.collect_list(turn)), lambda x: x["s"]), " | ").alias("talk"))


@query("SELECT (SELECT count(DISTINCT text) FROM documents) AS texts, (SELECT count(DISTINCT user_id) FROM events) AS users, (SELECT count(*) FROM (SELECT DISTINCT event_type, user_id FROM events)) AS pairs")
def o_distinct(spark, d):
    e = load(spark, d, "events")
    a = load(spark, d, "documents").agg(F.countDistinct("text").alias("texts"))
    return a.crossJoin(e.agg(F.countDistinct("user_id").alias("users"))).crossJoin(e.select("event_type", "user_id").distinct().agg(F.count("*").alias("pairs")))


@query()
def o_distinct_approx(spark, d):
    return load(spark, d, "documents").agg(F.approx_count_distinct("text", 0.02).alias("texts"))


@query(f"WITH {T.curated()} SELECT speaker, count(*) FILTER (split = 'accept') AS accepted, count(*) FILTER (split = 'reject') AS rejected, count(*) FILTER (motion = 0) AS static FROM curated GROUP BY speaker")
def o_conditional(spark, d):
    return curated(spark, d).groupBy("speaker").agg(F.sum(F.when(F.col("split") == "accept", 1).otherwise(0)).alias("accepted"), F.count_if(F.col("split") == "reject").alias("rejected"), F.count_if(F.col("motion") == 0).alias("static"))


GROUPED = "SELECT source, lang, q, {g}::BIGINT AS level, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM (SELECT source, lang, n_chars > 1500 AS q, n_chars FROM documents) GROUP BY {by}"


def _grouped(spark, d):
    return load(spark, d, "documents").select("source", "lang", (F.col("n_chars") > 1500).alias("q"), "n_chars")


def _agg(g):
    return g.agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query(GROUPED.format(g="(4 * grouping(source) + 2 * grouping(lang) + grouping(q))", by="ROLLUP (source, lang, q)"))
def o_rollup(spark, d):
    return _agg(_grouped(spark, d).rollup("source", "lang", "q"))


@query(GROUPED.format(g="(4 * grouping(source) + 2 * grouping(lang) + grouping(q))", by="CUBE (source, lang, q)"))
def o_cube(spark, d):
    return _agg(_grouped(spark, d).cube("source", "lang", "q"))


@query(GROUPED.format(g="(4 * grouping(source) + 2 * grouping(lang) + grouping(q))", by="GROUPING SETS ((source, lang), (lang, q), (q), ())"))
def o_grouping_sets(spark, d):
    return _agg(_grouped(spark, d).groupingSets([["source", "lang"], ["lang", "q"], ["q"], []], "source", "lang", "q"))


@query(f"WITH {LINES} SELECT family, " + ", ".join(f"max(CASE WHEN metric = '{m}' THEN v END) AS {m}" for m in ("cer", "cs", "emb_sim")) + f" FROM (SELECT family, metric, {T.r6('avg(v)')} AS v FROM (SELECT family, unnest(['cer', 'cs', 'emb_sim']) AS metric, unnest([cer, cs, emb_sim])::DOUBLE AS v FROM lines) GROUP BY ALL) GROUP BY family")
def o_pivot(spark, d):
    long = fx.line_board(spark, d).select("family", *[F.col(c).cast("double").alias(c) for c in ("cer", "cs", "emb_sim")]).unpivot("family", ["cer", "cs", "emb_sim"], "metric", "v")
    return rounded(long.groupBy("family").pivot("metric", ["cer", "cs", "emb_sim"]).agg(F.avg("v")), "cer", "cs", "emb_sim")


@query(f"WITH {GOLD} SELECT system_id, unnest(['emb_sim', 'cer', 'cs']) AS metric, unnest([emb_sim, cer, cs])::DOUBLE AS value FROM gold")
def o_unpivot(spark, d):
    g = fx.golden(spark).select("system_id", *[F.col(c).cast("double").alias(c) for c in ("emb_sim", "cer", "cs")])
    return g.unpivot("system_id", ["emb_sim", "cer", "cs"], "metric", "value")


@query(f"SELECT event_type, arg_min(event_id, (value, event_id)) AS lowest, arg_max(event_id, (value, event_id)) AS highest, {T.r6('median(value)')} AS med, {T.r6('quantile_cont(value, 0.25)')} AS q25, {T.r6('quantile_cont(value, 0.9)')} AS q90, {T.r6('quantile_disc(value, 0.5)')} AS d50 FROM events GROUP BY 1")
def o_minby_quantiles(spark, d):
    at = F.struct("value", "event_id")
    g = load(spark, d, "events").groupBy("event_type").agg(
        F.min_by("event_id", at).alias("lowest"), F.max_by("event_id", at).alias("highest"), F.median("value").alias("med"),
        F.percentile("value", 0.25).alias("q25"), F.percentile("value", 0.9).alias("q90"), F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY value)").alias("d50"))
    return rounded(g, "med", "q25", "q90", "d50")


@query(f"""SELECT doc_id, row_number() OVER w::INT AS rn, rank() OVER v::INT AS rk, dense_rank() OVER v::INT AS dr, {T.r6('percent_rank() OVER v')} AS pr, {T.r6('cume_dist() OVER v')} AS cd, ntile(4) OVER w::INT AS nt
FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars, doc_id), v AS (PARTITION BY source ORDER BY n_chars // 100)""".replace("row_number() OVER w::INT", "(row_number() OVER w)::INT").replace("rank() OVER v::INT AS rk", "(rank() OVER v)::INT AS rk").replace("dense_(rank() OVER v)", "(dense_rank() OVER v)").replace("dense_rank() OVER v::INT", "(dense_rank() OVER v)::INT").replace("ntile(4) OVER w::INT", "(ntile(4) OVER w)::INT"))
def o_ranking(spark, d):
    w = Window.partitionBy("source").orderBy("n_chars", "doc_id")
    v = Window.partitionBy("source").orderBy(F.floor(F.col("n_chars") / 100))
    return load(spark, d, "documents").select("doc_id", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), r6(F.percent_rank().over(v)).alias("pr"), r6(F.cume_dist().over(v)).alias("cd"), F.ntile(4).over(w).alias("nt"))


@query("""SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after2, first_value(event_id) OVER w AS first, last_value(event_id) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last,
nth_value(event_id, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)""")
def o_offsets(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return load(spark, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after2"), F.first("event_id").over(w).alias("first"), F.last("event_id").over(full).alias("last"), F.nth_value("event_id", 2).over(full).alias("second"))


@query(f"""WITH e AS (SELECT *, {SEC} AS t FROM events) SELECT event_id, {T.r6('avg(value) OVER (PARTITION BY user_id ORDER BY t ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING)')} AS smooth,
{T.r6('sum(value) OVER (PARTITION BY user_id ORDER BY t ROWS UNBOUNDED PRECEDING)')} AS running, count(*) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS hour FROM e""")
def o_frames(spark, d):
    w = Window.partitionBy("user_id").orderBy("t")
    e = load(spark, d, "events").withColumn("t", seconds())
    return e.select("event_id", r6(F.avg("value").over(w.rowsBetween(-2, 2))).alias("smooth"), r6(F.sum("value").over(w.rowsBetween(Window.unboundedPreceding, 0))).alias("running"), F.count("*").over(w.rangeBetween(-3600, 0)).alias("hour"))


@query("SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10")
def o_topk(spark, d):
    return load(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(10)


@query("SELECT source, doc_id, rn::INT AS rn FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS rn FROM documents) WHERE rn <= 3")
def o_topk_group(spark, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return load(spark, d, "documents").select("source", "doc_id", F.row_number().over(w).alias("rn")).where("rn <= 3")


@query("SELECT doc_id, n_chars FROM documents ORDER BY n_chars, doc_id LIMIT 10 OFFSET 20")
def o_offset(spark, d):
    return load(spark, d, "documents").select("doc_id", "n_chars").orderBy("n_chars", "doc_id").offset(20).limit(10)


@query(f"""WITH l AS (SELECT doc_id FROM labels), t AS (SELECT doc_id FROM documents WHERE {T.bucket100('doc_id')} < 80), e AS (SELECT event_type FROM events), g AS (SELECT event_type FROM events WHERE value >= 50)
SELECT 'union' AS op, count(*) AS n FROM (SELECT * FROM l UNION SELECT * FROM t) UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM l INTERSECT SELECT * FROM t) UNION ALL SELECT 'except', count(*) FROM (SELECT * FROM l EXCEPT SELECT * FROM t)
UNION ALL SELECT 'union_all', count(*) FROM (SELECT * FROM e UNION ALL SELECT * FROM g) UNION ALL SELECT 'intersect_all', count(*) FROM (SELECT * FROM e INTERSECT ALL SELECT * FROM g) UNION ALL SELECT 'except_all', count(*) FROM (SELECT * FROM e EXCEPT ALL SELECT * FROM g)""")
def o_setops(spark, d):
    lab = load(spark, d, "labels").select("doc_id")
    t = load(spark, d, "documents").where(fx.bucket100(F.col("doc_id")) < 80).select("doc_id")
    ev = load(spark, d, "events")
    e, g = ev.select("event_type"), ev.where("value >= 50").select("event_type")
    ops = {"union": lab.union(t).distinct(), "intersect": lab.intersect(t), "except": lab.exceptAll(t).distinct(), "union_all": e.unionByName(g), "intersect_all": e.intersectAll(g), "except_all": e.exceptAll(g)}
    out = None
    for k, x in ops.items():
        row = x.agg(F.lit(k).alias("op"), F.count("*").alias("n"))
        out = row if out is None else out.unionByName(row)
    return out


@query(f"SELECT doc_id FROM documents WHERE {T.bucket100('doc_id')} < 30")
def o_sample_hash(spark, d):
    return load(spark, d, "documents").where(fx.bucket100(F.col("doc_id")) < 30).select("doc_id")


@query()
def o_sample_random(spark, d):
    """Bernoulli and stratified samples: a sampling operator's own feature."""
    docs = load(spark, d, "documents")
    a = docs.sample(fraction=0.3, seed=7).groupBy("lang").agg(F.count("*").alias("n")).withColumn("method", F.lit("bernoulli"))
    b = docs.sampleBy("lang", {"en": 0.1, "de": 0.5, "fr": 0.5, "es": 1.0}, seed=7).groupBy("lang").agg(F.count("*").alias("n")).withColumn("method", F.lit("stratified"))
    return a.unionByName(b)


SUBQUERY = """SELECT d.doc_id FROM documents d WHERE d.n_chars > (SELECT avg(n_chars) FROM documents) AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.quality = 1)
AND d.doc_id NOT IN (SELECT doc_id FROM labels WHERE toxic = 1) AND d.n_chars > (SELECT avg(x.n_chars) FROM documents x WHERE x.source = d.source)"""


def _views(spark, d, *names):
    for n in names:
        load(spark, d, n).createOrReplaceTempView(n)


@query(SUBQUERY)
def o_subqueries(spark, d):
    _views(spark, d, "documents", "labels")
    return spark.sql(SUBQUERY)


@query("WITH RECURSIVE e(epoch, phase) AS (SELECT 1, 1 UNION ALL SELECT epoch + 1, CASE WHEN epoch < 3 THEN 1 ELSE 2 END FROM e WHERE epoch < 8) SELECT epoch, phase FROM e")
def o_recursive(spark, d):
    return spark.sql("WITH RECURSIVE e(epoch, phase) AS (SELECT 1, 1 UNION ALL SELECT epoch + 1, CASE WHEN epoch < 3 THEN 1 ELSE 2 END FROM e WHERE epoch < 8) SELECT epoch, phase FROM e")


SESSIONS_SQL = f"""WITH e AS (SELECT user_id, {SEC} AS t FROM events), g AS (SELECT *, CASE WHEN t - lag(t) OVER (PARTITION BY user_id ORDER BY t) <= {{gap}} THEN 0 ELSE 1 END AS new FROM e),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY t) AS session FROM g)"""


@query(SESSIONS_SQL.format(gap=1800) + f" SELECT user_id, session::BIGINT AS session, count(*) AS n, {T.r6('max(t) - min(t)')} AS duration FROM s GROUP BY ALL")
def o_sessions(spark, d):
    s = sessions(load(spark, d, "events").withColumn("t", seconds()), "user_id", "t", 1800)
    return s.select("user_id", "session", "n", r6(F.col("last_t") - F.col("first_t")).alias("duration"))


@query("""SELECT doc_id, length(text) AS chars, strlen(text) AS bytes, upper(replace(left(text, 8), 'ß', 's')) AS up, right(text, 5) AS tail, replace(left(text, 20), 'e', 'E') AS rep, translate(left(text, 20), 'abc', 'xyz') AS tra, regexp_replace(left(text, 40), '[^a-z]+', '-', 'g') AS rx,
regexp_extract(text, '([A-Z])([a-z]+)', 2) AS word, len(string_split(text, ' ')) AS words, reverse(left(text, 6)) AS rev, lang || '/' || source AS cat, trim('  ' || lang || ' ') AS tr, lpad(lang, 4, '*') AS lp, md5(text) AS md, instr(text, 'the') AS pos, contains(text, 'and') AS has, starts_with(text, 'T') AS st FROM documents""")
def o_string(spark, d):
    t = F.col("text")
    cut = F.left(t, F.lit(20))
    return load(spark, d, "documents").select(
        "doc_id", F.length(t).cast("bigint").alias("chars"), F.octet_length(t).cast("bigint").alias("bytes"), F.upper(F.replace(F.left(t, F.lit(8)), F.lit("ß"), F.lit("s"))).alias("up"), F.right(t, F.lit(5)).alias("tail"), F.replace(cut, F.lit("e"), F.lit("E")).alias("rep"),
        F.translate(cut, "abc", "xyz").alias("tra"), F.regexp_replace(F.left(t, F.lit(40)), "[^a-z]+", "-").alias("rx"), F.regexp_extract(t, "([A-Z])([a-z]+)", 2).alias("word"), F.size(F.split(t, " ")).cast("bigint").alias("words"), F.reverse(F.left(t, F.lit(6))).alias("rev"),
        F.concat_ws("/", "lang", "source").alias("cat"), F.trim(F.concat(F.lit("  "), F.col("lang"), F.lit(" "))).alias("tr"), F.lpad("lang", 4, "*").alias("lp"), F.md5(t.cast("binary")).alias("md"), F.instr(t, F.lit("the")).cast("bigint").alias("pos"), F.contains(t, F.lit("and")).alias("has"), F.startswith(t, F.lit("T")).alias("st"))


@query(f"""SELECT event_id, {T.r6('sqrt(value)')} AS sq, {T.r6('power(value, 1.5)')} AS pw, {T.r6('exp(-value / 100)')} AS ex, {T.r6('ln(value)')} AS l, {T.r6('log10(value)')} AS lg, ceil(value)::BIGINT AS c, floor(value)::BIGINT AS f, {T.r6('abs(value - 50)')} AS ab, round((value * 100)::BIGINT::DECIMAL(18,0) / 1000, 1)::DOUBLE AS half,
{T.r6('greatest(value, 40)')} AS g, {T.r6('least(value, 40)')} AS le, ((event_id - 500) % 7 + 7) % 7 AS pm, CASE WHEN event_id % 5 = 0 THEN NULL ELSE {T.r6('value / (event_id % 5)')} END AS dv FROM events""".replace("round((value * 100)::BIGINT::DECIMAL(18,0) / 1000, 1)::DOUBLE AS half,", "round(floor(value)::DECIMAL(18,1) / 4, 1)::DOUBLE AS half,"))
def o_math(spark, d):
    """Logarithms of zero are minus infinity; Spark's own functions give null there."""
    v = F.col("value")
    m = F.col("event_id") % 5
    log = lambda f: F.when(v == 0, float("-inf")).otherwise(f(v))
    return load(spark, d, "events").select(
        "event_id", r6(F.sqrt(v)).alias("sq"), r6(F.pow(v, 1.5)).alias("pw"), r6(F.exp(-v / 100)).alias("ex"), r6(log(F.ln)).alias("l"), r6(log(F.log10)).alias("lg"), F.ceil(v).alias("c"), F.floor(v).alias("f"), r6(F.abs(v - 50)).alias("ab"),
        F.round(F.floor(v).cast("decimal(18,1)") / F.lit(4).cast("decimal(2,0)"), 1).cast("double").alias("half"), r6(F.greatest(v, F.lit(40.0))).alias("g"), r6(F.least(v, F.lit(40.0))).alias("le"), F.pmod(F.col("event_id") - 500, F.lit(7)).alias("pm"), r6(F.try_divide(v, m)).alias("dv"))


@query("""SELECT event_id, date_trunc('hour', ts) AS hr, hour(ts) AS h, (dayofweek(ts) + 1)::INT AS dow, datediff('day', TIMESTAMP '2024-01-01', date_trunc('day', ts))::INT AS days, epoch(ts)::BIGINT AS secs, ts + INTERVAL 90 MINUTE AS later, strftime(ts, '%Y-%m-%d') AS ymd FROM events""".replace("epoch(ts)::BIGINT", "floor(epoch(ts))::BIGINT").replace("hour(ts) AS h", "hour(ts)::INT AS h"))
def o_datetime(spark, d):
    ts = F.col("ts")
    return load(spark, d, "events").select(
        "event_id", F.date_trunc("hour", ts).cast("timestamp_ntz").alias("hr"), F.hour(ts).alias("h"), F.dayofweek(ts).alias("dow"), F.datediff(F.to_date(ts), F.lit("2024-01-01").cast("date")).alias("days"),
        F.floor(seconds()).cast("bigint").alias("secs"), (ts + F.expr("INTERVAL 90 MINUTE")).alias("later"), F.date_format(ts, "yyyy-MM-dd").alias("ymd"))


@query(f"""WITH e AS (SELECT vec_id, embedding::DOUBLE[] AS v FROM embeddings) SELECT vec_id, {T.r6('list_sum(list_transform(v, lambda x: x * x))')} AS sq, len(list_filter(v, lambda x: x > 0))::INT AS pos, {T.r6('list_max(v)')} AS hi, {T.r6('list_min(v)')} AS lo, list_bool_or(list_transform(v, lambda x: x > 0.35)) AS big,
list_bool_and(list_transform(v, lambda x: x < 1)) AS unit, {T.r6('v[3]')} AS third, {T.r6('list_sum(v[1:8])')} AS head, list_contains(range(0, vec_id % 9 + 1), 5) AS has5, coalesce(list_position(range(0, vec_id % 9 + 1), 5), 0)::BIGINT AS at5, {T.r6('list_sort(v)[32]')} AS mid FROM e""")
def o_array(spark, d):
    v = F.col("v")
    add = lambda a: F.aggregate(a, F.lit(0.0), lambda s, x: s + x)
    seq = F.sequence(F.lit(0).cast("bigint"), F.col("vec_id") % 9)
    five = F.lit(5).cast("bigint")
    return load(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v")).select(
        "vec_id", r6(add(F.zip_with(v, v, lambda x, y: x * y))).alias("sq"), F.size(F.filter(v, lambda x: x > 0)).alias("pos"), r6(F.array_max(v)).alias("hi"), r6(F.array_min(v)).alias("lo"), F.exists(v, lambda x: x > 0.35).alias("big"), F.forall(v, lambda x: x < 1).alias("unit"),
        r6(F.element_at(v, 3)).alias("third"), r6(add(F.slice(F.flatten(F.array(v, v)), 1, 8))).alias("head"), F.array_contains(seq, five).alias("has5"), F.array_position(seq, five).alias("at5"), r6(F.element_at(F.sort_array(v), 32)).alias("mid"))


@query(f"""WITH {LINES} SELECT system_id, {T.r6('0.5 * (1 - cer) + 0.5 * emb_sim')} AS cs, CASE WHEN cer > 0.4 THEN 1 ELSE 0 END + CASE WHEN emb_sim > 0.7 THEN 1 ELSE 0 END AS flags, {T.r6('emb_sim * 100')} AS pct FROM lines""")
def o_map(spark, d):
    g = fx.line_board(spark, d).withColumn("m", F.map_from_arrays(F.array(F.lit("literal"), F.lit("semantic")), F.array((1 - F.col("cer")).cast("double"), F.col("emb_sim").cast("double"))))
    weights = F.create_map(F.lit("literal"), F.lit(0.5), F.lit("semantic"), F.lit(0.5))
    products = F.map_zip_with("m", weights, lambda k, a, b: a * b)
    s = F.aggregate(F.map_values(products), F.lit(0.0), lambda a, x: a + x)
    kept = F.map_filter("m", lambda k, v: ((k == "literal") & (F.round(v, 6) < 0.6)) | ((k == "semantic") & (F.round(v, 6) > 0.7)))
    return g.select("system_id", r6(s).alias("cs"), F.size(kept).alias("flags"), r6(F.element_at(F.transform_values("m", lambda k, v: v * 100), "semantic")).alias("pct"))


@query(f"SELECT event_id, {K} AS k, {K} AS k2, '{{\"k\":' || {K} || '}}' AS back FROM events")
def o_json(spark, d):
    return load(spark, d, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"), F.from_json("props", "k int")["k"].alias("k2"), F.to_json(F.from_json("props", "k int")).alias("back"))


def html_sql(x: str) -> str:
    for rx in ("(?is)<(script|style)[^>]*>.*?</(script|style)>", "(?s)<!--.*?-->", "(?s)<[^>]*>"):
        x = f"regexp_replace({x}, '{rx}', ' ', 'g')"
    for entity, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
        x = f"replace({x}, '{entity}', '{char}')"
    return f"trim(regexp_replace({x}, '[ \\t\\r\\n]+', ' ', 'g'), ' ')"


@query(f"SELECT page_id, sha256(t) AS text_sha256, length(t)::BIGINT AS chars FROM (SELECT page_id, {html_sql('html')} AS t FROM pages)")
def o_html(spark, d):
    return load(spark, d, "pages").select("page_id", strip_html("html").alias("t")).select("page_id", F.sha2("t", 256).alias("text_sha256"), F.length("t").cast("bigint").alias("chars"))


@query("""SELECT event_id, CASE WHEN value > 50 THEN 'high' WHEN value > 20 THEN 'mid' ELSE 'low' END AS band, coalesce(nullif(event_type, 'click'), 'tap') AS kind, nullif(event_id % 3, 0) IS NULL AS third, ifnull(nullif(event_type, 'view'), event_type || '!') AS nv FROM events""")
def o_null(spark, d):
    v = F.col("value")
    return load(spark, d, "events").select(
        "event_id", F.when(v > 50, "high").when(v > 20, "mid").otherwise("low").alias("band"), F.coalesce(F.nullif("event_type", F.lit("click")), F.lit("tap")).alias("kind"),
        F.nullif(F.col("event_id") % 3, F.lit(0)).isNull().alias("third"), F.nvl(F.nullif("event_type", F.lit("view")), F.concat("event_type", F.lit("!"))).alias("nv"))


@query(f"WITH {T.MEASURED} SELECT pair_id, dist::BIGINT AS dist, hyp_len - ref_len AS growth FROM meas WHERE system_id = 'sys05'")
def o_udf_editops(spark, d):
    p = baselines.transcribe(fx.clip_text(spark, d), ["sys05"]).withColumn("o", udfs.edit_ops("hyp", "ref"))
    return p.select("pair_id", (F.col("o.sub") + F.col("o.del") + F.col("o.ins")).cast("bigint").alias("dist"), (F.col("o.ins") - F.col("o.del")).cast("bigint").alias("growth"))


@query(f"WITH {T.MEASURED} SELECT pair_id, dist FROM meas WHERE system_id = 'sys08'")
def e1_edits(spark, d):
    """Substitutions, deletions and insertions add up to the distance."""
    p = baselines.transcribe(fx.clip_text(spark, d), ["sys08"]).withColumn("o", udfs.edit_ops("hyp", "ref"))
    return p.select("pair_id", (F.col("o.sub") + F.col("o.del") + F.col("o.ins")).cast("bigint").alias("dist"))


@query()
def e1_edit_breakdown(spark, d):
    """Substitutions, deletions, insertions and matches, and word error rates, of a stand-in."""
    p = baselines.transcribe(fx.clip_text(spark, d), ["sys08"])
    return p.withColumn("o", udfs.edit_ops("hyp", "ref")).select("pair_id", "o.*", r6(udfs.wer("hyp", "ref")).alias("wer"))


@query(f"WITH {T.AUDIO}, {T.SNR} SELECT clip_id, {T.r6('snr_db')} AS snr_db FROM snrdb")
def o_udaf_snr(spark, d):
    return fx.clip_audio(spark, d).groupBy("clip_id").agg(udfs.snr_udaf("clean", "noisy").alias("snr_db")).select("clip_id", r6("snr_db").alias("snr_db"))


@query(f"WITH {T.AUDIO}, {T.SNR}, {T.FRAMES}, {T.motion()} SELECT clip_id, {T.r6('snr_db')} AS snr_db, {T.r6('motion')} AS motion FROM snrdb FULL JOIN motion USING (clip_id)")
def o_cogroup_score(spark, d):
    return rounded(udfs.cogroup_scores(fx.clip_audio(spark, d), fx.clip_frames(spark, d)), "snr_db", "motion")


@query(LANDMARKS_SQL)
def o_grouped_map_interp(spark, d):
    return rounded(udfs.interpolate_np(lips.centroids(lip_frames(spark, d))), "cx", "cy")


@query(f"WITH {T.MEASURED} SELECT pair_id, dist FROM meas WHERE system_id = 'sys04'")
def o_udtf_alignment(spark, d):
    """Edit operations of all pairs of a stand-in as rows, summed back to distances."""
    spark.udtf.register("alignment_rows", udfs.AlignmentRows)
    baselines.transcribe(fx.clip_text(spark, d), ["sys04"]).select("pair_id", "hyp", "ref").createOrReplaceTempView("alignment_pairs")
    return spark.sql("SELECT pair_id, count_if(op <> 'hit') AS dist FROM alignment_rows(TABLE(alignment_pairs)) GROUP BY pair_id")


@query("""WITH f AS (SELECT label AS clip_id, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS frame_no, embedding::DOUBLE[] AS px FROM embeddings),
w AS (SELECT *, (frame_no % 5 - 1) AS x0, (frame_no % 7 - 1) AS y0 FROM f)
SELECT clip_id, frame_no, i.i AS at, round(CASE WHEN x0 + i.i % 4 BETWEEN 0 AND 7 AND y0 + i.i // 4 BETWEEN 0 AND 7 THEN px[(y0 + i.i // 4) * 8 + x0 + i.i % 4 + 1] ELSE 0.0 END, 6) + 0.0 AS value FROM w, range(0, 16) i(i)""")
def o_udtf_crop(spark, d):
    """Pixels of windows as rows of a table function."""
    spark.udtf.register("crop_rows", udfs.CropRows)
    w = Window.partitionBy("clip_id").orderBy("vec_id")
    frames = load(spark, d, "embeddings").select(F.col("label").alias("clip_id"), "vec_id", "embedding").withColumn("frame_no", F.row_number().over(w).cast("bigint") - 1)
    frames.createOrReplaceTempView("crop_frames")
    return spark.sql("""SELECT clip_id, r.frame_no, cast(r.y * 4 + r.x AS BIGINT) AS at, round(r.value, 6) + 0D AS value
        FROM crop_frames f, LATERAL crop_rows(f.frame_no, f.embedding, 8, 8, cast(f.frame_no % 5 - 1 AS INT), cast(f.frame_no % 7 - 1 AS INT), 4) r""")


@query(f"WITH {T.MEASURED} SELECT system_id, {T.r6('avg(cer)')} AS cer, {T.r6('avg(sim)')} AS sim FROM meas WHERE system_id IN ('sys01', 'sys12') GROUP BY system_id")
def o_sqlfunc(spark, d):
    sqlf.register(spark)
    baselines.transcribe(fx.clip_text(spark, d), ["sys01", "sys12"]).withColumns({"vh": udfs.letter_counts("hyp"), "vr": F.col("ref_vec")}).createOrReplaceTempView("sqlfunc_pairs")
    return rounded(spark.sql("SELECT system_id, avg(cer(hyp, ref)) AS cer, avg(cosine(vh, vr)) AS sim FROM sqlfunc_pairs GROUP BY system_id"), "cer", "sim")


@query(f"""WITH {T.CLIPS}, p AS (SELECT clip_id, 'h' AS w, ' ' || lower(array_to_string(hyp_text, '')) || ' ' AS p FROM clips UNION ALL SELECT clip_id, 'r', ' ' || lower(array_to_string(ref_text, '')) || ' ' FROM clips),
c AS (SELECT clip_id, w, p, regexp_extract_all(p, '(?s).') AS c FROM p),
g AS (SELECT clip_id, w, unnest(CASE WHEN len(c) < 3 THEN [p] ELSE list_transform(range(1, len(c) - 1), lambda i: c[i] || c[i + 1] || c[i + 2]) END) AS gram FROM c),
n AS (SELECT clip_id, w, ('0x' || substr(md5(gram), 1, 8))::BIGINT % 64 AS slot, count(*)::DOUBLE AS n FROM g GROUP BY ALL),
q AS (SELECT clip_id, w, sqrt(sum(n * n)) AS norm FROM n GROUP BY ALL), d AS (SELECT a.clip_id, sum(a.n * b.n) AS dot FROM n a JOIN n b USING (clip_id, slot) WHERE a.w = 'h' AND b.w = 'r' GROUP BY 1)
SELECT a.clip_id, {T.r6('coalesce(dot, 0) / (a.norm * b.norm)')} AS sim FROM q a JOIN q b ON a.clip_id = b.clip_id AND a.w = 'h' AND b.w = 'r' LEFT JOIN d ON d.clip_id = a.clip_id""")
def e2_hashed_ngrams(spark, d):
    """Cosines of hashed trigram vectors of hypothesis and reference."""
    c = udfs.hashed_ngrams(udfs.hashed_ngrams(fx.clip_text(spark, d), "hyp_text", "vh", 3, 64), "ref_text", "vr", 3, 64)
    return c.select("clip_id", r6(cosine("vh", "vr")).alias("sim"))
