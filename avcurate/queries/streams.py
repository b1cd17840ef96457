"""Streams run over the given tables with availableNow; their twins are batch SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from avcurate.operators import curation, lips
from avcurate.operators.curation import CurationPolicy
from avcurate.queries import twins as T
from avcurate.queries.registry import query, r6, rounded
from avcurate.queries.relational import INTERVAL_SQL, SESSIONS_SQL
from avcurate.queries.workloads import LANDMARKS_SQL, lip_frames
from avcurate.session import shared_path
from avcurate.sources import fixtures as fx
from avcurate.sources.tables import load, write_scores_once
from avcurate.streaming import online


def events(spark, d):
    return online.read_events(spark, f"{d}/event[s].parquet")  # as a pattern, which may be one file


def naive(c: str):
    return F.col(c).cast("timestamp_ntz").alias(c)


SNR_OF = f"{T.r6('10 * log10(sum(value * value) / sum(r * r))')} AS snr_db"
EV = "e AS (SELECT *, -((props->>'$.k')::INT / 10.0::DOUBLE - 4.95::DOUBLE) AS r FROM events)"


@query(f"WITH {EV} SELECT date_trunc('hour', ts) AS start, count(*) AS n, {SNR_OF} FROM e GROUP BY 1")
def s_tumbling(spark, d):
    return online.run_to_latest(online.window_snr(events(spark, d))).select(naive("start"), "n", r6("snr_db").alias("snr_db"))


@query(f"WITH {EV} SELECT time_bucket(INTERVAL 15 MINUTE, ts, TIMESTAMP '2024-01-01') - i.i * INTERVAL 15 MINUTE AS start, count(*) AS n, {SNR_OF} FROM e, range(0, 4) i(i) GROUP BY 1")
def s_sliding(spark, d):
    return online.run_to_latest(online.window_snr(events(spark, d), "1 hour", "15 minutes")).select(naive("start"), "n", r6("snr_db").alias("snr_db"))


@query(SESSIONS_SQL.format(gap=1799.999999) + " SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, session, count(*) AS n FROM s GROUP BY ALL) GROUP BY ALL")
def s_session(spark, d):
    return online.run_to_latest(online.user_sessions(events(spark, d))).groupBy("user_id", "n").agg(F.count("*").alias("sessions"))


@query("SELECT event_type, count(*) AS n, count(DISTINCT event_id) AS ids FROM events GROUP BY 1")
def s_dedup(spark, d):
    """Each event comes twice, by a union of the stream with itself."""
    e = events(spark, d)
    return online.run_to_parquet(online.deduplicated(e.unionByName(e)).select("event_id", "event_type")).groupBy("event_type").agg(F.count("*").alias("n"), F.countDistinct("event_id").alias("ids"))


@query("SELECT event_id FROM events, (SELECT avg(value) AS m FROM events) WHERE value > m")
def s_static_join(spark, d):
    stats = load(spark, d, "events").agg(F.avg("value").alias("m"))
    return online.run_to_parquet(online.with_static(events(spark, d), stats).where("clean > m").select("event_id"))


@query(INTERVAL_SQL.format(gap=3600))
def s_interval(spark, d):
    return online.run_to_parquet(online.errors_after_clicks(events(spark, d)))


@query(f"WITH {T.curated()} SELECT clip_id, {T.r6('s_comp')} AS s_comp, split FROM curated")
def s_online_curation(spark, d):
    signals = write_scores_once(curation.clip_signals(fx.clip_text(spark, d), fx.clip_audio(spark, d), fx.clip_frames(spark, d)), shared_path(spark, "signals"))
    stats = write_scores_once(curation.fit_stats(signals, CurationPolicy()), shared_path(spark, "stats"))
    stream = spark.readStream.schema(signals.schema).option("maxFilesPerTrigger", 2).parquet(signals.inputFiles()[0].rsplit("/", 1)[0])
    return rounded(online.curate_online(stream, stats), "s_comp")


@query(LANDMARKS_SQL)
def s_stateful_interp(spark, d):
    cents = lips.centroids(lip_frames(spark, d)).select(F.col("clip_id").cast("bigint").alias("clip_id"), "frame_no", "cx", "cy", F.lit(False).alias("closes"))
    ends = cents.groupBy("clip_id").agg(F.max("frame_no").alias("frame_no")).select("clip_id", "frame_no", F.lit(None).cast("double").alias("cx"), F.lit(None).cast("double").alias("cy"), F.lit(True).alias("closes"))
    path = shared_path(spark, "cents")
    cents.unionByName(ends).repartition(2, "clip_id").write.parquet(path)
    stream = spark.readStream.schema(cents.schema).option("maxFilesPerTrigger", 1).parquet(path)
    out = online.run_to_parquet(online.interpolate_online(stream, idle_ms=None))  # each clip has a row that closes it
    return rounded(out.withColumn("clip_id", F.col("clip_id").cast("int")), "cx", "cy")
