"""Structured Streaming twins: windowed energies, sessions, deduplication, joins, state, online curation."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from avcurate.operators.curation import CurationPolicy, score
from avcurate.operators.signal import ratio_db
from avcurate.session import shared_path
from avcurate.sources.tables import SCHEMAS, with_k


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 4, delay: str = "10 minutes") -> DataFrame:
    """Files of events as they come; event time is ``ts`` as a timestamp, and rows later than ``delay`` may be dropped."""
    raw = spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return samples(raw).withWatermark("ts", delay)


def samples(events: DataFrame) -> DataFrame:
    """clean and residual of each event, with its time."""
    e = with_k(events).withColumn("ts", F.col("ts").cast("timestamp"))
    return e.select("event_id", "ts", "user_id", "event_type", F.col("value").alias("clean"), (-(F.col("k") / 10.0 - 4.95)).alias("residual"))


def window_snr(events: DataFrame, length: str = "1 hour", slide: str | None = None) -> DataFrame:
    """n and snr_db of tumbling or sliding windows; energies add up, so the batch form is the same."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    g = events.groupBy(w.alias("w")).agg(F.count("*").alias("n"), F.sum(F.col("clean") * F.col("clean")).alias("signal"), F.sum(F.col("residual") * F.col("residual")).alias("noise"))
    return g.select(F.col("w.start").alias("start"), "n", ratio_db(F.col("signal"), F.col("noise"))[0].alias("snr_db"))


def user_sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    g = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return g.select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame) -> DataFrame:
    return events.dropDuplicatesWithinWatermark(["event_id"])


def with_static(events: DataFrame, stats: DataFrame) -> DataFrame:
    """A stream and a small, frozen table of one row."""
    return events.crossJoin(F.broadcast(stats))


def errors_after_clicks(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join of each error with the same user's clicks before it; state is bounded by the watermarks."""
    c = events.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), "user_id", F.col("ts").alias("click_ts"))
    e = events.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), F.col("user_id").alias("error_user"), F.col("ts").alias("error_ts"))
    return c.join(e, F.expr(f"user_id = error_user AND error_ts >= click_ts AND error_ts <= click_ts + INTERVAL {within}")).select("click_id", "error_id", "user_id")


FILLED = "clip_id long, frame_no long, cx double, cy double, filled boolean"
IDLE_MS = 3_600_000
GAP_STATE = "last_no long, last_x double, last_y double, gap array<long>"


def fill_gaps(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState, idle_ms: int | None = IDLE_MS) -> Iterator[pd.DataFrame]:
    """Frames of a clip in order: a gap waits for the next valid frame; a row with ``closes``, or ``idle_ms`` without rows, ends the clip and its state."""
    if state.hasTimedOut:
        _, x, y, gap = state.get
        state.remove()
        yield pd.DataFrame([(key[0], f, x, y, True) for f in gap], columns=["clip_id", "frame_no", "cx", "cy", "filled"])
        return
    last_no, x, y, gap = state.get if state.exists else (None, None, None, [])
    gap, out = list(gap), []
    rows = sorted((r for b in frames for r in b.itertuples(index=False)), key=lambda r: (r.closes, r.frame_no))
    for r in rows:
        if r.closes:
            out += [(key[0], f, x, y, True) for f in gap]
            gap = []
        elif pd.isna(r.cx):
            gap.append(r.frame_no)
        else:
            for f in gap:
                s = None if last_no is None else (f - last_no) / (r.frame_no - last_no)
                out.append((key[0], f, r.cx, r.cy, True) if s is None else (key[0], f, x + (r.cx - x) * s, y + (r.cy - y) * s, True))
            out.append((key[0], r.frame_no, r.cx, r.cy, False))
            last_no, x, y, gap = r.frame_no, r.cx, r.cy, []
    if any(r.closes for r in rows):
        if state.exists:
            state.remove()
    else:
        state.update((last_no, x, y, gap))
        if idle_ms is not None:
            state.setTimeoutDuration(idle_ms)
    yield pd.DataFrame(out, columns=["clip_id", "frame_no", "cx", "cy", "filled"])


def interpolate_online(cents: DataFrame, idle_ms: int | None = IDLE_MS) -> DataFrame:
    """cents (clip_id, frame_no, cx, cy, closes) as a stream, each clip's frames in order over the batches; a clip without rows for ``idle_ms`` is closed.

    With None only ``closes`` ends a clip. A run over what is there needs that: with timeouts of processing time Spark adds batches without rows and never ends.
    """
    timeout = GroupStateTimeout.NoTimeout if idle_ms is None else GroupStateTimeout.ProcessingTimeTimeout

    def fill(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        return fill_gaps(key, frames, state, idle_ms)

    return cents.groupBy("clip_id").applyInPandasWithState(fill, FILLED, GAP_STATE, "append", timeout)


def run_to_table(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run over what is there into a memory table: for small results and tests."""
    spark = stream.sparkSession
    path = shared_path(spark, "stream")
    table = f"{name}_{path.rsplit('-', 1)[1][:12]}"
    q = stream.writeStream.format("memory").queryName(table).outputMode(mode).option("checkpointLocation", path).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(table)


def run_to_parquet(stream: DataFrame) -> DataFrame:
    """Run over what is there into Parquet files of the shared folder, exactly once, and read them."""
    spark = stream.sparkSession
    path = shared_path(spark, "stream")
    stream.writeStream.format("parquet").option("path", f"{path}/out").option("checkpointLocation", f"{path}/state").outputMode("append").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out")


def run_to_latest(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Run over what is there; each batch writes the result so far to a folder of its own, and the last one is read. Nothing meets in the driver."""
    spark = stream.sparkSession
    path, last = shared_path(spark, "stream"), []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/batch={number}")
        last.append(number)

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{path}/out/batch={last[-1]}") if last else spark.createDataFrame([], stream.schema)


def curate_online(signals: DataFrame, stats: DataFrame, policy: CurationPolicy = CurationPolicy(), out: str | None = None) -> DataFrame:
    """Score a stream of per-clip signals with frozen statistics; a batch overwrites its own folder, so a replay changes nothing."""
    spark = signals.sparkSession
    path = out or shared_path(spark, "curated")

    def write(batch: DataFrame, number: int) -> None:
        score(batch, stats, policy).select("clip_id", "s_comp", "split").write.mode("overwrite").parquet(f"{path}/out/batch={number}")

    signals.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("clip_id long, s_comp double, split string, batch int").parquet(f"{path}/out").drop("batch")
