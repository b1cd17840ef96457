"""Plans, sources, sinks, streams."""

from datetime import datetime, timedelta

import pytest
from pyspark.sql import functions as F

from avcurate.plans import checks
from avcurate.queries import QUERIES
from avcurate.queries.workloads import curated
from avcurate.sources import frames_source, tables
from avcurate.sources import fixtures as fx
from avcurate.streaming import online
from compare import SMALL


def test_curation_stays_in_the_jvm_and_reads_what_it_needs(spark):
    df = curated(spark, SMALL)
    assert not checks.python_nodes(df) and not checks.has_cartesian(df) and not checks.single_partition_windows(df)
    docs = [s for s in checks.read_schemas(df) if "doc_id" in s]
    assert docs and all("n_chars" not in s for s in docs)
    scores = tables.load(spark, SMALL, "documents").where("doc_id < 10").select("doc_id")
    assert any("LessThan(doc_id,10)" in p for p in checks.pushed_filters(scores))


@pytest.mark.parametrize("name", ["w2_split_exact", "w7_difficulty", "w3_curate", "w14_split_leak"])
def test_no_global_window(spark, name):
    df = QUERIES[name](spark, SMALL)
    text = df._jdf.queryExecution().executedPlan().toString()
    assert "EvalPython" not in text


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_round_trip(spark, tmp_path, fmt):
    df = spark.createDataFrame([(1, 'a "b", c\nd', 1.5), (2, "", 0.0), (3, "é", None)], "id long, s string, v double")
    assert sorted(map(tuple, tables.roundtrip(df, fmt, f"file://{tmp_path}/x").collect())) == sorted(map(tuple, df.collect()))


def test_columns_are_checked(spark):
    with pytest.raises(ValueError):
        tables.assert_columns(spark.range(1), ["clip_id"])


def test_sinks(spark, tmp_path):
    c = curated(spark, SMALL)
    tables.write_curated(c, f"file://{tmp_path}/c")
    assert spark.read.parquet(f"file://{tmp_path}/c").where("split = 'accept'").count() == 55
    tables.write_frames_bucketed(fx.clip_frames(spark, SMALL), "frames_b", 4)
    g = spark.table("frames_b").groupBy("clip_id").count()
    assert checks.exchanges(g) == 0 and g.count() == 200


def test_media_and_frames(spark, tmp_path):
    (tmp_path / "a.bin").write_bytes(b"\x01\x02")
    assert tables.load_media(spark, f"file://{tmp_path}/*.bin").first().content == b"\x01\x02"
    frames_source.register(spark)
    df = spark.read.format("frames").option("clips", 3).option("frames", 2).load()
    assert df.count() == 6 and df.where("aggregate(pixels, 0F, (a, x) -> a + x) = 1").count() == 6


def test_late_rows(spark, tmp_path):
    """Rows out of order within the delay count; the stream's result is the batch's."""
    start = datetime(2024, 1, 1)
    def write(name, minutes):
        rows = [(i, start + timedelta(minutes=m), 1, "click", 2.0, '{"k": 10}') for i, m in minutes]
        spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/in")
    path = f"file://{tmp_path}/in"
    write("a", [(1, 0), (2, 50)])
    write("b", [(3, 45), (4, 70)])
    write("c", [(5, 200)])
    s = online.read_events(spark, path, 1, "30 minutes")
    got = {r.start: r.n for r in online.run_to_table(online.window_snr(s), "late", "append").collect()}
    assert got[start] == 3 and got[start + timedelta(hours=1)] == 1
    upd = online.run_to_table(online.window_snr(online.read_events(spark, path, 1, "30 minutes")), "upd", "update")
    assert upd.where(F.col("start") == F.lit(start)).agg(F.max("n")).first()[0] == 3
