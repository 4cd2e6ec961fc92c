import shutil

import pytest
from pyspark.sql import functions as F

from joinsynth.ledger import BudgetExceeded
from joinsynth.streaming import degrees as stream

D = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def split_events(spark, tmp_path_factory):
    """The events in three files in order of time."""
    folder = tmp_path_factory.mktemp("events")
    events = spark.read.parquet(f"{D}/events.parquet").toPandas().sort_values("ts")
    for i in range(3):
        part = events.iloc[i * len(events) // 3 : (i + 1) * len(events) // 3]
        spark.createDataFrame(part, stream.EVENTS).coalesce(1).write.parquet(str(folder / f"p{i}"))
        source = next((folder / f"p{i}").glob("part-*.parquet"))
        shutil.copy(source, folder / f"events{i}.parquet")
        shutil.rmtree(folder / f"p{i}")
    return str(folder)


def test_windows_equal_batch(spark, split_events, tmp_path):
    got = stream.run_available(stream.tumbling(stream.read_events(spark, split_events)), "t_tumbling", "complete", str(tmp_path / "c"))
    want = spark.read.parquet(f"{D}/events.parquet").groupBy(F.window("ts", "1 day").start.alias("start"), "event_type").agg(F.count("*").alias("freq"))
    assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0


def test_state_survives_batches_and_caps(spark, split_events, tmp_path):
    got = stream.run_available(stream.capped_degrees(stream.read_events(spark, split_events), 40), "t_state", "update", str(tmp_path / "c"))
    got = {r.user_id: r.d for r in got.groupBy("user_id").agg(F.max("degree").alias("d")).collect()}
    want = {r.user_id: min(40, r["count"]) for r in spark.read.parquet(f"{D}/events.parquet").groupBy("user_id").count().collect()}
    assert got == want


def test_late_rows_are_dropped_behind_the_watermark(spark, split_events, tmp_path):
    """A file of old events that comes last adds nothing to windows that are closed."""
    old = spark.read.parquet(f"{D}/events.parquet").orderBy("ts").limit(50)
    old.coalesce(1).write.parquet(str(tmp_path / "p"))
    folder = tmp_path / "in"
    shutil.copytree(split_events, folder)
    shutil.copy(next((tmp_path / "p").glob("part-*.parquet")), folder / "events9.parquet")
    run = lambda src, name: stream.run_available(stream.tumbling(stream.read_events(spark, str(src))), name, "append", str(tmp_path / name)).agg(F.sum("freq")).first()[0]
    assert run(folder, "t_late") <= run(split_events, "t_in_time") + 50


def test_schedule_divides_the_budget(spark, split_events, tmp_path):
    seen = []
    ledger = stream.release_on_schedule(stream.read_events(spark, split_events), 2, 1.0, 1e-6, lambda b, e, d, n: seen.append((n, e, b.count())), str(tmp_path / "c"))
    assert [s[:2] for s in seen] == [(0, 0.5), (1, 0.5)] and ledger.total == pytest.approx((1.0, 1e-6))
    with pytest.raises(BudgetExceeded):
        ledger.spend("one more", 0.1)


def test_stream_static_join_and_dedup(spark, split_events, tmp_path):
    customers = spark.read.parquet(f"{D}/customer.parquet")
    joined = stream.run_available(stream.with_segment(stream.read_events(spark, split_events), customers), "t_static", "append", str(tmp_path / "a"))
    assert joined.count() == spark.read.parquet(f"{D}/events.parquet").join(customers, F.col("user_id") == F.col("c_custkey")).count()
    assert stream.run_available(stream.dedup(stream.read_events(spark, split_events)), "t_dedup", "append", str(tmp_path / "b")).count() == 1000


@pytest.mark.parametrize("mode", ["complete", "append"])
def test_results_of_streams_stay_off_the_driver(spark, split_events, tmp_path, mode):
    """A result in an in-memory table is held by the driver row by row; it is to lie in files."""
    build = stream.sessions if mode == "complete" else stream.dedup
    got = stream.run_available(build(stream.read_events(spark, split_events)), f"t_files_{mode}", mode, str(tmp_path / mode))
    assert got.inputFiles()
    if mode == "complete":
        ts = spark.read.parquet(f"{D}/events.parquet")
        want = ts.groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("freq")).select("user_id", F.col("w.start").alias("start"), "freq")
        assert got.exceptAll(want).count() == want.exceptAll(got).count() == 0
    else:
        assert got.select("event_id").distinct().count() == got.count() == 1000


def test_stream_without_files_is_empty(spark, tmp_path):
    (tmp_path / "in").mkdir()
    assert stream.run_available(stream.sessions(stream.read_events(spark, str(tmp_path / "in"))), "t_nothing", "complete", str(tmp_path / "c")).count() == 0
