import shutil

from conftest import SF

from cellscrub.streaming import monitor


def folder(tmp_path):
    (tmp_path / "in").mkdir()
    shutil.copy(f"{SF}/events.parquet", tmp_path / "in" / "events.parquet")
    return str(tmp_path / "in")


def test_windows_of_stream_and_batch(spark, tmp_path):
    path = folder(tmp_path)
    batch = {r.window_start: (r.n, r.n_errors) for r in monitor.error_rate(monitor.dirtied(spark.read.parquet(path))).collect()}
    out = monitor.run_to_memory(monitor.error_rate(monitor.dirtied(monitor.event_stream(spark, path))), "windows", "complete", str(tmp_path / "cp"))
    assert {r.window_start: (r.n, r.n_errors) for r in out.collect()} == batch


def test_drift_monitor_counts_every_event(spark, tmp_path):
    path = folder(tmp_path)
    out = monitor.run_to_memory(monitor.drift(monitor.dirtied(monitor.event_stream(spark, path))), "drift", "update", str(tmp_path / "cp"))
    assert out.agg({"n": "sum"}).first()[0] == spark.read.parquet(path).count()


def test_duplicates_are_dropped_within_the_watermark(spark, tmp_path):
    path = folder(tmp_path)
    e = monitor.event_stream(spark, path)
    out = monitor.run_to_memory(monitor.deduplicated(e.union(e)), "once", "append", str(tmp_path / "cp"))
    assert out.count() == spark.read.parquet(path).count()
