"""Late rows, restarts and equality of streams with batches."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from subvote.operators.engine import IndexParams, SearchParams, build_index, search
from subvote.sources import vectors as sources
from subvote.streaming import engine

EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double"


def at(hour, minute=0):
    return dt.datetime(2024, 1, 1, hour, minute)


def write(spark, folder, name, rows):
    spark.createDataFrame(rows, EVENT).coalesce(1).write.mode("append").parquet(f"{folder}/{name}")


def read(spark, folder, name):
    return engine.file_stream(spark, f"{folder}/{name}", EVENT, 1)


def sink(df, folder):
    engine.run_once(df.writeStream.format("parquet").outputMode("append").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/cp"))
    return df.sparkSession.read.parquet(f"{folder}/out")


def test_late_rows_are_dropped_and_a_restart_goes_on(spark, tmp_path):
    folder = str(tmp_path)
    write(spark, folder, "in", [(1, at(1), 1, "view", 1.0), (2, at(1, 30), 1, "view", 1.0)])
    sink(engine.windowed_counts(read(spark, folder, "in")), folder)
    write(spark, folder, "in", [(3, at(9), 1, "view", 1.0)])
    sink(engine.windowed_counts(read(spark, folder, "in")), folder)
    write(spark, folder, "in", [(4, at(1, 45), 1, "view", 1.0), (5, at(8, 30), 1, "view", 1.0), (6, at(20), 1, "view", 1.0)])
    out = sink(engine.windowed_counts(read(spark, folder, "in")), folder)
    got = sorted((r["start"].hour, r["n"]) for r in out.collect())
    assert (1, 2) in got and (8, 1) in got  # event 4 came after its hour was closed


def test_dedup_join_and_sessions(spark, tmp_path):
    folder = str(tmp_path)
    rows = [(1, at(1), 1, "view", 1.0), (2, at(1, 20), 1, "purchase", 5.0), (3, at(3), 1, "purchase", 5.0), (4, at(1, 10), 2, "view", 1.0)]
    write(spark, folder, "in", rows + rows)
    events = engine.deduplicated(read(spark, folder, "in"), late="10 hours")
    assert sink(events, folder + "/a").count() == 4
    stream = read(spark, folder, "in").dropDuplicates(["event_id"])
    met = engine.purchases_after_views(stream.filter("event_type = 'view'"), read(spark, folder, "in").filter("event_type = 'purchase'"))
    assert {tuple(r) for r in sink(met, folder + "/b").collect()} == {(2, 1)}


def test_session_windows_close(spark, tmp_path):
    folder = str(tmp_path)
    write(spark, folder, "in", [(1, at(1), 1, "view", 1.0), (2, at(1, 20), 1, "view", 1.0), (3, at(2, 30), 1, "view", 1.0)])
    write(spark, folder, "in", [(4, at(23), 9, "view", 1.0)])
    sink(engine.session_counts(read(spark, folder, "in")), folder)
    write(spark, folder, "in", [(5, at(23, 30), 9, "view", 1.0)])
    out = sink(engine.session_counts(read(spark, folder, "in")), folder)
    assert sorted((r["user_id"], r["n"]) for r in out.collect()) == [(1, 1), (1, 2)]


def test_append_stream_equals_batch(spark, sf, tmp_path):
    base, queries = sources.split(sources.embeddings(spark, sf))
    params = IndexParams(m=8, k=8, init="id_stride", iters=0, policy="never", shard_rows=100, storage="f8")
    first = build_index(base.filter("id % 3 = 0"), params)
    base.filter("id % 3 != 0").repartition(3).write.parquet(str(tmp_path / "v"))
    stream = engine.file_stream(spark, str(tmp_path / "v"), "id long, vec array<double>", 1)
    seen = []
    grown = engine.append_stream(stream, first, str(tmp_path / "cp"), lambda i, b: seen.append((b, i.n)))
    assert grown.n == base.count() and len(seen) == 3
    p = SearchParams("guaranteed", 1.0, 0.01)
    assert sorted(search(grown, queries, 5, p).collect()) == sorted(search(build_index(base, params), queries, 5, p).collect())


def test_drift_monitor(spark, sf, tmp_path):
    calm = sources.embeddings(spark, sf)
    calm.write.parquet(str(tmp_path / "v"))
    monitor = engine.DriftMonitor(64)
    history = monitor.watch(engine.file_stream(spark, str(tmp_path / "v"), "id long, vec array<double>", 1), str(tmp_path / "cp"))
    from subvote.operators import spectral

    assert history[-1][2] == pytest.approx(spectral.check(calm, calm.count(), 64, rule="guarded").cev, abs=0.05) and not monitor.rebuild
    loud = sources.decayed(calm, 0.7).withColumn("vec", F.transform("vec", lambda x: x * 100))
    monitor.update(loud, 99)
    assert monitor.rebuild


def test_append_survives_restart_and_replay(spark, tmp_path):
    """What a first run added is there after a restart, and a batch that runs again is not added twice."""
    folder = f"file://{tmp_path}"
    df = sources.synthetic(spark, 300, 16, partitions=2)
    base = build_index(df.filter("id < 100"), IndexParams(m=2, k=4, iters=1, policy="never", shard_rows=64))
    stream = lambda: engine.file_stream(spark, f"{folder}/in", "id long, vec array<double>", 1)
    df.filter("id >= 100 and id < 200").write.mode("append").parquet(f"{folder}/in")
    assert engine.append_stream(stream(), base, f"{folder}/cp").n == 200
    df.filter("id >= 200").write.mode("append").parquet(f"{folder}/in")
    again = build_index(df.filter("id < 100"), IndexParams(m=2, k=4, iters=1, policy="never", shard_rows=64))
    index = engine.append_stream(stream(), again, f"{folder}/cp")
    assert index.n == 300 and int(index.counts[0].sum()) == 300
    from subvote.operators.engine import append_saved, load_index

    append_saved(index, df.filter("id >= 100 and id < 200"), f"{folder}/cp-index", 0)
    assert load_index(spark, f"{folder}/cp-index").n == load_index(spark, f"{folder}/cp-index").counts[0].sum()
    got = search(load_index(spark, f"{folder}/cp-index"), df.filter("id % 50 = 0"), 1, SearchParams("guaranteed", 1.0, 0.01)).collect()
    assert sorted((r["query_id"], r["id"]) for r in got) == [(i, i) for i in range(0, 300, 50)]


def test_drift_state_survives_restart_and_replay(spark, tmp_path):
    folder = f"file://{tmp_path}"
    df = sources.synthetic(spark, 200, 8, partitions=1)
    stream = lambda: engine.file_stream(spark, f"{folder}/in", "id long, vec array<double>", 1)
    df.filter("id < 120").coalesce(1).write.mode("append").parquet(f"{folder}/in")
    first = engine.DriftMonitor(8, folder=f"{folder}/state").watch(stream(), f"{folder}/cp")
    df.filter("id >= 120").coalesce(1).write.mode("append").parquet(f"{folder}/in")
    monitor = engine.DriftMonitor(8, folder=f"{folder}/state")
    rows = monitor.watch(stream(), f"{folder}/cp")
    assert [r[1] for r in rows] == [*(r[1] for r in first), 200]
    monitor.update(df.filter("id >= 120"), rows[-1][0])  # the batch runs again
    assert monitor.n == 200
    assert [r[1] for r in engine.DriftMonitor(8, folder=f"{folder}/state").watch(stream(), f"{folder}/cp")] == [r[1] for r in rows]


def test_top_alerts_expire(spark, tmp_path):
    folder = str(tmp_path)
    write(spark, folder, "in", [(1, at(1), 1, "view", 1.0), (2, at(1, 5), 1, "view", 3.0), (3, at(1, 6), 1, "view", 2.0), (4, at(1, 7), 1, "view", 0.5)])
    out = sink(engine.top_alerts(read(spark, folder, "in"), k=2, idle=600, late="1 minute"), folder)
    assert {(r["event_id"], r["place"]) for r in out.collect()} == {(1, 1), (2, 1), (3, 2)}
    write(spark, folder, "in", [(5, at(9), 2, "view", 1.0)])
    sink(engine.top_alerts(read(spark, folder, "in"), k=2, idle=600, late="1 minute"), folder)
    write(spark, folder, "in", [(6, at(9, 30), 2, "view", 0.1)])
    out = sink(engine.top_alerts(read(spark, folder, "in"), k=2, idle=600, late="1 minute"), folder)
    gone = [r for r in out.collect() if r["kind"] == "gone"]
    assert [(r["user_id"], r["value"]) for r in gone] == [(1, 2.0)]
