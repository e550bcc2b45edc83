import datetime as dt

from pyspark.sql import functions as F

from windowforge.streaming import stream

SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double"


def at(minute):
    return dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minute)


def batches(spark, tmp_path, parts, schema=SCHEMA):
    """A stream that sees one file a trigger."""
    for k, rows in enumerate(parts):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in/{k:03d}")
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(f"{tmp_path}/in")


def run(df, name, tmp_path, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{tmp_path}/cp-{name}").trigger(availableNow=True).start()
    q.awaitTermination(120)
    assert q.exception() is None
    return df.sparkSession.table(name).collect()


def event(i, minute, user=1, kind="view"):
    return (i, at(minute), user, kind, 1.0)


def test_counts_and_late_rows(spark, tmp_path):
    parts = [[event(1, 5), event(2, 20)], [event(3, 400)], [event(7, 430)], [event(4, 10), event(5, 410)], [event(6, 900)]]
    got = run(stream.tumbling(batches(spark, tmp_path, parts)), "tumbling", tmp_path)
    counts = {r.start: r.events for r in got}
    assert counts[at(0)] == 2  # event 4 came after the watermark had passed its hour
    assert counts[at(360)] == 2 and counts[at(420)] == 1


def test_repeats_and_sessions(spark, tmp_path):
    parts = [[event(1, 0), event(1, 0), event(2, 10)], [event(2, 10), event(3, 100)], [event(9, 900)]]
    got = run(stream.deduplicated(batches(spark, tmp_path, parts)), "dedup", tmp_path)
    assert sorted(r.event_id for r in got) == [1, 2, 3, 9]
    s = run(stream.sessions(batches(spark, tmp_path / "s", parts)), "sess", tmp_path / "s")
    assert (at(0), at(40), 4) in {(r.start, r.end, r.events) for r in s}


def test_join_in_time(spark, tmp_path):
    schema = "user_id long, lts timestamp, view_id long"
    views = batches(spark, tmp_path / "a", [[(1, at(0), 10), (1, at(200), 11)]], schema)
    buys = batches(spark, tmp_path / "b", [[(1, at(30), 20), (1, at(100), 21), (2, at(30), 22)]], "user_id long, rts timestamp, purchase_id long")
    got = run(stream.interval_join(views, buys, "user_id"), "joined", tmp_path)
    assert {(r.view_id, r.purchase_id) for r in got} == {(10, 20)}


def test_frozen_and_growing_centres(spark, tmp_path):
    schema = "seg_id string, vec array<float>, cluster_id string"
    docs = batches(spark, tmp_path, [[("a", [1.0, 0.0], "x"), ("b", [0.0, 1.0], "y")], [("c", [0.9, 0.1], "x")]], schema)
    cents = spark.createDataFrame([("x", [1.0, 0.0]), ("y", [0.0, 1.0])], "cluster_id string, vec array<double>")
    for name, fn in (("assign", stream.assign_to(cents, f"{tmp_path}/assigned")), ("sums", stream.update_centroids(f"{tmp_path}/sums"))):
        q = docs.writeStream.foreachBatch(fn).option("checkpointLocation", f"{tmp_path}/cp-{name}").trigger(availableNow=True).start()
        q.awaitTermination(120)
        assert q.exception() is None
    assert {r.seg_id: r.cluster_id for r in spark.read.parquet(f"{tmp_path}/assigned").collect()} == {"a": "x", "b": "y", "c": "x"}
    got = {r.cluster_id: (r.n, [round(v, 5) for v in r.vec]) for r in stream.centroids(spark, f"{tmp_path}/sums").collect()}
    assert got == {"x": (2, [0.95, 0.05]), "y": (1, [0.0, 1.0])}


def test_online_packing(spark, tmp_path):
    parts = [[("k", "a", 6), ("k", "b", 5)], [("k", "c", 5), ("j", "d", 20)]]
    got = run(stream.pack(batches(spark, tmp_path, parts, "cluster_id string, seg_id string, n_tokens int"), 10), "packed", tmp_path)
    assert {r.seg_id: (r.window_no, r.offset, r.used) for r in got} == {"a": (0, 0, 6), "b": (1, 0, 5), "c": (1, 5, 5), "d": (0, 0, 10)}


def test_batch_twins_need_no_watermark(spark):
    rows = spark.createDataFrame([event(1, 0), event(2, 61)], SCHEMA)
    assert stream.sliding(rows).agg(F.sum("events")).first()[0] == 4
