"""Streams give what tables give."""

from __future__ import annotations

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridcluster.functions import features
from gridcluster.sources import tables
from gridcluster.streaming import scoring

CENTERS = np.array([[20.0, 6.0], [20.0, 18.0], [80.0, 12.0]])


def profile(df):
    return features.events_profile(df).select(F.col("row_id").alias("event_id"), "ts", "user_id", F.slice("feats", 1, 2).alias("feats"))


def in_files(spark, small, path):
    e = tables.load(spark, small, "events").orderBy("ts")
    e.repartitionByRange(4, "ts").write.parquet(path)
    return e


def drained(stream, path, name, mode="append"):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", path).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)


def test_stream_labels_equal_table_labels(spark, small, tmp_path):
    e = in_files(spark, small, f"{tmp_path}/in")
    s = scoring.score(profile(tables.stream(spark, f"{tmp_path}/in", e.schema)), CENTERS).select("event_id", "pred")
    got = drained(s, f"{tmp_path}/cp", "labels")
    want = scoring.score(profile(e), CENTERS).select("event_id", "pred")
    assert got.count() == want.count() and got.exceptAll(want).count() == 0
    # a restart from the same checkpoint reads nothing again
    q = s.writeStream.format("noop").option("checkpointLocation", f"{tmp_path}/cp2").trigger(availableNow=True).start()
    q.awaitTermination()
    q = s.writeStream.format("noop").option("checkpointLocation", f"{tmp_path}/cp2").trigger(availableNow=True).start()
    q.awaitTermination()
    assert not q.recentProgress or sum(p["numInputRows"] for p in q.recentProgress) == 0


def test_windows_and_dedup(spark, small, tmp_path):
    e = in_files(spark, small, f"{tmp_path}/in")
    scored = scoring.score(profile(tables.stream(spark, f"{tmp_path}/in", e.schema, 100)), CENTERS)
    got = drained(scoring.label_counts(scored, "tumbling", "1 hour", watermark="3650 days"), f"{tmp_path}/a", "windows", "complete")
    want = scoring.label_counts(scoring.score(profile(e), CENTERS), "tumbling", "1 hour")
    assert got.exceptAll(want).count() == 0 and got.count() == want.count()
    twice = tables.stream(spark, f"{tmp_path}/in", e.schema, 100)
    once = drained(scoring.dedup(twice.unionAll(tables.stream(spark, f"{tmp_path}/in", e.schema, 100))).select("event_id"), f"{tmp_path}/b", "dedup")
    assert once.count() == e.count()


def test_running_centers(spark, small, tmp_path):
    e = in_files(spark, small, f"{tmp_path}/in")
    scored = scoring.score(profile(tables.stream(spark, f"{tmp_path}/in", e.schema)), CENTERS)
    got = drained(scoring.running_centers(scored, 2), f"{tmp_path}/c", "running", "update")
    last = {r["pred"]: r for r in got.groupBy("pred").agg(F.max_by("center", "n").alias("c"), F.max("n").alias("n")).collect()}
    for r in scoring.score(profile(e), CENTERS).groupBy("pred").agg(F.count(F.lit(1)).alias("n"), F.avg(F.col("feats")[0]).alias("m")).collect():
        assert last[r["pred"]]["n"] == r["n"] and abs(last[r["pred"]]["c"][0] - r["m"]) < 1e-9


@pytest.mark.parametrize("kind", ["timestamp", "timestamp_ntz"])
def test_late_rows_go_aside(spark, monkeypatch, kind):
    import datetime as dt
    import time

    if kind == "timestamp_ntz":  # a driver in another zone than the session
        monkeypatch.setenv("TZ", "Asia/Tokyo")
        time.tzset()
    t = dt.datetime(2024, 1, 1, 12)
    good, late = [], []
    split = scoring.late_splitter(lambda d, i: good.extend(r["k"] for r in d.collect()), lambda d, i: late.extend(r["k"] for r in d.collect()), 600)
    rows = lambda *x: spark.createDataFrame([(k, t + dt.timedelta(seconds=s)) for k, s in x], f"k int, ts {kind}")
    try:
        split(rows((1, 0), (2, 1000)), 0)
        split(rows((3, 500), (4, 100), (5, 2000)), 1)
    finally:
        monkeypatch.undo()
        time.tzset()
    assert sorted(good) == [1, 2, 3, 5] and late == [4]


def test_latest_model_by_brute_force(spark):
    import datetime as dt

    t = dt.datetime(2024, 1, 1)
    at = lambda h: t + dt.timedelta(hours=h)
    e = spark.createDataFrame([(i, at(h)) for i, h in enumerate((0, 5, 30, 49, 100))], "event_id int, ts timestamp")
    v = spark.createDataFrame([(at(3), 1), (at(30), 2), (at(40), 3)], "ts timestamp, version int")
    got = {r["event_id"]: r["version"] for r in scoring.latest_model(e, v).collect()}
    assert got == {0: None, 1: 1, 2: 2, 3: 3, 4: 3}


def test_late_rows_after_a_restart(spark, tmp_path):
    """The greatest time seen lies in the state folder: a new process splits the next batch, or the same one again, alike."""
    import datetime as dt

    t = dt.datetime(2024, 1, 1, 12)
    rows = lambda *x: spark.createDataFrame([(k, t + dt.timedelta(seconds=s)) for k, s in x], "k int, ts timestamp")

    def fresh():
        good, late = [], []
        return scoring.late_splitter(lambda d, i: good.extend(r["k"] for r in d.collect()), lambda d, i: late.extend(r["k"] for r in d.collect()), 600, state=f"file://{tmp_path}/state"), good, late

    first, good, late = fresh()
    first(rows((1, 0), (2, 5000)), 0)
    assert good == [1, 2] and not late
    for _ in range(2):
        again, good, late = fresh()
        again(rows((3, 100), (4, 4900)), 1)
        assert good == [4] and late == [3]
