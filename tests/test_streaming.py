"""Streams give what batches give."""

import uuid

import pytest
from pathtraces import workloads as w
from pathtraces.operators import clean, counts
from pathtraces.operators.dag import LabeledDag
from pathtraces.sources import readings as src
from pathtraces.streaming import live

SF = "/root/testdata/sf0.001"
DELTA = src.EVENTS.delta(1440)


@pytest.fixture(scope="module")
def raw(spark):
    return LabeledDag.from_readings(w.readings_of(spark, SF), DELTA, "raw")


def test_edges_and_counts(spark, raw):
    edges = w.stream_edges(spark, SF)
    assert {tuple(r) for r in edges.collect()} == {tuple(r) for r in raw.edges.collect()}
    got = {tuple(r) for r in w.stream_path_counts(spark, SF).where("vid >= 0").collect()}
    assert got == {tuple(r) for r in counts.spread(counts.count_paths(raw, 3, direction="ending"), 3).collect()}


def test_sample_size(spark, raw):
    n = w.stream_sample(spark, SF).where("end_vid >= 0").count()
    total = counts.total_paths(counts.count_paths(raw, 3), 3)
    assert abs(n - 0.02 * total) < 5 * (0.02 * total) ** 0.5


def play(spark, tmp_path, batches, lateness):
    for k, rows in enumerate(batches):
        src.literal_readings(spark, rows).coalesce(1).write.mode("append").parquet(str(tmp_path / "in" / f"{k:03d}"))
    stream = spark.readStream.schema(src.SCHEMA).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    q = live.live_paths(stream, 10 * src.MINUTE, lateness).writeStream.format("parquet").option("path", str(tmp_path / "out")).option("checkpointLocation", str(tmp_path / "state")).trigger(availableNow=True).start()
    q.awaitTermination()
    play.progress = q.recentProgress
    return spark.read.parquet(str(tmp_path / "out")).where("tag >= 0").collect()


def test_late_readings(spark, tmp_path):
    at = lambda minute, vid, label: (1, minute * src.MINUTE, vid, label)
    end = [(-1, 10_000 * src.MINUTE, 99, "end")], [(-1, 20_000 * src.MINUTE, 100, "end")]
    batches = [[at(100, 1, "a"), at(104, 3, "c")], [at(102, 2, "b")], [at(200, 4, "a")], [at(300, 5, "b")], [at(101, 6, "z")], *end]
    rows = play(spark, tmp_path, batches, "5 minutes")
    edges = {(r.other, r.vid) for r in rows if r.kind == "edge"}
    assert edges == {(1, 2), (1, 3), (2, 3)}  # in order within the lateness
    assert [r.vid for r in rows if r.kind == "late"] == [6]
    assert 6 not in {r.vid for r in rows if r.kind != "late"}


def test_states_expire(spark, tmp_path):
    at = lambda tag, minute: (tag, minute * src.MINUTE, 1000 * tag + minute, "a")
    play(spark, tmp_path, [[at(t, 0) for t in range(1, 40)], [at(50, 500)], [at(51, 1000)], [at(52, 1500)]], "0 seconds")
    held = [p["stateOperators"][0]["numRowsTotal"] for p in play.progress]
    assert held[0] == 39 and held[-1] <= 2


def test_late_readings_of_a_replay(spark):
    got = w.stream_late(spark, SF).count()
    assert 0 < got < w.readings_of(spark, SF).where("seq % 37 = 0").count() + 1


def test_sessions_go_on_across_other_labels(spark):
    rows = [(1, 0, 1, "a"), (1, 60_000_000, 2, "b"), (1, 120_000_000, 3, "a")]
    got = {(r.label, r.n) for r in live.session_runs(src.literal_readings(spark, rows), "10 minutes").collect()}
    assert got == {("a", 2), ("b", 1)}
    assert clean.clean(src.literal_readings(spark, rows), 600_000_000, "collapse").count() == 3


def test_live_summary(spark, tmp_path):
    from pyspark.sql import functions as F

    for k in range(3):
        spark.createDataFrame([("x",)] * 50 + [(f"t{k}-{i}",) for i in range(30)], "text string").coalesce(1).write.parquet(str(tmp_path / "in" / str(k)))
    stream = spark.readStream.schema("text string").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", "true").parquet(str(tmp_path / "in"))
    seen = []
    q = live.live_frequent(stream, 5, lambda counters, n: seen.append(counters)).option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert len(seen) == 3 and all("x" in s and len(s) <= 5 for s in seen)
    timed = stream.withColumn("at", F.timestamp_seconds(F.when(F.col("text") == "x", F.lit(100)).otherwise(F.lit(700))))
    for slide, want in ((None, {(0, "x"): 150}), ("5 minutes", {(0, "x"): 150, (-300, "x"): 150})):
        name = f"windows_{uuid.uuid4().hex}"
        q = live.windowed_counts(timed, "at", "10 minutes", slide).writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True).start()
        q.awaitTermination()
        rows = spark.table(name).selectExpr("unix_seconds(window.start) s", "text", "n").collect()
        assert {(r.s, r.text): r.n for r in rows if r.text == "x"} == want
        assert sum(r.n for r in rows if r.text != "x") == (90 if slide is None else 180)
