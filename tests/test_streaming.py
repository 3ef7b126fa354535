"""Streams in several micro-batches: late rows, running centres, made-up events; the layout by feature."""

import json
import os
import time

import pytest
from pyspark.sql import functions as F

from colsketch.operators import adaptive as K
from colsketch.sources import formats
from colsketch.sources import matrix as M
from colsketch.streaming import sketch_stream as S

SCHEMA = "event_id long, user_id long, ts timestamp, props string"


@pytest.fixture
def replay(spark, tmp_path):
    """Writes each list of rows as a file of its own, in order, and reads them one file at a time."""

    def make(*files):
        home = tmp_path / "in"
        home.mkdir()
        for k, rows in enumerate(files):
            df = spark.createDataFrame(rows, "event_id long, user_id long, ts string, props string").withColumn("ts", F.col("ts").cast("timestamp"))
            df.coalesce(1).write.parquet(str(tmp_path / f"file{k}"))
            (part,) = (tmp_path / f"file{k}").glob("*.parquet")
            part.rename(home / f"{k}.parquet")
            os.utime(home / f"{k}.parquet", (1_700_000_000 + k, 1_700_000_000 + k))
        return S.read_events(spark, str(home), SCHEMA, 1)

    return make


def event(i, ts, user=1, k=3):
    return i, user, f"2024-01-{ts}", json.dumps({"k": k})


def test_late_rows_are_dropped_and_closed_windows_written_once(replay):
    stream = replay(
        [event(1, "01 10:00:00"), event(2, "01 11:30:00")],
        [event(3, "01 10:30:00"), event(4, "01 20:00:00")],  # in time, as the watermark is at 9:30
        [event(7, "01 20:30:00")],  # a micro-batch drops what is late by the watermark that the one before it used to close windows
        [event(5, "01 10:45:00")],  # its window closed at 18:00
        [event(6, "03 00:00:00")],
    )
    got = S.drain(S.windowed_sketch(S.increments(stream, 4, 1), "1 hour"), "append")
    assert sorted((r.h, abs(r.value)) for r in got.select(F.date_format("w.start", "d HH").alias("h"), "value").collect()) == [("1 10", 2), ("1 11", 1), ("1 20", 2)]


def test_repeated_events_count_once(replay):
    stream = replay([event(1, "01 10:00:00"), event(1, "01 10:00:00")], [event(1, "01 10:00:00"), event(2, "01 10:01:00")])
    assert sorted(r.event_id for r in S.drain(S.deduplicated(S.increments(stream, 4, 1)), "append").collect()) == [1, 2]


def test_complete_mode_gives_the_last_result(replay):
    stream = replay([event(1, "01 10:00:00")], [event(2, "01 10:00:00")], [event(3, "01 10:00:00", user=2)])
    assert sorted((r.user_id, abs(r.value)) for r in S.drain(S.running_sketch(S.increments(stream, 4, 1))).collect()) == [(1, 2), (2, 1)]


def test_no_files_give_no_rows(replay, tmp_path):
    got = S.drain(S.running_sketch(S.increments(replay(), 4, 1)))
    assert got.columns == ["user_id", "bucket", "value"] and got.count() == 0


def test_centres_are_means_of_all_that_came(replay):
    stream = replay([event(1, "01 10:00:00"), event(2, "01 10:00:00", user=2)], [event(3, "01 10:00:00")], [event(9, "02 10:00:00", user=7)])
    rows = stream.select("user_id", "ts", F.lit(0).alias("bucket"), F.when(F.col("event_id") < 9, F.col("event_id")).alias("value"))
    got = S.drain(S.online_centres(rows), "update").groupBy("user_id").agg(F.max(F.struct("seen", "centre")).alias("x"))
    assert {r.user_id: tuple(r.x) for r in got.collect()} == {1: (2, 2.0), 2: (1, 2.0), 7: (0, 0.0)}


def test_generated_events(spark, tmp_path):
    made, seen = S.generated_events(spark, 50, users=5, features=7), []
    rows = S.increments(made, 4, 1).select("event_id", "user_id", "delta")
    q = rows.writeStream.foreachBatch(lambda batch, number: seen.append([r.event_id for r in batch.collect()])).option("checkpointLocation", str(tmp_path / "c")).start()
    until = time.time() + 30
    while not seen and time.time() < until:
        time.sleep(0.2)
    q.stop()
    assert sorted(seen[0]) == list(range(50))


def _matrix(spark):
    cells = [(i, j, float(i + j + 1)) for i in range(30) for j in range(40) if (i * j) % 3 != 1]
    return M.FeatureMatrix(spark.createDataFrame(cells, "row_id long, feature_id long, value double"), spark.range(30).withColumnRenamed("id", "row_id"), 40)


def test_learned_maps_are_sent_or_joined(spark):
    fm = _matrix(spark)
    model = K.learn_full(fm, 4, 1, seed=1)
    rows = fm.entries.select(F.col("row_id").alias("user_id"), "feature_id")
    sent, joined = S.learned_increments(rows, model), S.learned_increments(rows, model, max_broadcast=0)
    key = lambda df: sorted((r.user_id, r.feature_id, r.bucket, round(r.delta, 9)) for r in df.collect())
    assert key(sent) == key(joined) and len(key(sent)) == fm.entries.count()


def test_only_wanted_folders_are_read(spark, tmp_path):
    fm, path = _matrix(spark), str(tmp_path / "by_feature")
    formats.write_by_feature(fm, path, 16, 2)
    wanted = spark.createDataFrame([(3,), (17,), (3,), (99,), (None,)], "feature_id long")
    got = formats.read_features(spark, path, wanted, 16)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, fm.entries.where("feature_id in (3, 17)").collect()))
    assert "PartitionFilters: [part" in got._jdf.queryExecution().toString().replace("isnotnull(part", "part").replace("[part#", "[part")
    assert formats.read_features(spark, path, wanted.where("feature_id is null"), 16).count() == 0
