"""Late rows, duplicates and state over files that arrive one after another."""

import datetime as dt

import pytest

from vpatterns.streaming import events as E

T0 = dt.datetime(2024, 1, 1)


@pytest.fixture
def drops(spark, tmp_path):
    def write(*batches):
        for i, rows in enumerate(batches):
            df = spark.createDataFrame([(k, T0 + dt.timedelta(hours=h), u, e) for k, h, u, e in rows], "event_id long, ts timestamp, user_id long, event_type string")
            df.coalesce(1).write.mode("append").parquet(f"file://{tmp_path}/b{i}")
        return spark.readStream.schema("event_id long, ts timestamp, user_id long, event_type string").option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(f"file://{tmp_path}")

    return write


def test_late_rows_are_dropped_in_append_mode(spark, tmp_path):
    schema = "event_id long, ts timestamp, user_id long, event_type string"
    (tmp_path / "in").mkdir()
    stream = spark.readStream.schema(schema).option("recursiveFileLookup", "true").parquet(f"file://{tmp_path}/in")
    q = E.tumbling(stream).writeStream.outputMode("append").format("memory").queryName("late_rows").start()
    for k, hour in enumerate((0, 1, 100, 2, 300)):
        rows = spark.createDataFrame([(k, T0 + dt.timedelta(hours=hour), 1, "a")], schema)
        rows.write.parquet(f"file://{tmp_path}/in/{k}")
        q.processAllAvailable()
    got = {r["start"]: r["n"] for r in spark.table("late_rows").collect()}
    q.stop()
    assert got[T0] == 2  # the row of hour 2 came after hour 100


def test_duplicates_within_the_watermark(drops):
    stream = drops([(1, 0, 1, "a")], [(1, 0, 1, "a"), (2, 1, 1, "a")])
    assert E.finished(E.deduplicated(stream), "append").count() == 2


def test_state_grows_batch_by_batch(drops):
    stream = drops([(1, 0, 1, "a")], [(2, 1, 1, "b"), (3, 1, 2, "b")])
    got = [(r["user_id"], r["mask"]) for r in E.finished(E.level_masks(stream, ["a", "b"]), "update").collect()]
    assert (1, 1) in got and (1, 3) in got and (2, 2) in got


def test_sessions(drops):
    stream = drops([(1, 0, 1, "a"), (2, 1, 1, "a"), (3, 50, 1, "a")])
    assert sorted(r["n"] for r in E.finished(E.sessions(stream)).collect()) == [1, 2]


def test_co_occurrence_counts_a_day_once(drops):
    stream = drops([(1, 0, 1, "a"), (2, 1, 1, "b")], [(3, 2, 1, "a"), (4, 30, 1, "b")])
    assert E.CoOccurrence().run(stream).count() == 3
