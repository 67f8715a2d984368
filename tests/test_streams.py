"""Streams whose files are written by many tasks at once."""

import pytest
from pyspark.sql import functions as F

from blockdelta import catalogue
from blockdelta.session import table
from blockdelta.streaming import epochs


@pytest.fixture
def many_tasks(spark):
    """Days go to tasks of their own, as they do once they are large."""
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    yield
    spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


def test_files_arrive_day_by_day(spark, sf_dir, many_tasks):
    where = spark._jvm.org.apache.hadoop.fs.Path(epochs.daily_files(spark, sf_dir))
    fs = where.getFileSystem(spark._jsc.hadoopConfiguration())
    files = [f for day in fs.listStatus(where) if day.isDirectory() for f in fs.listStatus(day.getPath())]
    days = [f.getPath().getParent().getName() for f in sorted(files, key=lambda f: f.getModificationTime())]
    assert len(days) > 20 and days == sorted(days)


def test_late_counts_every_event_once(spark, sf_dir, many_tasks):
    assert catalogue.QUERIES["stream_late"](spark, sf_dir).first()["n"] == table(spark, sf_dir, "events").count()


def test_every_update_is_acknowledged(spark, sf_dir, many_tasks):
    found = catalogue.QUERIES["stream_acknowledged"](spark, sf_dir)
    assert found.count() == table(spark, sf_dir, "events").where("event_id % 2 = 0").count()


def counted_late(spark, folder, events):
    events.write.parquet(f"{folder}/events.parquet")
    return catalogue.QUERIES["stream_late"](spark, str(folder)).first()["n"]


def test_late_counts_every_event_of_many_years_and_without_a_time(spark, sf_dir, tmp_path):
    """The closing event is behind the last days if it only follows the first one."""
    events = table(spark, sf_dir, "events").where("event_id < 60")
    moved = events.withColumn("ts", F.expr("CASE WHEN event_id % 10 > 0 THEN ts + make_interval(event_id % 3) END"))
    assert counted_late(spark, tmp_path, moved) == 60


def test_late_counts_the_events_of_a_single_day_once(spark, sf_dir, tmp_path):
    """No later day closes the first one's window before it comes again."""
    events = table(spark, sf_dir, "events").where("ts < '2024-01-02'")
    assert counted_late(spark, tmp_path, events) == events.count()


def test_late_counts_no_events(spark, sf_dir, tmp_path):
    assert counted_late(spark, tmp_path, table(spark, sf_dir, "events").where("false")) == 0


def test_files_arrive_day_by_day_on_stores_with_times_of_their_own(spark, sf_dir, tmp_path, monkeypatch):
    """Times by the store: here the later days were written first."""
    events = table(spark, sf_dir, "events").where("ts < '2024-01-04'")
    events.write.parquet(f"{tmp_path}/events.parquet")
    monkeypatch.setattr(epochs, "_set_time", lambda fs, file, ms: fs.setTimes(file, 2_000_000_000_000 - ms, -1))
    path = epochs.daily_files(spark, str(tmp_path))
    fs, days = epochs._days(spark, path)
    times = [f.getModificationTime() for day in days for f in fs.listStatus(day) if f.getPath().getName().startswith("part-")]
    assert len(times) == 3 and times == sorted(set(times))
    assert spark.read.parquet(path).count() == events.count()
