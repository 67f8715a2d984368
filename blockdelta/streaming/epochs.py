"""Streaming forms: a micro-batch is a checkpoint epoch."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.encode import cents
from ..session import fresh_folder, settled, table

EVENT_SCHEMA = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def daily_files(spark: SparkSession, sf_dir: str) -> str:
    """The events as files by day, as they would arrive."""
    path = fresh_folder(spark, "events-by-day")
    table(spark, sf_dir, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd")).repartition("day").write.partitionBy("day").parquet(path)
    return path if _in_turn(spark, path) else _one_by_one(spark, path)


def _days(spark: SparkSession, path: str) -> tuple:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = where.getFileSystem(spark._jsc.hadoopConfiguration())
    return fs, sorted((f.getPath() for f in fs.listStatus(where) if f.isDirectory()), key=lambda f: f.getName())


def _set_time(fs, file, ms: int) -> None:
    fs.setTimes(file, ms, -1)


def _in_turn(spark: SparkSession, path: str) -> bool:
    """File times in the order of the days, one second apart and in the past: a stream takes files by time, and tasks that write at once finish
    in any order. Later days first would move the watermark past the earlier ones, whose events were then dropped. False if the store keeps its own times."""
    fs, days = _days(spark, path)
    now = int(time.time() * 1000)
    for k, day in enumerate(days):
        for f in fs.listStatus(day):
            _set_time(fs, f.getPath(), now - (len(days) - k) * 1000)
    times = [[f.getModificationTime() for f in fs.listStatus(day)] for day in days]
    return all(max(a) < min(b) for a, b in zip(times, times[1:]))


def _one_by_one(spark: SparkSession, path: str) -> str:
    """For stores that keep their own times: the days are written again one after another, each in a later second."""
    out = fresh_folder(spark, "events-one-by-one")
    for day in _days(spark, path)[1]:
        spark.read.parquet(day.toString()).write.parquet(f"{out}/{day.getName()}")
        time.sleep(1.1)
    return out


def read_events(spark: SparkSession, path: str, files_per_epoch: int = 4) -> DataFrame:
    """The stream of events; watermarks need an instant, so the time becomes one (UTC session)."""
    stream = spark.readStream.schema(EVENT_SCHEMA).option("maxFilesPerTrigger", files_per_epoch).option("recursiveFileLookup", "true").parquet(path)
    return stream.withColumn("at", F.col("ts").cast("timestamp"))


def drained(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Runs a streaming query until its input is used up and gives what its sink holds. Its progress is kept in the shared folder."""
    spark, out = stream.sparkSession, fresh_folder(stream.sparkSession, f"stream-{name}")
    writer = stream.writeStream.option("checkpointLocation", f"{out}-progress").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", out).outputMode("append").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(out)

    def keep(batch: DataFrame, epoch: int) -> None:
        # Idempotent: a repeated epoch replaces its own folder.
        batch.write.mode("overwrite").parquet(f"{out}/epoch={epoch}")

    writer.foreachBatch(keep).outputMode(mode).start().awaitTermination()
    return spark.read.option("basePath", out).schema(f"{_ddl(stream)}, epoch bigint").parquet(out)


def drained_with_late(stream: DataFrame, source: str, day: str) -> DataFrame:
    """Drains an append query, closes the windows still open by an event far ahead of the last one, then delivers the files of one day again
    and drains it on from its progress.

    So every window is in the result and the day is behind the watermark, over however many or few days the events go.
    """
    spark, out = stream.sparkSession, fresh_folder(stream.sparkSession, "stream-late")

    def run() -> None:
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{out}-progress").outputMode("append").trigger(availableNow=True).start().awaitTermination()

    run()
    last = spark.read.parquet(source).drop("day").orderBy(F.desc_nulls_last("ts")).limit(1)
    last.withColumn("ts", F.col("ts") + F.expr("INTERVAL 400 DAY")).write.parquet(f"{source}/ahead")
    run()
    spark.read.parquet(f"{source}/day={day}").write.parquet(f"{source}/again")
    run()
    return spark.read.schema(stream.schema).parquet(out)


def _ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema)


def changed_cells_by_day(events: DataFrame) -> DataFrame:
    """Tumbling windows: cells that change in each daily interval."""
    return events.groupBy(F.window("at", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("cells")).select(F.col("w.start").cast("timestamp_ntz").alias("day"), "cells")


def live_cells(events: DataFrame, days: int = 7) -> DataFrame:
    """Sliding windows: the size of a dataset that keeps its last days only."""
    return events.groupBy(F.window("at", f"{days} days", "1 day").alias("w")).agg((F.count(F.lit(1)) * 8).alias("bytes")).select(F.col("w.end").cast("timestamp_ntz").alias("until"), "bytes")


def bursts(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Session windows: datasets that appear with a user's burst of events and retire after it."""
    return events.groupBy("user_id", F.session_window("at", gap).alias("w")).agg((F.count(F.lit(1)) * 8).alias("bytes")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("born"), "bytes")


def once(events: DataFrame, delay: str = "1 day") -> DataFrame:
    """Events without replays, so that these dirty nothing again."""
    return events.withWatermark("at", delay).dropDuplicatesWithinWatermark(["event_id"])


def acknowledged(events: DataFrame, acks: DataFrame, within: str = "1 hour") -> DataFrame:
    """Updates with their acknowledgement, which follows within an interval; both sides are bounded by watermarks."""
    left = events.withWatermark("at", "1 day").select("event_id", "at", "value")
    right = acks.withWatermark("acked", "1 day").select(F.col("event_id").alias("ack_id"), "acked")
    soon = (F.col("event_id") == F.col("ack_id")) & (F.col("acked") >= F.col("at")) & (F.col("acked") <= F.col("at") + F.expr(f"INTERVAL {within}"))
    return left.join(right, soon).select("event_id", F.unix_seconds(F.col("acked")).alias("acked_s"))


def epoch_shares(spark: SparkSession, sf_dir: str, b: int = 512, ranks: int = 16, files_per_epoch: int = 4) -> DataFrame:
    """Each epoch merges its events into the state, compares blocks with the ledger of the epoch before, and only then lets the new ledger take its place.

    Gives (epoch, n_dirty, n_invalid) and is restartable: state and ledger are folders named by epoch.
    """
    from ..operators import blocks, tracker

    folder = fresh_folder(spark, "epochs")
    n = max(1, table(spark, sf_dir, "events").count())
    stream = read_events(spark, daily_files(spark, sf_dir), files_per_epoch)

    def epoch(batch: DataFrame, k: int) -> None:
        rank = F.expr(f"event_id * {ranks} div {n}")
        first = F.expr(f"((event_id * {ranks} div {n}) * {n} + {ranks - 1}) div {ranks}")
        new = batch.select(rank.cast("int").alias("rank"), F.lit("value").alias("dataset_id"), (F.col("event_id") - first).alias("pos"), cents(F.col("value")).alias("cell"))
        own = batch.sparkSession
        old = own.read.parquet(f"{folder}/state-{k - 1}") if k else None
        state = new if old is None else old.join(new.select("rank", "dataset_id", "pos"), ["rank", "dataset_id", "pos"], "left_anti").unionByName(new)
        state.write.mode("overwrite").parquet(f"{folder}/state-{k}")
        cut = blocks.cut(own.read.parquet(f"{folder}/state-{k}"), b)
        ledger = own.read.parquet(f"{folder}/ledger-{k - 1}") if k else tracker.create_ledger(cut, version=0).limit(0)
        states = settled(tracker.classify(cut, ledger), "epoch-states")
        states.select(F.lit(k).alias("epoch"), "status").write.mode("overwrite").parquet(f"{folder}/shares/epoch_no={k}")
        tracker.advance(ledger, states, "md5", k).write.mode("overwrite").parquet(f"{folder}/ledger-{k}")

    stream.writeStream.foreachBatch(epoch).option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True).start().awaitTermination()
    shares = spark.read.parquet(f"{folder}/shares")
    return shares.groupBy("epoch").agg(F.count_if(F.col("status") == "dirty").alias("n_dirty"), F.count_if(F.col("status") == "invalid").alias("n_invalid"), F.count(F.lit(1)).alias("n_blocks"))


def keyed_digests(events: DataFrame) -> DataFrame:
    """Arbitrary state: for each user the digest of the values of its last epoch and the number of its events so far, kept between epochs.

    Emits each user that an epoch has events of, with whether its digest is another than the one kept: values that only repeat are
    clean. A digest takes the place of the old one together with the epoch's own commit, so a failed epoch changes nothing.
    """
    import hashlib

    import pandas as pd

    def update(key, parts, state):
        (before, seen) = state.get if state.exists else (None, 0)
        rows = pd.concat(list(parts)).sort_values(["event_id", "cell"])
        digest = hashlib.md5(rows["cell"].to_numpy("<i8").tobytes()).hexdigest()
        state.update((digest, seen + len(rows)))
        yield pd.DataFrame({"user_id": [key[0]], "seen": [seen + len(rows)], "changed": [digest != before]})

    grouped = events.select("user_id", "event_id", cents(F.col("value")).alias("cell")).groupBy("user_id")
    return grouped.applyInPandasWithState(update, "user_id bigint, seen bigint, changed boolean", "digest string, seen bigint", "append", "NoTimeout")
