"""The timed experiments: checkpoint times relative to a full checkpoint, hashing and writing times, and the model held against them."""

from __future__ import annotations

import statistics
import time
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import workloads
from ..functions import costmodel
from ..functions.digests import digest
from ..operators import blocks, gather, regions, tracker
from ..session import fresh_folder, settled
from ..sources.store import BlockStore
from . import engine


def seconds(f) -> float:
    start = time.perf_counter()
    f()
    return time.perf_counter() - start


def _drain(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def write_time(state: DataFrame, repeats: int = 3) -> float:
    """Seconds a block for writing the whole state; the job ends when its last task has."""
    n = max(1, state.count())
    spark = state.sparkSession
    return statistics.median(seconds(lambda: state.write.parquet(fresh_folder(spark, "t_w"))) for _ in range(repeats)) / n


def hash_time(state: DataFrame, algo: str = "md5", repeats: int = 3) -> float:
    """Seconds a block for hashing: the time of a pass with the digest less that of a pass without."""
    n = max(1, state.count())
    bare = statistics.median(seconds(lambda: _drain(state.select(F.octet_length("payload")))) for _ in range(repeats))
    hashed = statistics.median(seconds(lambda: _drain(state.select(digest(F.col("payload"), algo)))) for _ in range(repeats))
    return max(1e-12, hashed - bare) / n


def hash_throughput(state: DataFrame, algo: str) -> float:
    """Bytes hashed a second."""
    n, size = state.count(), state.agg(F.sum("block_len")).first()[0] or 0
    return size / max(1e-9, hash_time(state, algo) * n)


def threshold(spark: SparkSession, sf: str, sizes: tuple[int, ...] = (2048, 8192, 32768), slots: tuple[int, ...] = (2, 4)) -> Iterator[dict]:
    """Break-even shares by block size with two widths of the writing job, from times measured here."""
    cells = settled(workloads.plasma(spark, sf, 1, "B", "one"), "state")
    for b in sizes:
        state = settled(blocks.cut(cells, b), "blocks")
        for algo in ("md5", "crc32"):
            t_h = hash_time(state, algo)
            for n in slots:
                t_w = write_time(state.coalesce(n))
                yield {"experiment": "threshold", "b": b, "slots": n, "algo": algo, "rho": t_h / t_w, "dirty_share": costmodel.break_even(t_h / t_w)}


def shares(before: DataFrame, after: DataFrame, b: int, algo: str = "md5") -> dict[str, float]:
    """The parts of an update's time that go into comparing and into writing."""
    ledger = settled(tracker.create_ledger(blocks.cut(before, b), algo), "ledger")
    state = settled(blocks.cut(after, b), "blocks")
    t_hash = seconds(lambda: settled(tracker.classify(state, ledger, algo).select(*blocks.KEYS, "status"), "states"))
    states = settled(tracker.classify(state, ledger, algo).select(*blocks.KEYS, "status"), "states")
    todo = state.join(states.where(F.col("status").isin(*regions.WRITTEN)), blocks.KEYS, "left_semi")
    t_write = seconds(lambda: todo.write.parquet(fresh_folder(state.sparkSession, "shares")))
    return {"hash_share": t_hash / (t_hash + t_write), "write_share": t_write / (t_hash + t_write)}


def relative_time(states: list[DataFrame], b: int, mode: str, algo: str = "md5", force_dirty: bool = False, repeats: int = 3) -> dict[str, float]:
    """Change of an update's time against a full checkpoint of the same state, with the spread over repeats.

    ``states`` are the state before and after the update; both are written down first, so that making them is no part of the times.
    """
    spark, (before, after) = states[0].sparkSession, [settled(s, "state") for s in states]
    changes, share = [], 0.0
    for _ in range(repeats):
        full = BlockStore(spark, fresh_folder(spark, "bench"), b, algo)
        engine.checkpoint(before, full)
        t0 = seconds(lambda: engine.checkpoint(after, full, "full"))
        store = BlockStore(spark, fresh_folder(spark, "bench"), b, algo)
        engine.checkpoint(before, store)
        box = []
        t = seconds(lambda: box.append(engine.checkpoint(after, store, mode, force_dirty=force_dirty)))
        changes.append(t / t0 - 1)
        share = (box[0].dirty + box[0].invalid) / max(1, box[0].total_blocks)
    return {"dirty_share": share, "change": statistics.mean(changes), "spread": statistics.pstdev(changes)}


def scenarios(spark: SparkSession, sf: str) -> dict[str, list[DataFrame]]:
    return {
        "blast wave": [workloads.wave(spark, sf, t) for t in ("2024-01-10 00:00:00", "2024-01-11 00:00:00")],
        "plasma one-buffer A": [workloads.plasma(spark, sf, s, "A", "one") for s in (0, 1)],
        "plasma one-buffer B": [workloads.plasma(spark, sf, s, "B", "one") for s in (0, 1)],
        "heat grid": [workloads.heat(spark, sf, t) for t in (1, 5)],
    }


def everything(spark: SparkSession, sf: str) -> Iterator[dict]:
    b = 1024
    for name, states in scenarios(spark, sf).items():
        for algo in ("md5", "crc32"):
            for mode in ("copy_on_write", "buffered"):
                yield {"experiment": "relative time", "workload": name, "algo": algo, "mode": mode, **relative_time(states, b, mode, algo, repeats=2)}
        yield {"experiment": "relative time", "workload": name, "algo": "md5", "mode": "all dirty", **relative_time(states, b, "copy_on_write", force_dirty=True, repeats=2)}
        state = settled(blocks.cut(settled(states[1], "state"), b), "blocks")
        t_w, t_h = write_time(state), hash_time(state)
        measured = engine_share(states, b)
        yield {"experiment": "model", "workload": name, "t_write": t_w, "t_hash": t_h, "rho": t_h / t_w, "break_even": costmodel.break_even(t_h / t_w), "predicted": costmodel.speedup(measured, t_h / t_w)}
        yield {"experiment": "shares", "workload": name, **shares(*states, b)}
        for algo in ("md5", "crc32"):
            yield {"experiment": "hash throughput", "workload": name, "algo": algo, "mb_per_second": hash_throughput(state, algo) / 1e6}
    yield from threshold(spark, sf)
    wave = scenarios(spark, sf)["plasma one-buffer B"]
    for size in (128, 512, 2048, 8192, 32768):
        states = tracker.classify(blocks.cut(wave[1], size), tracker.create_ledger(blocks.cut(wave[0], size)))
        merged = settled(regions.merge(states, size), "regions")
        n, total = merged.count(), merged.agg(F.sum("n_bytes")).first()[0] or 0
        packed = gather.units(gather.pack(merged, 64 << 10)).count()
        yield {"experiment": "block size", "b": size, "regions": n, "written_bytes": total, "units": packed}


def engine_share(states: list[DataFrame], b: int) -> float:
    found = tracker.classify(blocks.cut(states[1], b), tracker.create_ledger(blocks.cut(states[0], b)))
    return found.agg(F.avg((F.col("status") != tracker.CLEAN).cast("int"))).first()[0] or 0.0
