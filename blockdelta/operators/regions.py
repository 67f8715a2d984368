"""Merging adjacent written blocks into regions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

WRITTEN = ("dirty", "invalid")
#: Blocks of a range that one task looks at, as the checkpoint driver asks for it.
STRIDE = 1 << 16

_RUN = ["rank", "dataset_id", "part", "island"]


def _islands(states: DataFrame, stride: int | None) -> DataFrame:
    """Written blocks with their range and, within it, their run."""
    todo = states.where(F.col("status").isin(*WRITTEN)).select("rank", "dataset_id", "block_no", "block_len", (F.col("status") == "invalid").cast("bigint").alias("inv"))
    todo = todo.withColumn("part", F.lit(0).cast("bigint") if stride is None else F.expr(f"block_no div {stride}"))
    return todo.withColumn("island", F.col("block_no") - F.row_number().over(Window.partitionBy("rank", "dataset_id", "part").orderBy("block_no")))


def _stitched(islands: DataFrame, stride: int | None) -> DataFrame:
    """Runs within ranges, each with ``run``: the first block of the whole run that it is a part of."""
    runs = islands.groupBy(*_RUN).agg(F.min("block_no").alias("first"), F.max("block_no").alias("last"), F.sum("block_len").alias("n_bytes"), F.count(F.lit(1)).alias("n_blocks"), F.sum("inv").alias("n_invalid"))
    if stride is None:
        return runs.withColumn("run", F.col("first"))
    by_place = Window.partitionBy("rank", "dataset_id").orderBy("first")
    begins = F.when(F.lag("last").over(by_place) + 1 == F.col("first"), F.lit(None)).otherwise(F.col("first"))
    return runs.withColumn("begins", begins).withColumn("run", F.last("begins", ignorenulls=True).over(by_place)).drop("begins")


def merge(states: DataFrame, b: int, stride: int | None = None) -> DataFrame:
    """regions (rank, dataset_id, region_no, start_byte, n_bytes, n_blocks, n_invalid): maximal runs of adjacent dirty or invalid blocks.

    With ``stride`` runs are first found within ranges of that many blocks, in parallel, and then stitched where they
    touch; a dataset of any length is then no single task's work, only its runs are.
    """
    runs = _stitched(_islands(states, stride), stride)
    if stride is not None:
        runs = runs.groupBy("rank", "dataset_id", "run").agg(*[F.sum(c).alias(c) for c in ("n_bytes", "n_blocks", "n_invalid")])
    number = F.row_number().over(Window.partitionBy("rank", "dataset_id").orderBy("run"))
    return runs.select("rank", "dataset_id", number.alias("region_no"), (F.col("run") * b).alias("start_byte"), "n_bytes", "n_blocks", "n_invalid")


def members(states: DataFrame, b: int, stride: int | None = None) -> DataFrame:
    """Keys of all written blocks with the start_byte of the region that holds each."""
    islands = _islands(states, stride)
    runs = _stitched(islands, stride).select(*_RUN, (F.col("run") * b).alias("start_byte"))
    return islands.join(runs, _RUN).select("rank", "dataset_id", "block_no", "start_byte")


def iter_regions(states: DataFrame, b: int) -> Iterator[tuple]:
    """Regions one after the other, as an application would ask for them; for tests and small states."""
    for r in merge(states, b).orderBy("rank", "dataset_id", "region_no").toLocalIterator():
        yield r["rank"], r["dataset_id"], r["start_byte"], r["n_bytes"]
