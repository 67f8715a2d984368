"""What differential checkpointing is held against."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators import blocks, tracker
from ..operators.protect import catalogue
from ..sources.store import BlockStore
from .engine import Outcome, checkpoint


def full(cells: DataFrame, store: BlockStore) -> Outcome:
    """The whole state each time, as with the feature off."""
    return checkpoint(cells, store, "full")


def touched(write_log: DataFrame, page: int = 4096) -> DataFrame:
    """Blocks that any store has touched, whether or not a value changed."""
    return write_log.select("rank", "dataset_id", F.expr(f"pos * 8 div {page}").alias("block_no")).distinct()


def address_space(cells: DataFrame, order: dict[str, str] | None = None, descending: bool = False) -> DataFrame:
    """Cells by their address in each rank's memory: datasets one behind the other, by name or in reverse."""
    by = F.desc("dataset_id") if descending else F.asc("dataset_id")
    sizes = catalogue(cells)
    start = F.sum("size_bytes").over(Window.partitionBy("rank").orderBy(by).rowsBetween(Window.unboundedPreceding, 0)) - F.col("size_bytes")
    placed = sizes.select("rank", "dataset_id", (start / 8).cast("bigint").alias("start"))
    return cells.join(placed, ["rank", "dataset_id"]).select("rank", F.lit("memory").alias("dataset_id"), (F.col("start") + F.col("pos")).alias("pos"), "cell")


def page_hash(before: DataFrame, after: DataFrame, page: int = 4096, algo: str = "md5") -> DataFrame:
    """states of memory pages by digest; ``before`` and ``after`` are address spaces. Datasets that move look changed."""
    return tracker.classify(blocks.cut(after, page), tracker.create_ledger(blocks.cut(before, page), algo), algo)


def touched_then_hash(write_log: DataFrame, before: DataFrame, after: DataFrame, page: int = 4096, algo: str = "md5") -> DataFrame:
    """states of touched pages only; what no store has touched is clean without hashing."""
    pages = touched(write_log, page)
    keys = ["rank", "dataset_id", "block_no"]
    old, new = (blocks.cut(x, page).join(pages, keys, "left_semi") for x in (before, after))
    return tracker.classify(new, tracker.create_ledger(old, algo), algo)


def delta_chain(cells: DataFrame, store: BlockStore) -> Outcome:
    """A file of changes for each update; restart merges them all."""
    return checkpoint(cells, store, "delta_chain")


def everything_dirty(cells: DataFrame, store: BlockStore) -> Outcome:
    """The feature on, with no block clean: the cost of hashing in full."""
    return checkpoint(cells, store, force_dirty=True)


def early_commit_loses(before: DataFrame, after: DataFrame, b: int, algo: str = "md5") -> DataFrame:
    """Blocks that a checkpoint would miss if digests had been committed at detection and the write had then failed:
    they differ from the last image, but the ledger already knows their new digests."""
    image = tracker.create_ledger(blocks.cut(before, b), algo)
    now = blocks.cut(after, b)
    states = tracker.classify(now, image, algo)
    early = tracker.advance_early(image, states, algo, 2)
    said = tracker.classify(now, early, algo).where(F.col("status") == tracker.CLEAN)
    return states.where(F.col("status").isin(tracker.DIRTY, tracker.INVALID)).select(*blocks.KEYS).join(said.select(*blocks.KEYS), blocks.KEYS, "left_semi")
