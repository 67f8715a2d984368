"""What is dirty: blocks against the ledger of committed digests."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.digests import digest
from .blocks import KEYS

CLEAN, DIRTY, INVALID, RETIRED = "clean", "dirty", "invalid", "retired"


def hashed(blocks: DataFrame, algo: str = "md5") -> DataFrame:
    """Keys, length and digest; payloads stop here, so a join moves a few dozen bytes a block."""
    return blocks.select(*KEYS, "block_len", digest(F.col("payload"), algo).alias("digest"))


def create_ledger(blocks: DataFrame, algo: str = "md5", version: int = 0) -> DataFrame:
    """Digests of all blocks as (rank, dataset_id, block_no, block_len, digest, algo, version)."""
    return hashed(blocks, algo).select("*", F.lit(algo).alias("algo"), F.lit(version).alias("version"))


def classify(blocks: DataFrame, ledger: DataFrame, algo: str = "md5", force_dirty: bool = False, hint: str | None = None) -> DataFrame:
    """states (keys, block_len, status, digest).

    invalid: no image, or one of another length (the last block of a dataset that grew or shrank); it counts as
    unhashed. dirty: the digests differ; clean: they are equal; retired: an image of a block that no longer exists.
    ``digest`` is null for retired blocks. With ``force_dirty`` every block with an image is dirty.
    """
    return compare(hashed(blocks, algo), ledger, force_dirty, hint)


def compare(new: DataFrame, ledger: DataFrame, force_dirty: bool = False, hint: str | None = None) -> DataFrame:
    """``classify`` for blocks whose digests are there already."""
    if hint:
        new = new.hint(hint)
    old = ledger.select(*KEYS, F.col("block_len").alias("old_len"), F.col("digest").alias("old_digest"))
    both = new.join(old, KEYS, "full_outer")
    same = F.lit(False) if force_dirty else F.col("digest").eqNullSafe(F.col("old_digest"))
    status = (
        F.when(F.col("block_len").isNull(), RETIRED)
        .when(F.col("old_len").isNull() | (F.col("old_len") != F.col("block_len")), INVALID)
        .when(same, CLEAN)
        .otherwise(DIRTY)
    )
    return both.select(*KEYS, F.coalesce("block_len", "old_len").alias("block_len"), status.alias("status"), "digest")


def compare_pairs(pairs: DataFrame, algo: str = "md5") -> DataFrame:
    """states (b, variant, keys, block_len, status) of blocks that hold both versions, as ``blocks.cut_runs`` gives them: their digests meet in the row, so
    no ledger moves. Both versions have the same cells, so nothing is invalid or retired."""
    same = F.coalesce("whole", digest(F.col("old"), algo) == digest(F.col("new"), algo))
    return pairs.select("b", "variant", *KEYS, "block_len", F.when(same, CLEAN).otherwise(DIRTY).alias("status"))


def invalid_blocks(keys: DataFrame, ledger: DataFrame) -> DataFrame:
    """Blocks without an image, found from keys and lengths alone: nothing is hashed."""
    return keys.select(*KEYS, "block_len").join(ledger.select(*KEYS, "block_len"), [*KEYS, "block_len"], "left_anti")


def advance(ledger: DataFrame, states: DataFrame, algo: str, version: int) -> DataFrame:
    """The ledger after a successful update: clean rows stay as they are, written blocks take their new digests, retired ones go."""
    clean = states.where(F.col("status") == CLEAN).select(*KEYS)
    fresh = states.where(F.col("status").isin(DIRTY, INVALID)).select(*KEYS, "block_len", "digest", F.lit(algo).alias("algo"), F.lit(version).alias("version"))
    return ledger.join(clean, KEYS, "left_semi").unionByName(fresh)


def advance_to_files(ledger: DataFrame, states: DataFrame, stored: DataFrame | None, algo: str, version: int) -> DataFrame:
    """The ledger after an update, with the digests of what its files really hold: a source that has moved on since the comparison cannot
    certify bytes that are not there. ``stored`` are the blocks read back; rows of other blocks and of those that were written
    again as they were stay, those of retired ones go."""
    gone = states.where(F.col("status") == RETIRED).select(*KEYS)
    if stored is None:
        return ledger.join(gone, KEYS, "left_anti")
    old = ledger.select(*KEYS, "block_len", F.col("digest").alias("old_digest"))
    new = hashed(stored, algo).join(old, [*KEYS, "block_len"], "left").where(~F.col("digest").eqNullSafe(F.col("old_digest"))).drop("old_digest")
    fresh = new.select("*", F.lit(algo).alias("algo"), F.lit(version).alias("version"))
    return ledger.join(gone.unionByName(fresh.select(*KEYS)), KEYS, "left_anti").unionByName(fresh)


def advance_early(ledger: DataFrame, states: DataFrame, algo: str, version: int) -> DataFrame:
    """What must not be done: committing digests at detection, before the write. Kept to show how a failed write then loses changes."""
    return advance(ledger, states, algo, version)


def check_ledger(ledger: DataFrame, algo: str, b: int) -> None:
    """Raises if the ledger was made with another digest or block size; such a ledger must never be compared with."""
    odd = ledger.where((F.col("algo") != algo) | (F.col("block_len") > b)).limit(1).count()
    if odd:
        raise ValueError(f"the ledger is not of {algo} over blocks of {b} bytes; a full checkpoint is needed")
