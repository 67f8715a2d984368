"""The two-parameter cost model. All functions take numbers or Columns; t_w and t_h are seconds per block to write and to hash."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def saving(total, dirty, t_write):
    """Seconds of writing that clean blocks spare."""
    return (total - dirty) * t_write


def overhead(total, dirty, t_hash):
    """Seconds of hashing: all blocks to compare, the dirty ones again to commit."""
    return (total + dirty) * t_hash


def hash_count(valid, dirty, invalid):
    """Hashes really computed: blocks without an image are not compared, only committed."""
    return valid + dirty + invalid


def tau(dirty_share, t_write, t_hash):
    """Net seconds a block: below 0 is a gain."""
    return (t_hash - t_write) + dirty_share * (t_write + t_hash)


def worst_case(t_write, t_hash):
    """Relative loss when everything is dirty."""
    return 2 * t_hash / t_write


def break_even(rho, keep_pending: bool = False, kind: str = "dirty"):
    """The dirty share (or, with kind='clean', the clean one) at which nothing is gained; None or NULL where hashing costs as much as writing."""
    dirty = 1 - rho if keep_pending else (1 - rho) / (1 + rho)
    share = dirty if kind == "dirty" else 1 - dirty
    if isinstance(rho, Column):
        return F.when(rho < 1, share)
    return share if rho < 1 else None


def speedup(dirty_share, rho, keep_pending: bool = False):
    """Predicted relative change of a checkpoint's time; negative is faster."""
    return rho - 1 + dirty_share * (1 if keep_pending else rho + 1)


def speedup_bounds(mean_share, most_share, rho):
    """From the mean dirty share and that of the dirtiest rank: (optimistic, pessimistic)."""
    return speedup(mean_share, rho), speedup(most_share, rho)


def ledger_bytes(state_bytes, b, digest_bytes):
    return state_bytes / b * digest_bytes


def scaling(timings: DataFrame) -> DataFrame:
    """Break-even share by number of ranks, from rows (ranks, t_write, t_hash)."""
    rho = F.col("t_hash") / F.col("t_write")
    return timings.select("ranks", rho.alias("rho"), break_even(rho).alias("eta"))
