"""One differential checkpoint: classify, merge, write, keep the ledger, commit."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import blocks as cutting
from ..operators import regions, tracker
from ..session import staging
from ..sources.store import BlockStore, StoreError

#: Beyond this part of touched buckets ``auto`` appends written blocks instead of writing their buckets anew.
SPREAD = 0.5


@dataclass(frozen=True)
class Outcome:
    version: int
    mode: str
    total_blocks: int
    dirty: int
    invalid: int
    retired: int
    state_bytes: int
    written_bytes: int
    physical_bytes: int
    n_regions: int
    compared_hashes: int
    committed_hashes: int

    @property
    def write_rate(self) -> float:
        """Changed bytes over all bytes."""
        return self.written_bytes / self.state_bytes if self.state_bytes else 0.0

    @property
    def physical_rate(self) -> float:
        """Bytes that went into files over all bytes; above the write rate where buckets are written anew."""
        return self.physical_bytes / self.state_bytes if self.state_bytes else 0.0


def sampled_share(cells: DataFrame, store: BlockStore, modulus: int = 64) -> float | None:
    """The part of written blocks in a sample fixed by keys, against the latest ledger; only the sample is cut and hashed. None without a ledger."""
    latest = store.latest()
    if latest is None:
        return None

    def some(df: DataFrame, block: str) -> DataFrame:
        return df.where(F.expr(f"pmod(({block}) * 2654435761 + rank * 40503, {modulus}) = 0"))

    states = tracker.classify(cutting.cut(some(cells, f"pos * 8 div {store.b}"), store.b), some(store.ledger(latest), "block_no"), store.algo)
    return states.agg(F.avg((F.col("status") != tracker.CLEAN).cast("int"))).first()[0]


def _spread(states: DataFrame, store: BlockStore) -> float:
    """The part of buckets with a block that is not clean."""
    buckets = states.withColumn("bucket", F.expr(f"block_no div {store.bucket_blocks}")).groupBy("rank", "bucket").agg(F.max((F.col("status") != tracker.CLEAN).cast("int")).alias("touched"))
    return buckets.agg(F.avg("touched")).first()[0] or 0.0


def checkpoint(cells: DataFrame, store: BlockStore, mode: str = "copy_on_write", gather_target: int | None = None, force_dirty: bool = False, keep_pending: bool = False, layout: DataFrame | None = None, rho: float | None = None) -> Outcome:
    """Commits the state ``cells`` as the store's next version.

    The state is cut once for the comparison; after that only cells of what is to be written move again. A first or full
    checkpoint cuts once in all. The ledger takes the digests of the files that were written, read back; with ``keep_pending`` it takes
    those of the comparison, which then must be of the same rows. With ``auto`` a sample of blocks and ``rho``, the hashing time over the writing
    time of a block, settle whether a differential update pays, and the spread of changes over buckets how it is written. What a failed
    attempt has written is removed; nothing of it would be in the way of the next one either.
    """
    cutting.check_size(store.b)
    store.new_attempt()
    try:
        with staging(store.spark) as stage:
            return _checkpoint(cells, store, mode, gather_target, force_dirty, keep_pending, layout, rho, stage)
    except Exception:
        store.discard()
        raise


def _checkpoint(cells, store, mode, gather_target, force_dirty, keep_pending, layout, rho, stage) -> Outcome:
    version, base = store.next_version(), store.latest()
    auto = mode == "auto"
    try:
        ledger = store.ledger(base) if base is not None else None
    except StoreError:  # of another digest or block size: never compared with
        ledger, mode = None, "full"
    if auto:
        share = sampled_share(cells, store) if ledger is not None and rho is not None else None
        mode = store.choose_mode("copy_on_write", share, rho)
    else:
        mode = store.choose_mode(mode)
    if ledger is None:
        mode = "full"

    def cut(wanted: DataFrame | None) -> DataFrame:
        return cutting.cut_some(cells, store.b, wanted, store.bucket_blocks)

    def written(prepared: dict) -> DataFrame:
        stored = store.written_blocks(prepared)
        return stored if stored is not None else cutting.cut(cells.limit(0), store.b)

    if mode == "full":
        prepared = store.write_update(version, cut, None, mode)
        fresh = stage(tracker.create_ledger(written(prepared), store.algo, version), "ledger")
        known = fresh.select(*cutting.KEYS, "block_len", "digest")
        seen = known.withColumn("status", F.lit(tracker.INVALID)) if ledger is None else tracker.compare(known, ledger, force_dirty)
        seen, after = stage(seen, "states"), fresh
    else:
        seen = tracker.classify(cut(None), ledger, store.algo, force_dirty)
        seen = stage(seen if keep_pending else seen.drop("digest"), "states")
        if auto and (store.manifest(base)["chain"] or _spread(seen, store) > SPREAD):
            mode = "delta_chain"
        prepared = store.write_update(version, cut, seen, mode, gather_target)
        after = tracker.advance(ledger, seen, store.algo, version) if keep_pending else tracker.advance_to_files(ledger, seen, store.written_blocks(prepared), store.algo, version)
    layout_path = store.write_containers(version, layout) if layout is not None else None
    store.promote(prepared, store.write_ledger(version, after), layout_path)

    n = seen.groupBy("status").agg(F.count(F.lit(1)).alias("n"), F.sum("block_len").alias("bytes")).collect()
    count, size = {r["status"]: r["n"] for r in n}, {r["status"]: r["bytes"] for r in n}
    alive = {s: k for s, k in count.items() if s != tracker.RETIRED}
    dirty, invalid = count.get(tracker.DIRTY, 0), count.get(tracker.INVALID, 0)
    changed = sum(size.get(s, 0) for s in regions.WRITTEN)
    total = sum(alive.values())
    state_bytes = sum(v for s, v in size.items() if s != tracker.RETIRED)
    physical = sum(f["bytes"] for f in prepared["files"] if f["dir"] == prepared["dir"])
    n_regions = regions.merge(seen, store.b, regions.STRIDE).count()
    return Outcome(version, prepared["mode"], total, dirty, invalid, count.get(tracker.RETIRED, 0), state_bytes, state_bytes if prepared["mode"] == "full" else changed, physical, n_regions, total - invalid, 0 if keep_pending and ledger is not None else dirty + invalid)
