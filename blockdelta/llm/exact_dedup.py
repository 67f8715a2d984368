"""Exact duplicates through an extendible-hash index on shared files. DataFrame functions only.

Every text is keyed by a 64-bit hash of its normalised bytes (A-Z lower-cased; null counts as empty). A first pass over the hashes alone
tells how many rows and bytes stand behind each. From that the directory grows: over leading hash bits it doubles, and buckets
split, until none holds more bytes of different texts than its capacity or only one hash is left in it. A bucket belongs to one
owner task, which has a range of the directory; texts move there once, and the owner chains those of one hash and tells
them apart by their bytes (the text is part of its grouping key). Hashes that stand for many rows, which are few by arithmetic,
are spread over all owners; each compares the bytes of its rows, and their entries then meet by hash and SHA-256.

The entries, without texts, are the index: files sorted by bucket and hash, one for each owner. Documents find their bucket
by the directory and their entry by hash and SHA-256 in it; two texts that shared all of these would stop the job rather than be merged.

Defined cases: null text is the empty text; an empty table gives no rows; rows repeated under one doc_id are the same
document and get the same verdict; of null doc_ids any other one wins, and a group of null ids only keeps them all.
Further columns pass through; the columns that the operator adds replace columns of the same names.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import HOT_SHARE, ascii_lower, look_up, staged

#: Bytes of different texts in a bucket, at least and at most as long as there are no more than MOST_BUCKETS, about.
LEAST_CAPACITY, CAPACITY, MOST_BUCKETS = 8 << 20, 64 << 20, 1 << 14
#: Bits by which overfull buckets are counted anew.
MORE_BITS = 8

Counts = dict[int, tuple[int, int]]


@dataclass(frozen=True)
class Directory:
    """The directory of an extendible hash: for each leading pattern of ``depth`` bits, the local depth of its bucket (a byte each)."""

    depth: int
    local: bytes

    def buckets(self) -> list[tuple[int, int]]:
        """(first slot, slots covered) of each bucket."""
        out, slot = [], 0
        while slot < len(self.local):
            width = 1 << (self.depth - self.local[slot])
            out.append((slot, width))
            slot += width
        return out

    def bucket_of(self, key: Column) -> Column:
        """The bucket's first slot: the leading ``local`` bits of the key, padded with zeros."""
        if self.depth == 0:
            return F.lit(0).cast("bigint")
        slot = F.shiftrightunsigned(key, 64 - self.depth)
        # Depths are looked up as letters, so that each is one byte of a string too.
        local = F.ascii(F.substring(F.lit(bytearray(48 + d for d in self.local)), (slot + 1).cast("int"), F.lit(1)).cast("string")) - 48
        free = F.lit(self.depth) - local
        return F.call_function("shiftleft", F.call_function("shiftright", slot, free), free)

    def owner_of(self, bucket: Column, owners: int) -> Column:
        """Owners have ranges of slots; a bucket lies with the owner of its first one."""
        return F.floor(bucket * owners / F.lit(1 << self.depth)).cast("int")


def grow_directory(measure: Callable[[int, list[tuple[int, int]] | None], Counts], bits: int, capacity: int) -> Directory:
    """Splits overfull buckets, doubling the directory as needed.

    ``measure(bits, within)`` gives (bytes, different hashes) by the leading ``bits`` bits, of all hashes or of those
    ``within`` the given (prefix, bits); it is asked again, for more bits, only about buckets that are still overfull then.
    """
    leaves: list[tuple[int, int]] = []
    open_: list[tuple[int, int]] = [(0, 0)]
    within = None
    while open_:
        levels: dict[int, Counts] = {bits: measure(bits, within)}
        for depth in range(bits - 1, open_[0][1] - 1, -1):
            sums: Counts = {}
            for prefix, (size, n) in levels[depth + 1].items():
                had = sums.get(prefix >> 1, (0, 0))
                sums[prefix >> 1] = (had[0] + size, had[1] + n)
            levels[depth] = sums
        overfull = []
        while open_:
            prefix, depth = open_.pop()
            size, n = levels[depth].get(prefix, (0, 0))
            if size <= capacity or n <= 1 or depth == 64:
                leaves.append((prefix, depth))
            elif depth == bits:
                overfull.append((prefix, depth))
            else:
                open_ += [(2 * prefix, depth + 1), (2 * prefix + 1, depth + 1)]
        open_ = within = overfull
        bits = min(64, bits + MORE_BITS)
    top = max(depth for _, depth in leaves)
    local = bytearray(1 << top)
    for prefix, depth in leaves:
        width = 1 << (top - depth)
        local[prefix * width : (prefix + 1) * width] = bytes([depth]) * width
    return Directory(top, bytes(local))


def _leading(bits: int) -> Column:
    return F.shiftrightunsigned("h", 64 - bits) if bits else F.lit(0).cast("bigint")


def build_index(keyed: DataFrame, capacity: int | None = None) -> tuple[DataFrame, Directory]:
    """Index entries (bucket, h, sha, keep_id, n) of ``keyed`` (id, h, norm), one for each distinct text, on shared files."""
    hashes = staged(keyed.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.max(F.octet_length("norm")).cast("long").alias("size")), "dedup-hashes")
    rows, total = (x or 0 for x in hashes.agg(F.sum("n"), F.sum("size")).first())
    if capacity is None:
        tasks = 4 * keyed.sparkSession.sparkContext.defaultParallelism
        capacity = max(min(CAPACITY, max(LEAST_CAPACITY, total // tasks)), total // MOST_BUCKETS)

    def measure(bits: int, within: list[tuple[int, int]] | None) -> Counts:
        some = hashes if within is None else hashes.where(_leading(within[0][1]).isin([prefix for prefix, _ in within]))
        counted = some.groupBy(_leading(bits).alias("p")).agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("n")).collect()
        return {r["p"]: (r["size"], r["n"]) for r in counted}

    # About four counts for each bucket that capacity asks for.
    directory = grow_directory(measure, max(2, (total // max(1, capacity)).bit_length() + 2), capacity)
    owners = min(len(directory.buckets()), MOST_BUCKETS)
    hot = [r["h"] for r in hashes.where(F.col("n") >= max(2, int(rows * HOT_SHARE))).select("h").collect()]  # at most 1 / HOT_SHARE
    held = keyed.withColumns({"bucket": directory.bucket_of(F.col("h")), "row": F.monotonically_increasing_id()})
    spread = F.pmod(F.xxhash64("id", "row"), F.lit(owners)).cast("int")
    held = held.withColumn("owner", F.when(F.col("h").isin(hot), spread).otherwise(directory.owner_of(F.col("bucket"), owners)))
    # The exchange puts each owner's rows into its task, so the aggregate needs no other one.
    chained = held.select("owner", "bucket", "h", "norm", "id").repartitionById(owners, "owner").groupBy("owner", "bucket", "h", "norm").agg(F.max("id").alias("keep_id"), F.count(F.lit(1)).alias("n"))
    entries = staged(chained.select("owner", "bucket", "h", F.sha2("norm", 256).alias("sha"), "keep_id", "n"), "dedup-entries")
    # Only a spread hash has entries of several owners; an owner has compared the bytes of its own.
    alike = F.count(F.lit(1)) > F.size(F.collect_set("owner"))
    safe = F.when(alike, F.raise_error(F.lit("two texts share their 64-bit hash and SHA-256"))).otherwise(F.max("keep_id"))
    merged = entries.groupBy("bucket", "h", "sha").agg(safe.cast(entries.schema["keep_id"].dataType).alias("keep_id"), F.sum("n").alias("n"))
    index = merged.withColumn("owner", directory.owner_of(F.col("bucket"), owners)).repartitionById(owners, "owner").drop("owner").sortWithinPartitions("bucket", "h", "sha")
    return staged(index, "dedup-index"), directory


def mark_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", capacity: int | None = None, prefix: str = "") -> DataFrame:
    """``docs`` with keep_id, group_size, kept and text_sha256, their names prefixed as asked."""
    norm = ascii_lower(F.coalesce(F.col(text_col), F.lit("")))
    keyed = docs.select(F.col(id_col).alias("id"), norm.alias("norm")).select("id", F.xxhash64("norm").alias("h"), "norm")
    index, directory = build_index(keyed, capacity)
    added = [f"{prefix}{name}" for name in ("keep_id", "group_size", "kept", "text_sha256")]
    own = [c for c in docs.columns if c not in added]
    if id_col in added or text_col in added:
        raise ValueError("the prefix must keep the names of id and text apart from the added ones")
    keyed_docs = docs.select(*own, norm.alias("__norm")).select(*own, F.xxhash64("__norm").alias("__h"), F.sha2("__norm", 256).alias("__sha"))

    def key(bucket: Column, h: Column, sha: Column) -> Column:
        return F.unhex(F.concat(F.lpad(F.hex(bucket), 16, "0"), F.lpad(F.hex(h), 16, "0"), sha))

    # Bucket and both hashes make up the key: two texts that shared them would have stopped the job.
    keyed_docs = keyed_docs.select(*own, "__sha", key(directory.bucket_of(F.col("__h")), F.col("__h"), F.col("__sha")).alias("__key_of"))
    entries = index.select(key(F.col("bucket"), F.col("h"), F.col("sha")).alias("__key_of"), F.col("keep_id").alias("__keep"), F.col("n").alias("__n"))
    found = look_up(keyed_docs, entries, "__key_of", "__n", F.xxhash64(id_col))
    return found.select(*own, F.col("__keep").alias(added[0]), F.col("__n").alias(added[1]), F.col(id_col).eqNullSafe(F.col("__keep")).alias(added[2]), F.col("__sha").alias(added[3]))
