"""Documents into shards of near-equal bytes by histogram sort.

Rows are ordered by a hash of their text and then of their id, so equal texts lie side by side and no key is ordered
by content that could be skewed. Splitters are found by counting exact bytes per range of leading key bits: each pass
narrows only the ranges that still hold a splitter, until the bytes below a boundary meet the tolerance. A range that
holds one text only (a group of copies, whatever its size) is split further by the hash of the id. Counts come to the driver as
at most (shards - 1) * 2**BITS rows a pass. Then the rows are exchanged once.

Defined cases: null text has size 1 and checksum 0; an empty table gives no rows; rows repeated under one id
have keys of their own; a null id hashes like any other. Further columns pass through, columns of the added names are replaced.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import staged

BITS = 10
#: Rows of a shard numbered by one task.
ROWS_PER_TASK = 1_000_000


def _shifts() -> list[int]:
    return [max(0, 64 - BITS * (k + 1)) for k in range(-(-64 // BITS))]


def _refine(rows: DataFrame, key: str, base: int, targets: list[tuple[int, int]], slack: float) -> dict[int, tuple[int, int, int | None]]:
    """Boundaries on ``key`` for each (splitter, target bytes).

    Gives (boundary, bytes below it, None), or (value, bytes below it, bytes of it) where one value holds the splitter.
    """
    done: dict[int, tuple[int, int, int | None]] = {}
    open_ranges: dict[int | None, list[tuple[int, int]]] = {None: targets}
    below_range = {None: base}
    previous = None
    for shift in _shifts():
        if not open_ranges:
            break
        level = rows
        if previous is not None:
            level = rows.where(F.call_function("shiftright", F.col(key), F.lit(previous)).isin(list(open_ranges)))
        counted = level.groupBy(F.call_function("shiftright", F.col(key), F.lit(shift)).alias("p")).agg(F.sum("size").alias("b"), F.min(key).alias("lo"), F.max(key).alias("hi")).collect()
        parents: dict[int | None, list] = {}
        for r in sorted(counted, key=lambda r: r["p"]):
            parents.setdefault(None if previous is None else r["p"] >> (previous - shift), []).append(r)
        narrower: dict[int | None, list[tuple[int, int]]] = {}
        for parent, wanted in open_ranges.items():
            below, todo = below_range[parent], sorted(wanted, key=lambda x: x[1])
            for r in parents.get(parent, []):
                while todo and todo[0][1] <= below + r["b"]:
                    splitter, target = todo.pop(0)
                    low_gap, high_gap = target - below, below + r["b"] - target
                    if min(low_gap, high_gap) <= slack:
                        done[splitter] = (r["p"] << shift, below, None) if low_gap <= high_gap else ((r["p"] + 1) << shift, below + r["b"], None)
                    elif r["lo"] == r["hi"]:
                        done[splitter] = (r["lo"], below, r["b"])
                    else:
                        narrower.setdefault(r["p"], []).append((splitter, target))
                        below_range[r["p"]] = below
                below += r["b"]
            for splitter, _ in todo:
                done[splitter] = ((1 << 63), below, None)
        open_ranges, previous = narrower, shift
    return done


def find_splitters(rows: DataFrame, shards: int, tolerance: float) -> list[tuple[int, int | None]]:
    """(boundary of h, boundary of v within h or None) of each splitter, from ``rows`` (h, v, size)."""
    total = rows.agg(F.sum("size")).first()[0] or 0
    slack = tolerance * total / shards
    targets = [(k, total * (k + 1) // shards) for k in range(shards - 1)]
    first = _refine(rows, "h", 0, targets, slack)
    out: dict[int, tuple[int, int | None]] = {k: (b, None) for k, (b, _, whole) in first.items() if whole is None}
    hot: dict[int, list[tuple[int, int]]] = {}
    for k, (value, _, whole) in first.items():
        if whole is not None:
            hot.setdefault(value, []).append(targets[k])
    for value, wanted in hot.items():  # at most one for each splitter
        below = first[wanted[0][0]][1]
        for k, (b, _, _) in _refine(rows.where(F.col("h") == F.lit(value)), "v", below, wanted, slack).items():
            out[k] = (value, b)
    return [out[k] for k in range(shards - 1)] if total else []


def _at_least(column: str, boundary: int) -> Column:
    return F.lit(False) if boundary >= 1 << 63 else F.col(column) >= F.lit(boundary)


def shard_of(splitters: list[tuple[int, int | None]], key: str = "h", within: str = "v") -> Column:
    """The number of splitters at or below the row's key (the columns ``key`` and ``within``)."""
    shard = F.lit(0)
    for h, v in splitters:
        past = _at_least(key, h) if v is None else _at_least(key, h) & ((F.col(key) != F.lit(h)) | _at_least(within, v))
        shard = shard + F.when(past, 1).otherwise(0)
    return shard


def assign_shards(docs: DataFrame, shards: int = 16, tolerance: float = 0.002, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, size, text_crc32, law, shard, slot, grown_shard."""
    text = F.col(text_col)
    binary = F.coalesce(text, F.lit("")).cast("binary")
    compact = docs.select(F.col(id_col), (F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 1).alias("size"), F.crc32(binary).alias("text_crc32"), F.xxhash64(text).alias("h"), F.xxhash64(F.lit(1), F.col(id_col), F.monotonically_increasing_id()).alias("v"))
    compact = staged(compact, "shard-keys")  # the numbers of rows are written once and do not change any more
    placed = compact.withColumn("shard", shard_of(find_splitters(compact, shards, tolerance)))
    salts = max(64, -(-compact.count() // (shards * ROWS_PER_TASK)))
    placed = placed.withColumn("salt", F.pmod(F.xxhash64(F.lit(2), F.col(id_col), F.col("h")), F.lit(salts)))
    # Row counts of (shard, salt): shards * salts small rows; their running sums are where each task's numbers begin.
    counts = placed.groupBy("shard", "salt").agg(F.count(F.lit(1)).alias("n"))
    begin = counts.select(F.col("shard").alias("s1"), F.col("salt").alias("s2"), (F.sum("n").over(Window.partitionBy("shard").orderBy("salt").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")).alias("begin"))
    numbered = placed.withColumn("rn", F.row_number().over(Window.partitionBy("shard", "salt").orderBy("h", "v", id_col)))
    numbered = numbered.join(F.broadcast(begin), (F.col("shard") == F.col("s1")) & (F.col("salt") == F.col("s2")))
    return numbered.select(id_col, "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), (F.col("begin") + F.col("rn") - 1).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))


def write_shards(docs: DataFrame, path: str, shards: int = 16, tolerance: float = 0.002, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Writes the documents themselves as ``path/shard=k/``; the texts move once, to as many files as their bytes need.

    All columns pass through but one named ``shard``. Rows repeated under one id and text stay together here."""
    text = F.col(text_col)
    keyed = docs.drop("shard").withColumns({"__key": F.xxhash64(text), "__within": F.xxhash64(F.lit(1), F.col(id_col))})
    sizes = staged(keyed.select(F.col("__key").alias("h"), F.col("__within").alias("v"), (F.coalesce(F.octet_length(text), F.lit(0)).cast("long") + 1).alias("size")), "shard-keys")
    out = keyed.withColumn("shard", shard_of(find_splitters(sizes, shards, tolerance), "__key", "__within")).drop("__key", "__within")
    out.hint("rebalance", "shard").write.partitionBy("shard").parquet(path)
