"""Cutting datasets into blocks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.digests import digest
from ..functions.encode import cell_hex

KEYS = ["rank", "dataset_id", "block_no"]


def check_size(b: int, width: int = 8) -> None:
    if b <= 0 or b % width:
        raise ValueError(f"a block of {b} bytes does not hold whole cells of {width}")


def cut(cells: DataFrame, b: int) -> DataFrame:
    """blocks (rank, dataset_id, block_no, block_len, payload). A group holds one block: b / 8 cells."""
    check_size(b)
    block = F.expr(f"pos * 8 div {b}").alias("block_no")
    held = cells.select("rank", "dataset_id", block, "pos", cell_hex(F.col("cell")).alias("h"))
    joined = held.groupBy(*KEYS).agg((F.count(F.lit(1)) * 8).alias("block_len"), F.expr("listagg(h) WITHIN GROUP (ORDER BY pos)").alias("h"))
    return joined.select(*KEYS, "block_len", F.unhex("h").alias("payload"))


def cut_some(cells: DataFrame, b: int, wanted: DataFrame | None, bucket_blocks: int = 1) -> DataFrame:
    """blocks named in ``wanted``, by their keys or by rank and bucket; cells of others are dropped before anything moves. All blocks without it."""
    if wanted is None:
        return cut(cells, b)
    block = F.expr(f"pos * 8 div {b}")
    if "bucket" in wanted.columns:
        placed, keys = cells.withColumn("bucket", F.expr(f"(pos * 8 div {b}) div {bucket_blocks}")), ["rank", "bucket"]
    else:
        placed, keys = cells.withColumn("block_no", block), KEYS
    return cut(placed.join(wanted.select(*keys), keys, "left_semi").select(*cells.columns), b)


def cut_clustered(ordered: DataFrame, b: int) -> DataFrame:
    """blocks of cells that arrive as arrays, one row for each (rank, dataset_id, run of positions from ``start`` that begins a block).

    Nothing is shuffled: for state that is stored block-clustered.
    """
    check_size(b)
    cells = b // 8
    starts = F.sequence(F.lit(0), F.expr(f"(size(cells) - 1) div {cells}").cast("int"))
    piece = F.transform(starts, lambda i: F.struct((F.expr(f"start * 8 div {b}") + i).alias("block_no"), F.slice("cells", i * cells + 1, cells).alias("c")))
    rows = ordered.where(F.size("cells") > 0).select("rank", "dataset_id", F.inline(piece))
    payload = F.unhex(F.array_join(F.transform("c", cell_hex), ""))
    return rows.select(*KEYS, (F.size("c") * 8).cast("bigint").alias("block_len"), payload.alias("payload"))


def cut_runs(runs: DataFrame, sizes: list[int]) -> DataFrame:
    """blocks (b, variant, rank, dataset_id, block_no, block_len, whole, old, new) of every size in ``sizes``, with the bytes of two versions.

    ``runs`` (variant, rank, dataset_id, start, old, new) hold the cells from position ``start`` on, packed; a null ``new`` stands for ``old``.
    Sizes must divide the largest one. Of a single size, a block that lies within one run is compared where it is:
    ``whole`` says whether both digests agree, and its bytes stop there. Pieces of others meet by key, once for all sizes.
    """
    keys = ["variant", *KEYS]
    for b in sizes:
        check_size(b)
    most, per = max(sizes), max(sizes) // 8
    if any(most % b for b in sizes):
        raise ValueError(f"sizes {sizes} do not divide the largest one")
    end = F.expr("start + octet_length(old) div 8")
    spread = runs.where(F.octet_length("old") > 0).select("*", end.alias("end"), F.explode(F.sequence(F.expr(f"start div {per}"), F.expr(f"(start + octet_length(old) div 8 - 1) div {per}"))).alias("block_no"))
    low, high = F.greatest("start", F.col("block_no") * per), F.least("end", (F.col("block_no") + 1) * per)
    at, n = ((low - F.col("start")) * 8 + 1).cast("int"), ((high - low) * 8).cast("int")
    pieces = spread.select(*keys, low.alias("low"), n.alias("n"), F.substring(F.col("old"), at, n).alias("old"), F.substring(F.col("new"), at, n).alias("new"))
    if len(sizes) == 1:
        inside = F.col("n") == most
        same = F.when(inside, digest(F.col("old")) == digest(F.coalesce("new", "old")))
        pieces = pieces.select(*keys, "low", "n", same.alias("whole"), *[F.when(~inside, F.col(c)).alias(c) for c in ("old", "new")])
    else:
        pieces = pieces.withColumn("whole", F.lit(None).cast("boolean"))
    # Dealt by columns that are no constants: a key that folds away would cost a second shuffle.
    joined = pieces.repartition("rank", "block_no").groupBy(*keys).agg(
        F.sum("n").alias("block_len"), F.bool_and("whole").alias("whole"),
        F.expr("listagg(old) WITHIN GROUP (ORDER BY low)").alias("old"), F.expr("listagg(coalesce(new, old)) WITHIN GROUP (ORDER BY low)").alias("new"),
    )
    if len(sizes) == 1:
        return joined.select(F.lit(most).alias("b"), *keys, "block_len", "whole", "old", "new")

    def smaller(b: int) -> Column:
        def one(i: Column) -> Column:
            parts = [F.substring(F.col(c), (i * b + 1).cast("int"), F.lit(b)).alias(c) for c in ("old", "new")]
            return F.struct(F.lit(b).alias("b"), (F.col("block_no") * (most // b) + i).alias("block_no"), F.least(F.lit(b).cast("bigint"), F.col("block_len") - i * b).alias("block_len"), *parts)

        return F.transform(F.sequence(F.lit(0).cast("bigint"), F.expr(f"(block_len - 1) div {b}")), one)

    cut_up = joined.select("variant", "rank", "dataset_id", "whole", F.inline(F.concat(*[smaller(b) for b in sizes])))
    return cut_up.select("b", *keys, "block_len", "whole", "old", "new")


def cut_records(df: DataFrame, key: str, payload: str, b: int) -> DataFrame:
    """(key, block_no, block_len, payload) of each record's bytes by itself; an empty record has no block."""
    n = F.octet_length(payload)
    pieces = F.transform(F.sequence(F.lit(0), F.expr(f"(octet_length({payload}) - 1) div {b}").cast("int")), lambda i: F.substring(F.col(payload), i * b + 1, F.lit(b)))
    cut_up = df.where(n > 0).select(key, F.posexplode(pieces).alias("block_no", "payload"))
    return cut_up.select(key, F.col("block_no").cast("bigint").alias("block_no"), F.octet_length("payload").cast("bigint").alias("block_len"), "payload")


def cut_stream(df: DataFrame, rank: str, key: str, payload: str, b: int, dataset_id: str = "stream") -> DataFrame:
    """blocks of each rank's records joined in key order; blocks may straddle records."""
    n = F.octet_length(payload).cast("bigint")
    begin = F.sum(n).over(Window.partitionBy(rank).orderBy(key).rowsBetween(Window.unboundedPreceding, 0)) - n
    placed = df.select(F.col(rank).cast("int").alias("rank"), begin.alias("begin"), n.alias("n"), F.col(payload).alias("p")).where("n > 0")
    spread = placed.select("*", F.explode(F.sequence(F.expr(f"begin div {b}"), F.expr(f"(begin + n - 1) div {b}"))).alias("block_no"))
    first = F.greatest(F.lit(0).cast("bigint"), F.col("block_no") * b - F.col("begin"))
    last = F.least(F.col("n"), (F.col("block_no") + 1) * b - F.col("begin"))
    piece = F.substring(F.col("p"), (first + 1).cast("int"), (last - first).cast("int"))
    parts = spread.select("rank", "block_no", "begin", F.hex(piece).alias("h"))
    joined = parts.groupBy("rank", "block_no").agg(F.expr("listagg(h) WITHIN GROUP (ORDER BY begin)").alias("h"))
    return joined.select("rank", F.lit(dataset_id).alias("dataset_id"), "block_no", (F.length("h") / 2).cast("bigint").alias("block_len"), F.unhex("h").alias("payload"))


def uncut(blocks: DataFrame, b: int) -> DataFrame:
    """The cells of blocks."""
    text = F.hex("payload")
    values = F.transform(F.sequence(F.lit(0), F.expr("octet_length(payload) div 8 - 1").cast("int")), lambda i: F.substring(text, 16 * i + 1, F.lit(16)))
    cells = blocks.where(F.octet_length("payload") > 0).select("rank", "dataset_id", "block_no", F.posexplode(values).alias("i", "h"))
    high, low = (F.conv(F.substring("h", k, 8), 16, 10).cast("bigint") for k in (1, 9))
    signed = F.shiftleft(F.when(high >= 1 << 31, high - (1 << 32)).otherwise(high), 32).bitwiseOR(low)
    return cells.select("rank", "dataset_id", (F.col("block_no") * (b // 8) + F.col("i")).alias("pos"), signed.alias("cell"))
