"""Block digests: MD5 and CRC32, the two weak sums they are held against, exact bytes, and a combinable extension.

Weak sums are weighted sums of bytes or words, so they are plain aggregates over cells that combine before the shuffle.
"""

from __future__ import annotations

import warnings

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Digest bytes kept for each block, by algorithm. ``exact`` keeps the block itself.
WIDTH = {"md5": 16, "crc32": 4, "adler32": 4, "fletcher32_65535": 4, "fletcher32_65536": 4, "xor64": 8}
WEAK = ("adler32", "fletcher32_65535", "fletcher32_65536")
# Fixed value: the largest prime below 2**16.
ADLER_MODULUS = 65521


def as_binary(number: Column, width: int) -> Column:
    return F.unhex(F.lpad(F.hex(number), 2 * width, "0"))


def byte_values(payload: Column) -> Column:
    """The bytes of a BINARY as an array of numbers."""
    text = F.hex(payload)
    return F.when(F.octet_length(payload) == 0, F.array().cast("array<bigint>")).otherwise(
        F.transform(F.sequence(F.lit(0), F.octet_length(payload) - 1), lambda i: F.conv(F.substring(text, 2 * i + 1, F.lit(2)), 16, 10).cast("bigint"))
    )


def weighted(values: Column) -> tuple[Column, Column, Column]:
    """(count, sum, sum weighted by the distance to the end) of an array of numbers."""
    n = F.size(values).cast("bigint")
    plain = F.aggregate(values, F.lit(0).cast("bigint"), lambda a, x: a + x)
    far = F.aggregate(F.transform(values, lambda x, i: (n - i) * x), F.lit(0).cast("bigint"), lambda a, x: a + x)
    return n, plain, far


def adler32_of(n: Column, plain: Column, far: Column) -> Column:
    """From byte sums: one plus the sum below, byte count plus the weighted sum above."""
    return ((n + far) % ADLER_MODULUS) * 65536 + (1 + plain) % ADLER_MODULUS


def fletcher32_of(plain: Column, far: Column, modulus: int) -> Column:
    return (far % modulus) * 65536 + plain % modulus


def words_of(values: Column) -> Column:
    """16-bit little-endian words of an array of bytes; an odd last byte stands alone."""
    n = F.size(values)
    padded = F.concat(values, F.array(F.lit(0).cast("bigint")))
    return F.when(n == 0, values).otherwise(F.transform(F.sequence(F.lit(0), (n - 1).cast("int"), F.lit(2)), lambda i: F.element_at(padded, i + 1) + 256 * F.element_at(padded, i + 2)))


def digest(payload: Column, algo: str = "md5") -> Column:
    """The digest of a BINARY column as BINARY."""
    if algo in WEAK:
        warnings.warn(f"{algo} misses changes; use md5 or crc32", stacklevel=2)
    if algo == "md5":
        return F.unhex(F.md5(payload))
    if algo == "crc32":
        return as_binary(F.crc32(payload), 4)
    if algo == "exact":
        return payload
    if algo == "adler32":
        return as_binary(adler32_of(*weighted(byte_values(payload))), 4)
    if algo.startswith("fletcher32_"):
        _, plain, far = weighted(words_of(byte_values(payload)))
        return as_binary(fletcher32_of(plain, far, int(algo.split("_")[1])), 4)
    raise ValueError(f"no digest {algo} of whole blocks")


def block_sums(cells: DataFrame, b: int) -> DataFrame:
    """Adler32 and both Fletcher32 of each block, straight from cells: sums only, nothing is collected."""
    at = (F.col("pos") * 8) % b
    octets = [F.shiftright("cell", 56 - 8 * k).bitwiseAND(F.lit(255)) for k in range(8)]
    words = [octets[2 * k] + 256 * octets[2 * k + 1] for k in range(4)]
    sums = cells.groupBy("rank", "dataset_id", F.expr(f"pos * 8 div {b}").alias("block_no")).agg(
        (F.count(F.lit(1)) * 8).alias("block_len"),
        F.sum(sum(octets[1:], octets[0])).alias("s"),
        F.sum(sum(((at + k) * octets[k] for k in range(1, 8)), at * octets[0])).alias("si"),
        F.sum(sum(words[1:], words[0])).alias("w"),
        F.sum(sum(((at / 2).cast("bigint") + k) * words[k] for k in range(4))).alias("wi"),
    )
    n, half = F.col("block_len"), F.expr("block_len div 2")
    far, far_words = n * F.col("s") - F.col("si"), half * F.col("w") - F.col("wi")
    return sums.select(
        "rank", "dataset_id", "block_no", "block_len",
        adler32_of(n, F.col("s"), far).alias("adler32"),
        fletcher32_of(F.col("w"), far_words, 65535).alias("fletcher32_65535"),
        fletcher32_of(F.col("w"), far_words, 65536).alias("fletcher32_65536"),
    )


def xor_blocks(cells: DataFrame, b: int) -> DataFrame:
    """An order-free digest that combines before the shuffle, 8 bytes a block. An extension, never the default."""
    return cells.groupBy("rank", "dataset_id", F.expr(f"pos * 8 div {b}").alias("block_no")).agg(
        (F.count(F.lit(1)) * 8).alias("block_len"), as_binary(F.bit_xor(F.xxhash64("pos", "cell")), 8).alias("digest")
    )
