"""Digests against zlib, hashlib and worked values."""

import hashlib
import random
import zlib

import pytest
from pyspark.sql import functions as F

from blockdelta.functions import digests
from blockdelta.plans import collision


def of(spark, payloads, algo):
    df = spark.createDataFrame([(k, bytearray(p)) for k, p in enumerate(payloads)], "k int, p binary")
    with pytest.warns(UserWarning) if algo in digests.WEAK else _quiet():
        column = digests.digest(F.col("p"), algo)
    return [bytes(r["d"]) for r in df.select("k", column.alias("d")).orderBy("k").collect()]


class _quiet:
    def __enter__(self):
        return self

    def __exit__(self, *a):
        return False


def test_known_values(spark):
    rng = random.Random(1)
    payloads = [b"123456789", b"Wikipedia", bytes([0, 255]), b"", *(rng.randbytes(n) for n in (1, 7, 8, 128, 1000))]
    assert [int.from_bytes(d, "big") for d in of(spark, payloads, "crc32")] == [zlib.crc32(p) for p in payloads]
    assert zlib.crc32(b"123456789") == 3421780262
    assert [int.from_bytes(d, "big") for d in of(spark, payloads, "adler32")] == [zlib.adler32(p) for p in payloads]
    assert zlib.adler32(b"Wikipedia") == 300286872
    assert of(spark, payloads, "md5") == [hashlib.md5(p).digest() for p in payloads]
    assert hashlib.md5(bytes([0, 255])).hexdigest() == "d07d34efac6328007ad67c7e0a985e00"


def test_fletcher_modulus_hides_changes(spark):
    a, b = b"\x01\x02\x00\x00\x05\x06\x07\x08", b"\x01\x02\xff\xff\x05\x06\x07\x08"
    x, y = of(spark, [a, b], "fletcher32_65535")
    assert x == y
    x, y = of(spark, [a, b], "fletcher32_65536")
    assert x != y


def test_unknown(spark):
    with pytest.raises(ValueError):
        digests.digest(F.col("p"), "sum")


def test_collision_rate_of_single_bit_flips(spark):
    """All elements flipped in the last bit: collisions need balanced signs and balanced positions; the exact probability for 16 elements comes by counting."""
    n, ways = 16, {(0, 0): 1}
    for i in range(n):
        after = {}
        for (s, w), c in ways.items():
            for d in (1, -1):
                after[s + d, w + d * i] = after.get((s + d, w + d * i), 0) + c
        ways = after
    exact = ways[0, 0] / 2**n
    assert exact == pytest.approx(0.00803, abs=1e-5)
    trials = 60_000
    rows = {(r["algo"], r["pattern"]): r["hits"] for r in collision.run(spark, 128, trials, ("adler32", "crc32", "md5")).collect()}
    spread = 4 * (exact * (1 - exact) / trials) ** 0.5
    assert abs(rows["adler32", "p0"] / trials - exact) < spread
    assert rows["adler32", "p0"] > rows["adler32", "p1"] > rows["adler32", "p2"]
    assert all(hits == 0 for (algo, _), hits in rows.items() if algo != "adler32")


def test_one_changed_element_never_collides(spark):
    rows = collision.run(spark, 128, 2000, ("adler32",), mode="single").where("pattern in ('p0', 'p1', 'p2')").collect()
    assert all(r["hits"] == 0 for r in rows)


def test_xor64_by_hand(spark):
    """The combinable digest against the hash function itself, in any order of the cells."""
    import xxhash

    from blockdelta.functions.digests import xor_blocks

    cells = [(0, "a", pos, pos * 7919 - 100) for pos in range(10)]
    got = {r["block_no"]: bytes(r["digest"]) for r in xor_blocks(spark.createDataFrame(cells[::-1], "rank int, dataset_id string, pos bigint, cell bigint"), 32).collect()}
    for block in range(3):
        want = 0
        for _, _, pos, cell in cells[4 * block : 4 * block + 4]:
            seed = xxhash.xxh64(pos.to_bytes(8, "little", signed=True), seed=42).intdigest()
            want ^= xxhash.xxh64(cell.to_bytes(8, "little", signed=True), seed=seed).intdigest()
        assert got[block] == want.to_bytes(8, "big")
