"""The collision test: random buffers, changed by bit patterns; how often does a digest not notice?"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.digests import adler32_of, fletcher32_of

# The sizes and patterns of the test; "literal" are the constants as printed, "bits" what the text says of them.
SIZES = [1 << k for k in range(7, 16)]
PATTERNS = {"bits": {"p0": 0x1, "p1": 0x3, "p2": 0xF, "p3": 0xFF, "p4": 0xFFFF, "p5": None}, "literal": {"p0": 0x1, "p1": 0x3, "p2": 0xFF, "p3": 0xFFF, "p4": 0xFFFF, "p5": None}}
ALGORITHMS = ("adler32", "fletcher32_65535", "fletcher32_65536", "crc32", "md5")
MODES = ("whole", "single", "prefix")


def element(iteration: Column, i: Column, seed: int, generator: str) -> Column:
    """Element i of a buffer. ``hash`` is a 64-bit hash; ``linear`` is plain arithmetic that any SQL engine repeats."""
    if generator == "hash":
        return F.xxhash64(F.lit(seed), iteration, i)
    low, high = ((iteration * a + i * c + seed) * m % p for a, c, m, p in ((7919, 104729, 48271, 2147483647), (15485863, 32452843, 16807, 2147483629)))
    mixed_low, mixed_high = (low * 1103515245 + 12345) % 2147483647, (high * 69621 + 7) % 2147483629
    return F.shiftleft(mixed_high, 32).bitwiseXOR(mixed_low)


def grid(spark: SparkSession, sizes: list[int] | None = None, patterns: str = "bits") -> DataFrame:
    """(b, pattern, mask): every size with every pattern."""
    sized = spark.createDataFrame([(b,) for b in sizes or SIZES], "b int")
    masks = spark.createDataFrame(list(PATTERNS[patterns].items()), "pattern string, mask bigint")
    return sized.crossJoin(F.broadcast(masks))


def buffers(spark: SparkSession, b: int, n_iter: int, seed: int = 42, generator: str = "hash") -> DataFrame:
    """(iteration, xs): a buffer of b bytes for each iteration. The same rows come out of any retry."""
    it = F.col("id")
    return spark.range(n_iter).select(it.alias("iteration"), F.transform(F.sequence(F.lit(0), F.lit(b // 8 - 1)), lambda i: element(it, i.cast("bigint"), seed, generator)).alias("xs"))


def flip(xs: Column, mask: int | None, iteration: Column, seed: int, generator: str, mode: str) -> Column:
    """The changed buffer: all elements, the first one, or the first half. Without a mask the change is random, a new one for each buffer."""
    change = F.lit(mask).cast("bigint") if mask is not None else element(iteration, F.lit(1 << 20).cast("bigint"), seed, generator)
    limit = {"whole": F.size(xs), "single": F.lit(1), "prefix": F.size(xs) / 2}[mode]
    return F.transform(xs, lambda x, i: F.when(i < limit, x.bitwiseXOR(change)).otherwise(x))


def weak_sums(xs: Column) -> tuple[Column, ...]:
    """(bytes, byte sum, weighted byte sum, word sum, weighted word sum) of big-endian elements."""
    n = F.size(xs).cast("bigint")

    def fold(f) -> Column:
        return F.aggregate(F.transform(xs, f), F.lit(0).cast("bigint"), lambda a, v: a + v)

    def octet(x: Column, k: int) -> Column:
        return F.shiftright(x, 56 - 8 * k).bitwiseAND(F.lit(255))

    def word(x: Column, k: int) -> Column:
        return octet(x, 2 * k) + 256 * octet(x, 2 * k + 1)

    return (
        8 * n,
        fold(lambda x: sum((octet(x, k) for k in range(1, 8)), octet(x, 0))),
        fold(lambda x, i: sum(((8 * (n - i) - k) * octet(x, k) for k in range(1, 8)), 8 * (n - i) * octet(x, 0))),
        fold(lambda x: sum((word(x, k) for k in range(1, 4)), word(x, 0))),
        fold(lambda x, i: sum(((4 * (n - i) - k) * word(x, k) for k in range(1, 4)), 4 * (n - i) * word(x, 0))),
    )


def hashes(xs: Column, algos: tuple[str, ...]) -> dict[str, Column]:
    size, s, far, w, far_words = weak_sums(xs)
    payload = F.unhex(F.array_join(F.transform(xs, lambda x: F.lpad(F.hex(x), 16, "0")), ""))
    every = {"adler32": lambda: adler32_of(size, s, far), "fletcher32_65535": lambda: fletcher32_of(w, far_words, 65535), "fletcher32_65536": lambda: fletcher32_of(w, far_words, 65536), "crc32": lambda: F.crc32(payload), "md5": lambda: F.md5(payload)}
    return {a: every[a]() for a in algos}


#: Moduli of the weak sums; two sums agree if both their parts do.
MODULI = {"adler32": 65521, "fletcher32_65535": 65535, "fletcher32_65536": 65536}


def run_cumulative(spark: SparkSession, b: int, n_iter: int, patterns: str = "bits", seed: int = 42, generator: str = "hash", given: DataFrame | None = None) -> DataFrame:
    """(algo, b, pattern, n_iter, hits, per_billion) of the weak sums where elements change one after the other and every
    stage is compared with the untouched buffer; ``n_iter`` in the result counts the comparisons.

    The sums are linear, so a stage collides when what has been added up so far is 0 in both parts; each element is looked at once."""
    rows = given if given is not None else buffers(spark, b, n_iter, seed, generator)
    out = None
    zero = F.lit(0).cast("bigint")
    for name, mask in PATTERNS[patterns].items():
        pairs = rows.select(F.arrays_zip("xs", flip(F.col("xs"), mask, F.col("iteration"), seed, generator, "whole").alias("ys")).alias("zs"))

        def step(acc: Column, z: Column) -> Column:
            _, s, far, w, far_words = (y - x for x, y in zip(weak_sums(F.array(z["xs"])), weak_sums(F.array(z["ys"]))))
            behind = acc["left"] - 1
            parts = {"s": acc["s"] + s, "far": acc["far"] + far + 8 * behind * s, "w": acc["w"] + w, "far_words": acc["far_words"] + far_words + 4 * behind * w}
            hits = []
            for algo, m in MODULI.items():
                near, distant = (parts["s"], parts["far"]) if algo == "adler32" else (parts["w"], parts["far_words"])
                hits.append((acc[algo] + F.when((near % m == 0) & (distant % m == 0), F.lit(1)).otherwise(F.lit(0)).cast("bigint")).alias(algo))
            return F.struct(behind.alias("left"), *[v.alias(k) for k, v in parts.items()], *hits)

        start = F.struct(F.size("zs").cast("bigint").alias("left"), *[zero.alias(k) for k in ("s", "far", "w", "far_words", *MODULI)])
        one = pairs.select(F.size("zs").alias("n"), F.aggregate("zs", start, step).alias("h")).agg(F.coalesce(F.sum("n"), zero).alias("n_iter"), *[F.sum(f"h.{a}").alias(a) for a in MODULI])
        stack = ", ".join(f"'{a}', {a}" for a in MODULI)
        one = one.selectExpr("n_iter", f"stack({len(MODULI)}, {stack}) AS (algo, hits)").withColumn("pattern", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out.select("algo", F.lit(b).alias("b"), "pattern", "n_iter", F.coalesce("hits", zero).alias("hits"), F.when(F.col("n_iter") > 0, F.expr("coalesce(hits, 0) * 1000000000 div n_iter")).alias("per_billion"))


def run(spark: SparkSession, b: int, n_iter: int = 100_000, algos: tuple[str, ...] = ALGORITHMS, patterns: str = "bits", mode: str = "whole", seed: int = 42, generator: str = "hash", given: DataFrame | None = None) -> DataFrame:
    """(algo, b, pattern, n_iter, hits, per_billion). Each buffer is one row, and a task keeps only its counts. ``given`` are buffers (iteration, xs) from real data."""
    if mode not in MODES:
        raise ValueError(mode)
    rows = given if given is not None else buffers(spark, b, n_iter, seed, generator)
    rows = rows.select("iteration", "xs", F.struct(*[h.alias(a) for a, h in hashes(F.col("xs"), algos).items()]).alias("h"))
    counted = []
    for name, mask in PATTERNS[patterns].items():
        changed = rows.select("h", flip(F.col("xs"), mask, F.col("iteration"), seed, generator, mode).alias("ys"))
        again = changed.select("h", F.struct(*[h.alias(a) for a, h in hashes(F.col("ys"), algos).items()]).alias("g"))
        one = again.agg(F.count(F.lit(1)).alias("n_iter"), *[F.sum((F.col(f"h.{a}") == F.col(f"g.{a}")).cast("bigint")).alias(a) for a in algos])
        stack = ", ".join(f"'{a}', {a}" for a in algos)
        counted.append(one.selectExpr("n_iter", f"stack({len(algos)}, {stack}) AS (algo, hits)").withColumn("pattern", F.lit(name)))
    out = counted[0]
    for c in counted[1:]:
        out = out.unionByName(c)
    hits = F.coalesce("hits", F.lit(0).cast("bigint"))
    return out.select("algo", F.lit(b).alias("b"), "pattern", "n_iter", hits.alias("hits"), F.when(F.col("n_iter") > 0, F.expr("coalesce(hits, 0) * 1000000000 div n_iter")).alias("per_billion"))
