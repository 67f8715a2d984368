"""Measures over states, regions, sizes and run logs. Shares are given per million, so that sums of doubles decide nothing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.costmodel import speedup
from ..functions.digests import WIDTH

LIVE, WRITTEN = "status <> 'retired'", "status IN ('dirty', 'invalid')"


def ppm(part: Column, whole: Column) -> Column:
    return F.when(whole > 0, F.expr("1000000") * part / whole).cast("bigint")


def _count(c: Column) -> Column:
    return F.sum(F.when(c, 1).otherwise(0))


def dirty_share(states: DataFrame, *by: str) -> DataFrame:
    """Blocks, written blocks and bytes, and both shares."""
    live = states.where(LIVE)
    out = live.groupBy(*by).agg(F.count(F.lit(1)).alias("n_blocks"), _count(F.expr(WRITTEN)).alias("n_written"), F.sum("block_len").alias("state_bytes"), F.sum(F.when(F.expr(WRITTEN), F.col("block_len")).otherwise(0)).alias("written_bytes"))
    return out.select(*by, "n_blocks", "n_written", "state_bytes", "written_bytes", ppm(F.col("n_written"), F.col("n_blocks")).alias("block_ppm"), ppm(F.col("written_bytes"), F.col("state_bytes")).alias("byte_ppm"))


def hash_count(states: DataFrame) -> DataFrame:
    """Hashes that comparing and committing take: none to compare for a block without an image."""
    n, invalid, dirty = F.count(F.lit(1)), _count(F.col("status") == "invalid"), _count(F.col("status") == "dirty")
    return states.where(LIVE).agg((n - invalid).alias("compared"), (dirty + invalid).alias("committed"), (n + dirty).alias("by_model"))


def ledger_bytes(states: DataFrame, algo: str) -> DataFrame:
    """Bytes of digests and their share of the state."""
    n, size = F.count(F.lit(1)) * WIDTH[algo], F.sum("block_len")
    return states.where(LIVE).agg(n.alias("ledger_bytes"), size.alias("state_bytes")).select("*", ppm(F.col("ledger_bytes"), F.col("state_bytes")).alias("share_ppm"))


def rank_skew(states: DataFrame) -> DataFrame:
    """The dirtiest rank, its share, the mean of all ranks and their ratio per thousand."""
    per = dirty_share(states, "rank")
    most = per.agg(F.max(F.struct("block_ppm", (-F.col("rank")).alias("r"))).alias("m"), F.sum("n_written").alias("w"), F.sum("n_blocks").alias("n"))
    return most.select((-F.col("m.r")).alias("rank"), F.col("m.block_ppm").alias("most_ppm"), ppm(F.col("w"), F.col("n")).alias("mean_ppm"), F.when(F.col("w") > 0, (F.col("m.block_ppm") * F.col("n") / (F.col("w") * 1000)).cast("bigint")).alias("ratio_permille"))


def space_time(states: DataFrame) -> DataFrame:
    """Share of written blocks by version and rank; ``states`` has a version."""
    return dirty_share(states, "version", "rank").select("version", "rank", "block_ppm")


def space_time_map(states: DataFrame, ranks: int) -> DataFrame:
    """The same as a matrix, a column for each rank."""
    return space_time(states).groupBy("version").pivot("rank", list(range(ranks))).agg(F.first("block_ppm"))


def chunk_cdf(regions: DataFrame) -> DataFrame:
    """For each region size: regions and bytes in regions up to it, per million. Sizes are summed first, so the windows run over different sizes only."""
    sizes = regions.groupBy("n_bytes").agg(F.count(F.lit(1)).alias("n"))
    order = Window.orderBy("n_bytes").rowsBetween(Window.unboundedPreceding, 0)
    whole = Window.partitionBy()
    size = F.col("n") * F.col("n_bytes")
    return sizes.select("n_bytes", "n", ppm(F.sum("n").over(order), F.sum("n").over(whole)).alias("by_count_ppm"), ppm(F.sum(size).over(order), F.sum(size).over(whole)).alias("by_bytes_ppm"))


def chunk_quantiles(regions: DataFrame, approximate: bool = False) -> DataFrame:
    """Quartiles of region sizes."""
    if approximate:
        q = F.percentile_approx("n_bytes", [0.25, 0.5, 0.75], 10_000)
        return regions.agg(q.alias("q")).select(*[F.col("q")[k].alias(n) for k, n in enumerate(("q25", "q50", "q75"))])
    return regions.agg(*[F.expr(f"percentile_disc({p}) WITHIN GROUP (ORDER BY n_bytes)").cast("bigint").alias(n) for p, n in ((0.25, "q25"), (0.5, "q50"), (0.75, "q75"))])


def fragmentation(regions: DataFrame, *by: str) -> DataFrame:
    return regions.groupBy(*by).agg(F.count(F.lit(1)).alias("n_regions"), F.sum("n_bytes").alias("bytes"), F.expr("sum(n_bytes) div count(1)").alias("mean_bytes"), F.max("n_bytes").alias("max_bytes"))


def sparsity(filled: DataFrame) -> DataFrame:
    """Room that is not used, by version."""
    return filled.groupBy("version").agg(F.sum("container_bytes").alias("capacity"), F.sum("chunk_bytes").alias("live")).select("version", "capacity", "live", ppm(F.col("capacity") - F.col("live"), F.col("capacity")).alias("empty_ppm"))


def read_only(states: DataFrame, by_block: bool = False) -> DataFrame:
    """Datasets (or blocks) that were clean at every version."""
    keys = ["rank", "dataset_id", *(["block_no"] if by_block else [])]
    return states.where(LIVE).groupBy(*keys).agg(F.bool_and(F.col("status") == "clean").alias("read_only")).where("read_only").select(*keys)


def sizes(catalogue: DataFrame) -> DataFrame:
    """Number and size of datasets, by rank and in all (rank null)."""
    return catalogue.rollup("rank").agg(F.count(F.lit(1)).alias("n_datasets"), F.sum("size_bytes").alias("bytes"), F.expr("sum(size_bytes) div count(1)").alias("mean_bytes"))


def serial_overhead(serialised: DataFrame, catalogue: DataFrame) -> DataFrame:
    """Bytes of the one buffer against those of the datasets that it repeats."""
    buffer = serialised.agg((F.count(F.lit(1)) * 8).alias("buffer_bytes"))
    return buffer.crossJoin(F.broadcast(catalogue.agg(F.sum("size_bytes").alias("dataset_bytes")))).select("*", ppm(F.col("buffer_bytes"), F.col("dataset_bytes")).alias("extra_memory_ppm"))


def false_clean(by_digest: DataFrame, by_bytes: DataFrame) -> DataFrame:
    """Changed blocks that a digest calls clean."""
    keys = ["rank", "dataset_id", "block_no"]
    clean = by_digest.where(F.col("status") == "clean").select(*keys)
    dirty = by_bytes.where(F.col("status") == "dirty").select(*keys)
    return dirty.agg(F.count(F.lit(1)).alias("n_changed")).crossJoin(F.broadcast(dirty.join(clean, keys, "left_semi").agg(F.count(F.lit(1)).alias("n_missed"))))


def file_counts(manifest: dict) -> dict[str, int]:
    """Files and metadata records of a version: one of its own for each bucket, or for each rank with a sidecar."""
    own = [f for f in manifest["files"] if f["version"] == manifest["version"]]
    return {"files_referred": len(manifest["files"]), "files_written": len(own), "metadata_records": len(own) if manifest["meta"] == "embedded" else len({f["rank"] for f in own})}


def relative(runs: DataFrame) -> DataFrame:
    """Mean and spread of the time relative to the mean of the baseline runs; ``runs`` has workload, method and seconds, the baseline is ``off``."""
    base = runs.where(F.col("method") == "off").groupBy("workload").agg(F.avg("seconds").alias("t0"))
    change = runs.join(base, "workload").withColumn("d", F.col("seconds") / F.col("t0") - 1)
    return change.groupBy("workload", "method").agg(F.avg("d").alias("change"), F.coalesce(F.stddev("d"), F.lit(0.0)).alias("spread"), F.count(F.lit(1)).alias("n"))


def model_error(runs: DataFrame) -> DataFrame:
    """Measured less predicted change; ``runs`` has workload, dirty_share, rho and change."""
    return runs.select("workload", "change", speedup(F.col("dirty_share"), F.col("rho")).alias("predicted")).withColumn("error", F.col("change") - F.col("predicted"))


def sampled_share(blocks: DataFrame, modulus: int) -> DataFrame:
    """Blocks of a sample fixed by their keys: one in ``modulus``, the same ones at each version."""
    return blocks.where(F.pmod(F.col("block_no") * 2654435761 + F.col("rank") * 40503, F.lit(modulus)) == 0)
