"""Reading a version back, and checking it."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..operators.blocks import KEYS, uncut
from .store import BlockStore, StoreError

_FILE = "rank int, bucket long, version int"


def _files(store: BlockStore, manifest: dict, ranks: list[int] | None) -> DataFrame:
    """The rows of all files that a manifest names, with the version they were written in; only the ranks asked for are read."""
    spark, parts = store.spark, []
    for folder, version in sorted({(f["dir"], f["version"]) for f in manifest["files"]}, key=lambda x: (x[1], x[0])):
        buckets = [(f["rank"], f["bucket"]) for f in manifest["files"] if f["dir"] == folder and (ranks is None or f["rank"] in ranks)]
        if not buckets:
            continue
        paths = [f"{store.path}/data/{folder}/rank={r}/bucket={k}" for r, k in buckets]
        data = spark.read.option("basePath", f"{store.path}/data/{folder}").parquet(*paths)
        parts.append(data.select(F.col("rank").cast("int").alias("rank"), F.col("bucket").cast("bigint").alias("bucket"), "dataset_id", "block_no", "block_len", "payload", "gone", F.lit(version).alias("version")))
    if not parts:
        return spark.createDataFrame([], f"rank int, bucket long, dataset_id string, block_no long, block_len long, payload binary, gone boolean, version int")
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def merge_chain(rows: DataFrame) -> DataFrame:
    """The newest image of each block; blocks whose newest entry says that they are gone are left out."""
    newest = rows.groupBy(*KEYS).agg(F.max_by(F.struct("block_len", "payload", "gone"), "version").alias("m"))
    return newest.where("not m.gone").select(*KEYS, "m.block_len", "m.payload")


def blocks(store: BlockStore, version: int | None = None, ranks: list[int] | None = None, datasets: list[str] | None = None) -> DataFrame:
    """blocks of a version (the latest, if none is named)."""
    version = store.latest() if version is None else version
    if version is None:
        raise StoreError("the store is empty")
    manifest = store.manifest(version)
    rows = _files(store, manifest, ranks)
    if datasets is not None:
        rows = rows.where(F.col("dataset_id").isin(datasets))
    return merge_chain(rows) if manifest["chain"] else rows.select(*KEYS, "block_len", "payload")


def read(store: BlockStore, version: int | None = None, ranks: list[int] | None = None, datasets: list[str] | None = None) -> DataFrame:
    """cells of a version."""
    return uncut(blocks(store, version, ranks, datasets), store.b)


def read_sized(store: BlockStore, sizes: DataFrame, version: int | None = None) -> DataFrame:
    """cells cut to the sizes (rank, dataset_id, size_bytes) that the layout's metadata gives."""
    return read(store, version).join(sizes.select("rank", "dataset_id", "size_bytes"), ["rank", "dataset_id"]).where("pos * 8 < size_bytes").drop("size_bytes")


def verify(store: BlockStore, version: int) -> DataFrame:
    """(rank, bucket, version, ok) of each file: what is there against the checksums in the manifest. Missing files are not ok."""
    manifest, spark = store.manifest(version), store.spark
    expected = spark.createDataFrame([(f["rank"], f["bucket"], f["version"], f["dir"], f["checksum"]) for f in manifest["files"]], f"{_FILE}, dir string, checksum string")
    found = None
    for folder in sorted({f["dir"] for f in manifest["files"]}):
        if store._exists(f"{store.path}/data/{folder}"):
            part = store._checksums(spark.read.parquet(f"{store.path}/data/{folder}")).select(F.col("rank").cast("int").alias("rank"), F.col("bucket").cast("bigint").alias("bucket"), F.lit(folder).alias("dir"), F.col("checksum").alias("now"))
            found = part if found is None else found.unionByName(part)
    if found is None:
        return expected.select("rank", "bucket", "version", F.lit(False).alias("ok"))
    return expected.join(found, ["rank", "bucket", "dir"], "left").select("rank", "bucket", "version", F.coalesce(F.col("now") == F.col("checksum"), F.lit(False)).alias("ok"))


def require_sound(store: BlockStore, version: int) -> None:
    """Raises unless every file of the version is whole."""
    broken = verify(store, version).where("not ok").limit(3).collect()
    if broken:
        raise StoreError(f"version {version} is damaged: " + ", ".join(f"rank {r['rank']} bucket {r['bucket']}" for r in broken))


def asof(versions: DataFrame, asked: DataFrame) -> DataFrame:
    """For each (asked_at), the version in force: the last one committed at or before it."""
    met = asked.join(versions, F.col("committed_at") <= F.col("asked_at"), "left")
    return met.groupBy("asked_at").agg(F.max_by("version", "committed_at").alias("version"))


def size_history(sizes: DataFrame) -> DataFrame:
    """Sizes with the change since the version before."""
    order = Window.partitionBy("rank", "dataset_id").orderBy("version")
    return sizes.select("*", (F.col("size_bytes") - F.coalesce(F.lag("size_bytes").over(order), F.lit(0))).alias("growth"))
