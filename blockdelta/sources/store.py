"""The versioned block store: immutable Parquet files, a ledger for each version, and one manifest whose creation is the commit.

Nothing that a committed version refers to is ever changed. Every attempt at a version writes to folders of its own, which only the
manifest names, so what a crash has left behind is in nobody's way; the commit creates the manifest, which fails if another
writer's is there. A manifest that its writer did not finish is no version, and its number is not used again. Blocks lie in
buckets, ranges of block numbers within a rank; a manifest says which folder holds each bucket. Its size grows with the number
of buckets only (about one for each I/O-sized stretch of state), never with the number of blocks.

Modes of an update: ``copy_on_write`` writes every bucket that holds a written block anew; ``delta_chain`` appends written
blocks only and restart merges the chain; ``buffered`` is a delta chain whose regions are gathered into write units first; ``full`` writes all.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import gather, regions
from ..operators.blocks import KEYS
from ..operators.tracker import CLEAN, RETIRED

MODES = ("copy_on_write", "delta_chain", "buffered", "full")
STEPS = ("start", "files", "ledger", "manifest", "promote")


class StoreError(RuntimeError):
    pass


class BlockStore:
    """A store in one folder. ``on_step`` is called with the name of each step as it is done; an exception from it stands for a crash there."""

    def __init__(self, spark: SparkSession, path: str, b: int = 16384, algo: str = "md5", bucket_blocks: int = 1024, meta: str = "embedded", on_step: Callable[[str], None] | None = None):
        if meta not in ("embedded", "sidecar"):
            raise ValueError(meta)
        self.spark, self.path, self.b, self.algo, self.bucket_blocks, self.meta = spark, path.rstrip("/"), b, algo, bucket_blocks, meta
        self.on_step = on_step or (lambda step: None)
        self._copy: Future | None = None
        self._pool = ThreadPoolExecutor(1)
        self.attempt = uuid.uuid4().hex[:12]

    def new_attempt(self) -> None:
        """Folders that are written from here on have a new name."""
        self.attempt = uuid.uuid4().hex[:12]

    # Files, through Hadoop's interface, so any store that Spark reads will do.
    def _fs(self, path: str):
        jvm = self.spark._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        return where.getFileSystem(self.spark._jsc.hadoopConfiguration()), where

    def _exists(self, path: str) -> bool:
        fs, where = self._fs(path)
        return fs.exists(where)

    def _create(self, path: str, text: str) -> None:
        """Creates a file that must not exist yet."""
        fs, where = self._fs(path)
        try:
            out = fs.create(where, False)
        except Exception as error:
            raise StoreError(f"{path} exists already or cannot be made") from error
        try:
            out.write(bytearray(text.encode()))
        finally:
            out.close()

    def _read(self, path: str) -> str:
        fs, where = self._fs(path)
        source = fs.open(where)
        try:
            return self.spark._jvm.org.apache.commons.io.IOUtils.toString(source, "UTF-8")
        finally:
            source.close()

    def _list(self, path: str) -> list[str]:
        fs, where = self._fs(path)
        return sorted(s.getPath().getName() for s in fs.listStatus(where)) if fs.exists(where) else []

    # Versions.
    def _numbers(self) -> list[int]:
        return sorted(int(n[1:-5]) for n in self._list(f"{self.path}/manifests") if n.startswith("v") and n.endswith(".json"))

    def versions(self) -> list[int]:
        """Committed versions."""
        return [v for v in self._numbers() if self._whole(v) is not None]

    def latest(self) -> int | None:
        return next((v for v in reversed(self._numbers()) if self._whole(v) is not None), None)

    def next_version(self) -> int:
        return max(self._numbers(), default=0) + 1

    def _whole(self, version: int) -> dict | None:
        try:
            return json.loads(self._read(f"{self.path}/manifests/v{version}.json"))
        except ValueError:
            return None

    def manifest(self, version: int) -> dict:
        made = self._whole(version) if version in self._numbers() else None
        if made is None:
            raise StoreError(f"no version {version}")
        return made

    def ledger(self, version: int) -> DataFrame:
        made = self.manifest(version)
        if made["algo"] != self.algo or made["block_bytes"] != self.b:
            raise StoreError(f"the ledger of version {version} is of {made['algo']} over {made['block_bytes']} bytes; a full checkpoint is needed")
        return self.spark.read.parquet(made["ledger"])

    def _bucketed(self, df: DataFrame) -> DataFrame:
        return df.withColumn("bucket", F.expr(f"block_no div {self.bucket_blocks}"))

    # The base of an update.
    def prepare_base(self, copy: Callable[[], None] | None = None, async_: bool = True) -> None:
        """Makes ready what the next update starts from, beside the application. On immutable files there is nothing to copy;
        ``copy`` stands for what a file system without them has to do, and its failure makes the next checkpoint a full one."""
        work = copy or (lambda: None)
        if async_:
            self._copy = self._pool.submit(work)
        else:
            done: Future = Future()
            try:
                done.set_result(work())
            except Exception as error:
                done.set_exception(error)
            self._copy = done

    def choose_mode(self, wanted: str = "copy_on_write", dirty_share: float | None = None, rho: float | None = None) -> str:
        """``full`` if there is no base, its copy failed, or the cost model sees no gain at this dirty share; else the wanted mode."""
        if wanted not in MODES:
            raise ValueError(wanted)
        if self.latest() is None:
            return "full"
        if self._copy is not None and self._copy.exception() is not None:
            return "full"
        if dirty_share is not None and rho is not None:
            from ..functions.costmodel import break_even

            limit = break_even(rho)
            if limit is None or dirty_share > limit:
                return "full"
        return wanted

    # Writing.
    def write_update(self, version: int, cut: Callable[[DataFrame | None], DataFrame], states: DataFrame | None, mode: str, gather_target: int | None = None) -> dict:
        """Writes the files of ``version``; gives what its manifest needs. Readers see nothing of it yet.

        ``cut`` gives the blocks of the state: all of them, or those whose rank and bucket, or keys, are in a table. Only these are cut."""
        latest = self.latest()
        base = self.manifest(latest) if latest is not None else None
        if base is None or states is None:
            mode = "full"
        if mode == "copy_on_write" and base["chain"]:
            raise StoreError("a delta chain is continued by delta_chain, buffered or full")
        self.on_step("start")
        folder = f"v{version}-{self.attempt}"
        data = f"{self.path}/data/{folder}"
        chain: list[int] = []
        if mode == "full":
            rows = self._bucketed(cut(None)).withColumn("gone", F.lit(False))
        elif mode == "copy_on_write":
            touched = self._bucketed(states.where(F.col("status") != CLEAN)).select("rank", "bucket").distinct()
            rows = self._bucketed(cut(touched)).withColumn("gone", F.lit(False))
        else:
            written = states.where(F.col("status").isin(*regions.WRITTEN)).select(*KEYS)
            gone = self._bucketed(states.where(F.col("status") == RETIRED).select(*KEYS, "block_len", F.lit(None).cast("binary").alias("payload")))
            rows = self._bucketed(cut(written)).withColumn("gone", F.lit(False)).unionByName(gone.withColumn("gone", F.lit(True)))
            chain = [*base["chain"], version]
        if mode == "buffered":
            packed = gather.pack(regions.merge(states, self.b, regions.STRIDE), gather_target or 16 << 20)
            members = regions.members(states, self.b, regions.STRIDE).join(packed.select("rank", "dataset_id", "start_byte", "unit_no"), ["rank", "dataset_id", "start_byte"])
            rows = rows.join(members.select(*KEYS, "unit_no"), KEYS, "left").withColumn("bucket", F.coalesce("unit_no", F.lit(-1))).drop("unit_no")
        # The rank and the bucket spread a hot rank over tasks; one file each keeps files few and large.
        rows.repartition("rank", "bucket").sortWithinPartitions("rank", "bucket", "dataset_id", "block_no").write.partitionBy("rank", "bucket").parquet(data)
        self.on_step("files")
        files = self._files_of(folder, version)
        if mode == "copy_on_write":
            rewritten = {(f["rank"], f["bucket"]) for f in files}
            # A touched bucket that was not written anew holds retired blocks only.
            lost = {(r["rank"], r["bucket"]) for r in touched.collect()} - rewritten
            files += [f for f in base["files"] if (f["rank"], f["bucket"]) not in rewritten and (f["rank"], f["bucket"]) not in lost]
        elif mode != "full":
            files = base["files"] + files
        return {"version": version, "parent": base["version"] if base else None, "mode": mode, "algo": self.algo, "block_bytes": self.b, "bucket_blocks": self.bucket_blocks, "meta": self.meta, "chain": chain, "dir": folder, "files": files}

    def _files_of(self, folder: str, version: int) -> list[dict]:
        """One entry for each bucket of a folder."""
        data = f"{self.path}/data/{folder}"
        if not any(n.startswith("rank=") for n in self._list(data)):
            return []
        summed = self._checksums(self.spark.read.parquet(data)).collect()
        return [{"rank": r["rank"], "bucket": r["bucket"], "version": version, "dir": folder, "bytes": r["bytes"], "blocks": r["blocks"], "checksum": r["checksum"]} for r in summed]

    def written_blocks(self, prepared: dict) -> DataFrame | None:
        """The blocks in the files that an update has just written, read back; None if it wrote none."""
        data = f"{self.path}/data/{prepared['dir']}"
        if not any(n.startswith("rank=") for n in self._list(data)):
            return None
        return self.spark.read.parquet(data).where("not gone").select(F.col("rank").cast("int").alias("rank"), "dataset_id", "block_no", "block_len", "payload")

    def _checksums(self, data: DataFrame) -> DataFrame:
        """One row for each rank and bucket: bytes, blocks and a checksum that knows nothing of the ledger's digests."""
        each = F.concat_ws(":", "dataset_id", F.col("block_no").cast("string"), F.col("block_len").cast("string"), F.coalesce(F.sha1("payload"), F.lit("gone")))
        return data.select("rank", "bucket", "block_len", each.alias("e")).groupBy("rank", "bucket").agg(F.sum("block_len").alias("bytes"), F.count(F.lit(1)).alias("blocks"), F.md5(F.expr("listagg(e, ',') WITHIN GROUP (ORDER BY e)")).alias("checksum"))

    def write_ledger(self, version: int, ledger: DataFrame) -> str:
        path = f"{self.path}/ledger/v{version}-{self.attempt}"
        ledger.write.parquet(path)
        self.on_step("ledger")
        return path

    def write_containers(self, version: int, chunk_meta: DataFrame) -> str:
        """The layout's metadata: with the version's data, or in a folder of its own for ``sidecar``."""
        folder = f"v{version}-{self.attempt}"
        where = f"{self.path}/data/{folder}/_layout" if self.meta == "embedded" else f"{self.path}/layout/{folder}"
        chunk_meta.write.parquet(where)
        return where

    def promote(self, prepared: dict, ledger_path: str, layout: str | None = None) -> int:
        """The commit: the manifest is created, which only one writer of a version can do."""
        self.on_step("manifest")
        version = prepared["version"]
        self._create(f"{self.path}/manifests/v{version}.json", json.dumps(prepared | {"ledger": ledger_path, "layout": layout, "status": "committed"}))
        self.on_step("promote")
        return version

    def _remove(self, names: Callable[[str], bool]) -> list[str]:
        """Deletes folders by name; gives their names."""
        gone = []
        for kind in ("data", "ledger", "layout"):
            for name in self._list(f"{self.path}/{kind}"):
                if names(name):
                    fs, where = self._fs(f"{self.path}/{kind}/{name}")
                    fs.delete(where, True)
                    gone.append(name)
        return gone

    def discard(self) -> None:
        """Removes what this store's current attempt has written; the driver does so when an update fails."""
        self._remove(lambda name: name.endswith(f"-{self.attempt}"))

    def rollback(self, version: int) -> None:
        """Removes what unfinished attempts at a version have left; a committed version is refused."""
        if version in self.versions():
            raise StoreError(f"version {version} is committed")
        self._remove(lambda name: name.split("-")[0] == f"v{version}")

    def vacuum(self, retain: int = 2) -> list[int]:
        """Forgets all but the last ``retain`` versions and deletes folders that none of these refers to, up to the latest version:
        attempts at later ones may be under way."""
        versions = self.versions()
        kept = {v: self.manifest(v) for v in versions[-retain:]}
        for v in versions:
            if v not in kept:
                fs, where = self._fs(f"{self.path}/manifests/v{v}.json")
                fs.delete(where, False)
        needed = {f["dir"] for made in kept.values() for f in made["files"]} | {made["dir"] for made in kept.values()} | {made["ledger"].rsplit("/", 1)[-1] for made in kept.values()}
        last = versions[-1] if versions else 0
        gone = self._remove(lambda name: name not in needed and int(name.split("-")[0][1:]) <= last)
        return sorted({int(name.split("-")[0][1:]) for name in gone})

    # A version that is completed piece by piece. Its arrivals are marked in the store, so it outlives its driver.
    def open_version(self, version: int) -> None:
        if version in self._numbers():
            raise StoreError(f"version {version} is committed already")
        if not self._exists(f"{self.path}/open/v{version}/_opened"):
            self._create(f"{self.path}/open/v{version}/_opened", "")

    def _arrivals(self, version: int) -> list[str]:
        if not self._exists(f"{self.path}/open/v{version}/_opened"):
            raise StoreError(f"version {version} is not open")
        return [n for n in self._list(f"{self.path}/open/v{version}") if n.startswith("v")]

    def _datasets(self, version: int) -> DataFrame | None:
        paths = [f"{self.path}/data/{n}" for n in self._arrivals(version)]
        paths = [p for p in paths if any(n.startswith("rank=") for n in self._list(p))]
        if not paths:
            return None
        parts = [self.spark.read.parquet(p).select(F.col("rank").cast("int").alias("rank"), "dataset_id") for p in paths]
        out = parts[0]
        for part in parts[1:]:
            out = out.unionByName(part)
        return out.distinct()

    def add(self, version: int, blocks: DataFrame) -> None:
        """Appends the datasets in ``blocks`` to an open version. Datasets that have arrived already are left out, so an ``add`` may be
        repeated; one that failed half-way has not arrived."""
        there = self._datasets(version)
        rows = self._bucketed(blocks if there is None else blocks.join(there, ["rank", "dataset_id"], "left_anti")).withColumn("gone", F.lit(False))
        folder = f"v{version}-{uuid.uuid4().hex[:12]}"
        rows.repartition("rank", "bucket").write.partitionBy("rank", "bucket").parquet(f"{self.path}/data/{folder}")
        self._create(f"{self.path}/open/v{version}/{folder}", "")

    def missing(self, version: int, catalogue: DataFrame) -> DataFrame:
        """Datasets of the catalogue that have not arrived."""
        there = self._datasets(version)
        asked = catalogue.select("rank", "dataset_id")
        return asked if there is None else asked.join(there, ["rank", "dataset_id"], "left_anti")

    def seal(self, version: int, catalogue: DataFrame, ledger: DataFrame) -> int:
        """Commits an open version; raises if a dataset is missing."""
        absent = self.missing(version, catalogue).limit(1).collect()
        if absent:
            raise StoreError(f"dataset {absent[0]['dataset_id']} of rank {absent[0]['rank']} has not arrived")
        files = [f for folder in self._arrivals(version) for f in self._files_of(folder, version)]
        prepared = {"version": version, "parent": self.latest(), "mode": "full", "algo": self.algo, "block_bytes": self.b, "bucket_blocks": self.bucket_blocks, "meta": self.meta, "chain": [], "dir": f"v{version}-{self.attempt}", "files": files}
        self.promote(prepared, self.write_ledger(version, ledger))
        fs, where = self._fs(f"{self.path}/open/v{version}")
        fs.delete(where, True)
        return version
