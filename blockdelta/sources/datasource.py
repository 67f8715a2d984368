"""``spark.read.format("blockstore")``: a version of a store as a table of blocks, one input partition for each bucket file.

Options: ``path``; ``version`` (the latest by default); ``rank`` to read one rank only. Files are opened on the executors through Arrow's file systems,
so the path must be one that these know; ``restore.blocks`` reads through Spark's own readers and has no such limit.
"""

from __future__ import annotations

import json

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Bucket(InputPartition):
    def __init__(self, folder: str, rank: int):
        self.folder, self.rank = folder, rank


def _open(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path if "://" in path else f"file://{path.removeprefix('file:')}")


class BlockReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.version, self.rank = options["path"].rstrip("/"), options.get("version"), options.get("rank")

    def _manifest(self) -> dict:
        from pyarrow import fs as arrow

        fs, root = _open(f"{self.path}/manifests")
        version = self.version
        if version is None:
            names = [f.base_name for f in fs.get_file_info(arrow.FileSelector(root)) if f.base_name.startswith("v") and f.base_name.endswith(".json")]
            version = max(int(n[1:-5]) for n in names)
        with fs.open_input_stream(f"{root}/v{version}.json") as source:
            return json.loads(source.read())

    def partitions(self):
        made = self._manifest()
        if made["chain"]:
            raise ValueError("a delta chain is merged by restore.blocks")
        return [_Bucket(f"{self.path}/data/{f['dir']}/rank={f['rank']}/bucket={f['bucket']}", f["rank"]) for f in made["files"] if self.rank is None or int(self.rank) == f["rank"]]

    def read(self, partition):
        import pyarrow.dataset as ds

        fs, root = _open(partition.folder)
        for batch in ds.dataset(root, format="parquet", filesystem=fs).to_batches(columns=["dataset_id", "block_no", "block_len", "payload"]):
            for row in batch.to_pylist():
                yield partition.rank, row["dataset_id"], row["block_no"], row["block_len"], row["payload"]


class BlockSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "blockstore"

    def schema(self) -> str:
        return "rank int, dataset_id string, block_no bigint, block_len bigint, payload binary"

    def reader(self, schema):
        return BlockReader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(BlockSource)
