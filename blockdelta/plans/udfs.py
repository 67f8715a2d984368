"""Python forms of operators for use from SQL text and for reference; none of them is on the engine's own path."""

from __future__ import annotations

import hashlib
import zlib

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf


def register_regions_udtf(spark: SparkSession, name: str = "dirty_regions") -> None:
    """``dirty_regions(TABLE(states) PARTITION BY (rank, dataset_id) ORDER BY block_no)``: the runs of one dataset, a row at a time."""

    @udtf(returnType="rank int, dataset_id string, first_block bigint, n_bytes bigint, n_blocks bigint")
    class Regions:
        def __init__(self):
            self.run = None

        def eval(self, row):
            if row["status"] not in ("dirty", "invalid"):
                return
            if self.run and self.run[2] + self.run[4] == row["block_no"]:
                self.run[3] += row["block_len"]
                self.run[4] += 1
                return
            if self.run:
                yield tuple(self.run)
            self.run = [row["rank"], row["dataset_id"], row["block_no"], row["block_len"], 1]

        def terminate(self):
            if self.run:
                yield tuple(self.run)

    spark.udtf.register(name, Regions)


def grouped_md5(cells: DataFrame, b: int) -> DataFrame:
    """Block digests by a grouped aggregate over (pos, cell) in Arrow batches."""

    @pandas_udf("string")
    def md5_of(pos: pd.Series, cell: pd.Series) -> str:
        ordered = cell.to_numpy()[pos.to_numpy().argsort()]
        return hashlib.md5(ordered.astype(">i8").tobytes()).hexdigest()

    return cells.groupBy("rank", "dataset_id", F.expr(f"pos * 8 div {b}").alias("block_no")).agg(md5_of("pos", "cell").alias("digest"))


def adler32_reference():
    """Adler32 of a BINARY column by zlib, for comparison."""

    @pandas_udf("bigint")
    def adler32(payload: pd.Series) -> pd.Series:
        return payload.map(zlib.adler32)

    return adler32
