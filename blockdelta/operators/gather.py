"""Gathering small regions into write units of at least a target size."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

ORDER = ["dataset_id", "region_no"]


def pack(regions: DataFrame, target: int = 16 << 20, mode: str = "greedy") -> DataFrame:
    """regions with unit_no. A unit is written as soon as it exceeds ``target``; what is left at the end of a rank is the last unit.

    ``greedy`` goes through each rank's regions in order, batch by batch; a task holds one batch and two numbers, however many regions a
    rank has. ``cutline`` cuts the running sum at multiples of the target instead: units a little less even.
    """
    if mode == "cutline":
        before = Window.partitionBy("rank").orderBy(*ORDER)
        start = F.sum("n_bytes").over(before.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n_bytes")
        return regions.select("*", (start / target).cast("bigint").alias("unit_no"))
    if mode != "greedy":
        raise ValueError(mode)

    def number(batches: Iterator) -> Iterator:
        import pyarrow as pa

        rank, unit, held = None, 0, 0
        for batch in batches:
            units = []
            for own, size in zip(batch.column("rank").to_pylist(), batch.column("n_bytes").to_pylist()):
                if own != rank:
                    rank, unit, held = own, 0, 0
                elif held > target:
                    unit, held = unit + 1, 0
                held += size
                units.append(unit)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(units, pa.int64())], names=[*batch.schema.names, "unit_no"])

    ordered = regions.repartition("rank").sortWithinPartitions("rank", *ORDER)
    return ordered.mapInArrow(number, regions.select("*", F.lit(0).cast("bigint").alias("unit_no")).schema)


def units(packed: DataFrame) -> DataFrame:
    return packed.groupBy("rank", "unit_no").agg(F.sum("n_bytes").alias("unit_bytes"), F.count(F.lit(1)).alias("n_regions"))
