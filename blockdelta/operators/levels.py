"""Reliability levels: local, replica, parity over a group of ranks, shared store."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..session import fresh_folder


def parity(cells: DataFrame, group_size: int) -> DataFrame:
    """Bitwise sums over the ranks of a group, position by position; shorter ranks count as zeros."""
    group = F.expr(f"rank div {group_size}")
    return cells.groupBy(group.cast("int").alias("group_no"), "dataset_id", "pos").agg(F.bit_xor("cell").alias("cell"))


def rebuild(parity_cells: DataFrame, survivors: DataFrame, lost_rank: int, group_size: int, size_cells: DataFrame | None = None) -> DataFrame:
    """The cells of one lost rank; ``size_cells`` (dataset_id, n_cells) cuts off what other ranks had beyond it."""
    group = lost_rank // group_size
    others = survivors.where((F.expr(f"rank div {group_size}") == group) & (F.col("rank") != lost_rank)).select("dataset_id", "pos", "cell")
    own = parity_cells.where(F.col("group_no") == group).select("dataset_id", "pos", "cell")
    cells = own.unionByName(others).groupBy("dataset_id", "pos").agg(F.bit_xor("cell").alias("cell"))
    if size_cells is not None:
        cells = cells.join(size_cells, "dataset_id").where("pos < n_cells").drop("n_cells")
    return cells.select(F.lit(lost_rank).alias("rank"), "dataset_id", "pos", "cell")


def post_process(cells: DataFrame, level: int, group_size: int = 4) -> dict[str, str]:
    """Writes what a level adds to the local copy; gives the folders by what they hold. Runs after hashing, apart from the application."""
    spark, made = cells.sparkSession, {}
    if level not in (1, 2, 3, 4):
        raise ValueError(f"no level {level}")
    if level == 2:
        made["replica"] = fresh_folder(spark, "replica")
        cells.write.parquet(made["replica"])
    if level == 3:
        made["parity"] = fresh_folder(spark, "parity")
        parity(cells, group_size).write.parquet(made["parity"])
    if level == 4:
        made["shared"] = fresh_folder(spark, "shared")
        cells.repartition("rank").write.partitionBy("rank").parquet(made["shared"])
    return made
