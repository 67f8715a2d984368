"""The file layout of datasets whose sizes change: containers of fixed size and place, filled as one space."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

OWN = ["rank", "dataset_id"]


def plan(sizes: DataFrame) -> DataFrame:
    """containers (.., container_no, born_version, container_bytes, virtual_start) from sizes (rank, dataset_id, version, size_bytes).

    A version that exceeds all room so far adds one container for the excess; none ever changes or goes.
    """
    past = Window.partitionBy(*OWN).orderBy("version").rowsBetween(Window.unboundedPreceding, -1)
    room = F.coalesce(F.max("size_bytes").over(past), F.lit(0).cast("bigint"))
    grown = sizes.withColumn("room", room).where("size_bytes > room")
    number = F.row_number().over(Window.partitionBy(*OWN).orderBy("version"))
    return grown.select(*OWN, number.alias("container_no"), F.col("version").alias("born_version"), (F.col("size_bytes") - F.col("room")).alias("container_bytes"), F.col("room").alias("virtual_start"))


def place(containers: DataFrame, meta_bytes: int = 64) -> DataFrame:
    """With file_offset: containers of a version follow all earlier ones, each version behind a metadata block with an entry for each of its containers."""
    order = Window.partitionBy("rank").orderBy("born_version", "dataset_id").rowsBetween(Window.unboundedPreceding, 0)
    meta = F.count(F.lit(1)).over(Window.partitionBy("rank").orderBy("born_version")) * meta_bytes
    offset = F.sum("container_bytes").over(order) - F.col("container_bytes") + meta
    return containers.select("*", offset.alias("file_offset"))


def fill(containers: DataFrame, sizes: DataFrame) -> DataFrame:
    """chunk_bytes of each container at each version from its birth on: containers fill in order, the rest stays empty."""
    both = sizes.join(containers, OWN).where("born_version <= version")
    chunk = F.greatest(F.lit(0).cast("bigint"), F.least(F.col("container_bytes"), F.col("size_bytes") - F.col("virtual_start")))
    return both.select(*OWN, "version", "container_no", chunk.alias("chunk_bytes"), "container_bytes")


def chunk_meta(filled: DataFrame) -> DataFrame:
    """The nested metadata block of each rank and version."""
    entry = F.struct("dataset_id", "container_no", "chunk_bytes", "container_bytes")
    return filled.groupBy("rank", "version").agg(F.sort_array(F.collect_list(entry)).alias("entries"))


def extents(regions: DataFrame, placed: DataFrame) -> DataFrame:
    """Where regions lie in the file: split at container edges. Containers are few next to regions; Spark broadcasts them if they are small."""
    held = placed.select(*OWN, "container_no", "container_bytes", "virtual_start", "file_offset")
    end = F.col("start_byte") + F.col("n_bytes")
    met = regions.join(held, OWN).where((F.col("start_byte") < F.col("virtual_start") + F.col("container_bytes")) & (end > F.col("virtual_start")))
    first = F.greatest("start_byte", "virtual_start")
    last = F.least(end, F.col("virtual_start") + F.col("container_bytes"))
    return met.select(*OWN, "region_no", "container_no", (F.col("file_offset") + first - F.col("virtual_start")).alias("file_offset"), (last - first).alias("n_bytes"))
