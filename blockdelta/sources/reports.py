"""Reports of measures in formats that other tools read."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.types import StructType

from ..session import fresh_folder

FORMATS = ("csv", "json", "orc")


def write(report: DataFrame, form: str, path: str | None = None) -> str:
    """Writes a report and gives its folder."""
    if form not in FORMATS:
        raise ValueError(form)
    path = path or fresh_folder(report.sparkSession, f"report-{form}")
    writer = report.write.option("header", "true") if form == "csv" else report.write
    writer.format(form).save(path)
    return path


def read(spark: SparkSession, path: str, form: str, schema: StructType) -> DataFrame:
    reader = spark.read.schema(schema)
    return (reader.option("header", "true") if form == "csv" else reader).format(form).load(path)
