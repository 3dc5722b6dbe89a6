"""Sources and sinks: tables, edge lists in several formats, labels and logs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE = "u long, v long"


def read_table(spark: SparkSession, directory: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{directory.rstrip('/')}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", schema: str = EDGE) -> DataFrame:
    """parquet, orc, json, csv (u,v), text (two ids a line), adjacency (id: id id ...)."""
    if fmt in ("parquet", "orc", "json", "csv"):
        return spark.read.schema(schema).format(fmt).load(path)
    lines = spark.read.text(path).where(~F.col("value").startswith("#"))
    if fmt == "text":
        ends = F.split(F.trim("value"), r"[\s,]+")
        return lines.select(ends[0].cast("long").alias("u"), ends[1].cast("long").alias("v"))
    if fmt == "adjacency":
        head = F.split("value", ":")
        return lines.select(F.trim(head[0]).cast("long").alias("u"), F.explode(F.split(F.trim(head[1]), r"\s+")).cast("long").alias("v"))
    raise ValueError(f"unknown format: {fmt}")


def write_labels(labels: DataFrame, path: str, mode: str = "overwrite", table: str | None = None, buckets: int | None = None) -> None:
    """Parquet; with a table name and buckets, a table bucketed by vertex, which later joins need not shuffle."""
    if table and buckets:
        labels.write.mode(mode).bucketBy(buckets, "vertex").sortBy("vertex").option("path", path).saveAsTable(table)
    else:
        labels.write.mode(mode).parquet(path)
