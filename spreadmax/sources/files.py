"""Edge lists in files, and sinks for results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "src LONG, dst LONG, w DOUBLE"


def read_edges(spark: SparkSession, path: str, fmt: str = "csv", sep: str = "\t") -> DataFrame:
    """Edge lists `u v [w]` in csv (with # comments), json, text (any white space) or parquet."""
    if fmt == "csv":
        return spark.read.csv(path, sep=sep, comment="#", schema=SCHEMA, mode="PERMISSIVE").filter("src IS NOT NULL AND dst IS NOT NULL")
    if fmt == "json":
        return spark.read.json(path, schema=SCHEMA).filter("src IS NOT NULL AND dst IS NOT NULL")
    if fmt == "parquet":
        return spark.read.parquet(path)
    if fmt == "text":
        parts = F.split(F.trim("value"), r"\s+")
        cut = spark.read.text(path).filter(~F.col("value").startswith("#") & (F.trim("value") != ""))
        return cut.select(
            F.get(parts, F.lit(0)).cast("long").alias("src"),
            F.get(parts, F.lit(1)).cast("long").alias("dst"),
            F.get(parts, F.lit(2)).cast("double").alias("w"),
        )
    raise ValueError(f"unknown format {fmt}")


def write(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "errorifexists", partition_by: list[str] | None = None) -> None:
    out = df.write.mode(mode).format(fmt)
    if partition_by:
        out = out.partitionBy(*partition_by)
    out.save(path)


def save_as_table(df: DataFrame, name: str, buckets: int, by: str) -> None:
    """A bucketed and sorted catalog table: later joins on `by` need no shuffle of this side."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def from_rows(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)
