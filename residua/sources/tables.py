"""Scans: the given tables by declared columns, edge lists in several formats, and sinks for results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGES = "src long, dst long, cap long"


def read(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A table of the data set, only the columns asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def read_edges(spark: SparkSession, path: str, fmt: str = "csv") -> tuple[DataFrame, DataFrame]:
    """Edges and rejected lines of a CSV, JSON, Parquet or white-space separated text edge list."""
    if fmt == "parquet":
        raw = spark.read.schema(EDGES).parquet(path).withColumn("line", F.lit(None).cast("string"))
    elif fmt == "text":
        part = F.split(F.trim("value"), r"\s+")
        raw = spark.read.text(path).select(*[F.expr(f"try_cast(try_element_at(split(trim(value), '\\\\s+'), {k + 1}) as bigint)").alias(n) for k, n in enumerate(("src", "dst", "cap"))], F.when(F.size(part) >= 1, F.col("value")).alias("line"))
    else:
        raw = spark.read.schema(EDGES + ", line string").option("mode", "PERMISSIVE").option("columnNameOfCorruptRecord", "line").format(fmt).load(path)
    bad = "src is null or dst is null or cap is null or cap < 0"
    return raw.where(f"not ({bad})").select("src", "dst", "cap"), raw.where(bad)


def write_edges(arcs: DataFrame, path: str, fmt: str = "parquet") -> None:
    arcs.select("src", "dst", "cap").write.mode("overwrite").format(fmt).save(path)
