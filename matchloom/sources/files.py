"""Edge lists and coordinate matrices from files, and results to files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..edges import canonical_edges

EDGE_SCHEMA = "u long, v long, w double"


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", combine: str = "sum", nonpositive: str = "drop") -> DataFrame:
    """``parquet``, ``json``, ``csv`` (u,v,w with header), ``text`` (three columns apart by white
    space, # comments) or ``matrix`` (coordinate format: % comments, a size line, i j [value];
    absolute values become weights, the diagonal goes)."""
    if fmt in ("parquet", "json"):
        raw = spark.read.format(fmt).schema(EDGE_SCHEMA).load(path)
    elif fmt == "csv":
        raw = spark.read.schema(EDGE_SCHEMA).option("header", "true").csv(path)
    elif fmt in ("text", "matrix"):
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where(~F.col("value").rlike("^\\s*([#%]|$)")).withColumn("p", parts)
        if fmt == "matrix":  # the size line is the only one whose entries exceed the file's own indices
            size = spark.read.text(path).where(~F.col("value").rlike("^\\s*(%|$)")).limit(1).first()[0]
            lines = lines.where(F.col("value") != F.lit(size))
        raw = lines.select(F.col("p")[0].cast("long").alias("u"), F.col("p")[1].cast("long").alias("v"), F.when(F.size("p") > 2, F.col("p")[2].cast("double")).otherwise(F.lit(1.0)).alias("w"))
        if fmt == "matrix":
            return canonical_edges(raw, combine="max", nonpositive="abs").where("w > 0")
    else:
        raise ValueError(f"unknown format {fmt}")
    return canonical_edges(raw, combine=combine, nonpositive=nonpositive)


def write_result(df: DataFrame, path: str, mode: str = "overwrite", partition_by: tuple[str, ...] = (), bucket_by: tuple[int, str] | None = None, table: str | None = None) -> None:
    """Parquet files, or with ``bucket_by`` (number, column) a bucketed table of that name."""
    writer = df.write.mode(mode).partitionBy(*partition_by) if partition_by else df.write.mode(mode)
    if bucket_by:
        writer.bucketBy(bucket_by[0], bucket_by[1]).sortBy(bucket_by[1]).option("path", path).saveAsTable(table)
    else:
        writer.parquet(path)
