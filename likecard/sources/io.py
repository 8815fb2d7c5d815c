"""Tables and patterns in, models and catalogs out."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import schemas


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str | Column) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def patterns_from_list(spark: SparkSession, patterns: list[tuple[str, str]]) -> DataFrame:
    """(pid, kind, lit) of (kind, literal) pairs."""
    return spark.createDataFrame([(i, k, lit) for i, (k, lit) in enumerate(patterns)], schemas.PATTERNS)


def read_strings(spark: SparkSession, path: str, fmt: str, column: str = "value", **options) -> DataFrame:
    """(sid, s) from text, csv, json, orc or parquet files."""
    df = spark.read.format(fmt).options(**options).load(path)
    return df.select(F.monotonically_increasing_id().alias("sid"), F.col(column).cast("string").alias("s"))


def read_patterns(spark: SparkSession, path: str, fmt: str, column: str = "value", **options) -> DataFrame:
    """(pid, pattern) of LIKE texts from files."""
    return read_strings(spark, path, fmt, column, **options).toDF("pid", "pattern")


def save_catalog(catalog: DataFrame, name: str, buckets: int = 64) -> None:
    """A catalog as a table bucketed and sorted by key, so joins on keys need no shuffle."""
    catalog.write.bucketBy(buckets, "key").sortBy("key").mode("overwrite").saveAsTable(name)
