"""Frontier pruning: tier-1 keys without a shorter prefix in tier 1."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def reduce(catalog: DataFrame) -> DataFrame:
    """The catalog without covered tier-1 keys. Counts fall along prefixes, so a
    tier-1 key is covered exactly if its parent, one character shorter, is in
    tier 1."""
    parent = catalog.filter("tier = 1").select(F.col("key").alias("_parent"))
    ones = catalog.filter("tier = 1").withColumn("_up", F.expr("left(key, len - 1)"))
    kept = ones.join(parent, F.col("_up") == F.col("_parent"), "left_anti").drop("_up")
    return catalog.filter("tier > 1").unionByName(kept)
