"""uniform_sample: matches among one record in a hundred, scaled up."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...plans.workloads import digest
from ..exact import count_patterns


def fit(strings: DataFrame, one_in: int = 100) -> DataFrame:
    return strings.filter(digest("smp|", F.col("sid")) % one_in < 1)


def estimate(patterns: DataFrame, sample: DataFrame, one_in: int = 100) -> DataFrame:
    """patterns (pid, kind, lit) with est, 1 at least."""
    counted = count_patterns(sample, patterns)
    return counted.withColumn("est", F.greatest(F.lit(1.0), (F.col("true_n") * one_in).cast("double"))).drop("true_n")
