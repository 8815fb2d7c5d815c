"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def ratio_error(est: Column, true: Column) -> Column:
    e, t = F.greatest(est.cast("double"), F.lit(1.0)), F.greatest(true.cast("double"), F.lit(1.0))
    return F.greatest(e / t, t / e)


def summary(evaluated: DataFrame, *by: str) -> DataFrame:
    """Mean and 50th, 90th, 99th and 100th percentile of ratio_error, exact."""
    e = F.col("ratio_error")
    cells = [F.count("*").alias("n"), F.round(F.avg(e), 6).alias("mean")]
    cells += [F.round(F.percentile(e, F.lit(q)), 6).alias(name) for q, name in ((0.5, "p50"), (0.9, "p90"), (0.99, "p99"))]
    return evaluated.groupBy(*by).agg(*cells, F.round(F.max(e), 6).alias("max"))


def sketch_summary(evaluated: DataFrame, *by: str, accuracy: int = 10_000) -> DataFrame:
    """As summary, percentiles by mergeable sketches: for very many patterns."""
    e = F.col("ratio_error")
    return evaluated.groupBy(*by).agg(F.count("*").alias("n"), F.avg(e).alias("mean"), F.percentile_approx(e, [0.5, 0.9, 0.99], accuracy).alias("quantiles"), F.max(e).alias("max"))


def by_length(evaluated: DataFrame, *by: str) -> DataFrame:
    return evaluated.groupBy(*by, F.length("key").alias("len")).agg(F.count("*").alias("n"), F.round(F.avg("ratio_error"), 6).alias("mean"))


def by_tier(evaluated: DataFrame, scheme, *by: str) -> DataFrame:
    return evaluated.groupBy(*by, scheme.tier_col(F.col("true_n")).alias("true_tier")).agg(F.count("*").alias("n"), F.round(F.avg("ratio_error"), 6).alias("mean"))


def empty_hit_rate(evaluated: DataFrame, *by: str) -> DataFrame:
    """Shares of patterns that match nothing whose estimate is under 2, and whose tier is 1."""
    return evaluated.filter("true_n = 0").groupBy(*by).agg(F.count("*").alias("n"), F.avg((F.col("est") < 2).cast("double")).alias("under_two"), F.avg((F.col("tier") == 1).cast("double")).alias("tier_one"))


def plan_impact(times: DataFrame, baseline: str) -> DataFrame:
    """times: (query, method, seconds), several runs each. Per method: queries
    improved and degraded against the baseline, the mean change of each in
    percent, and total seconds, on mean times."""
    mean = times.groupBy("query", "method").agg(F.avg("seconds").alias("s"))
    base = mean.filter(F.col("method") == baseline).select("query", F.col("s").alias("b"))
    change = mean.join(base, "query").withColumn("change", (F.col("s") - F.col("b")) / F.col("b") * 100)
    return change.groupBy("method").agg(
        F.count_if(F.col("change") < 0).alias("improved"),
        F.avg(F.when(F.col("change") < 0, -F.col("change"))).alias("improved_pct"),
        F.count_if(F.col("change") > 0).alias("degraded"),
        F.avg(F.when(F.col("change") > 0, F.col("change"))).alias("degraded_pct"),
        F.sum("s").alias("total_s"),
    )
