"""Patterns longer than the model's literals: a Markov chain over windows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import cut


def windows(key: Column, max_len: int) -> Column:
    """Array of (win, ctx): each character after the first max_len with the
    max_len - 1 before it, and those alone."""
    at = F.sequence(F.lit(2), F.length(key) - max_len + 1)
    return F.transform(at, lambda i: F.struct(F.substring(key, i, max_len).alias("win"), F.substring(key, i, max_len - 1).alias("ctx")))


def estimate(patterns: DataFrame, kind: str, max_len: int, estimate_head, estimate_inner, clamp: bool = False, floor: float = 1.0) -> DataFrame:
    """patterns (pid, key longer than max_len, ...) with est.

    key is in canonical form (reversed for suffixes). estimate_head and
    estimate_inner map (pid, key) frames to (pid, key, est): the model of the
    kind for the first max_len characters, the substring model for windows. Each
    different window is estimated once. est is the head times the product of
    win / ctx; clamp keeps each ratio at 1 at most and the result between floor
    and the least window estimate.
    """
    head = estimate_head(patterns.select("pid", F.substring("key", 1, max_len).alias("key"))).select("pid", F.col("est").alias("head"))
    steps = patterns.select("pid", F.explode(windows(F.col("key"), max_len)).alias("w")).select("pid", "w.win", "w.ctx")
    inner = F.reverse if kind == "S" else (lambda c: c)
    steps = steps.select("pid", inner(F.col("win")).alias("win"), inner(F.col("ctx")).alias("ctx"))
    needed = steps.select(F.explode(F.array("win", "ctx")).alias("key")).distinct().withColumn("pid", F.xxhash64("key"))
    known = cut(estimate_inner(needed).select("key", "est"))
    rated = steps.join(known.select(F.col("key").alias("win"), F.col("est").alias("ew")), "win").join(known.select(F.col("key").alias("ctx"), F.col("est").alias("ec")), "ctx")
    ratio = F.col("ew") / F.col("ec")
    ratio = F.least(ratio, F.lit(1.0)) if clamp else ratio
    product = rated.groupBy("pid").agg(F.product(ratio).alias("r"), F.min("ew").alias("least"))
    out = patterns.join(head, "pid").join(product, "pid")
    est = F.col("head") * F.col("r")
    if clamp:
        est = F.greatest(F.lit(floor), F.least(est, F.col("least")))
    return out.withColumn("est", est).drop("head", "r", "least")
