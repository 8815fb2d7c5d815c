"""ngram_signature: counts and min-hash signatures of the records that hold each gram."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...plans.workloads import digest


def grams(s, n: int):
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.length(s) - n + 1), lambda i: F.substring(s, i, n)))


def fit(strings: DataFrame, n: int = 3, sig: int = 64, portable: bool = False) -> DataFrame:
    """(gram, n, sig array): grams of 1 to n characters; minima of `sig` hashes
    of record ids, taken with partial sums. portable hashes can be redrawn by
    other engines."""
    rows = strings.filter("s != ''")
    flat = None
    for size in range(1, n + 1):
        part = rows.filter(F.length("s") >= size).select("sid", F.explode(grams(F.col("s"), size)).alias("gram"))
        flat = part if flat is None else flat.unionByName(part)
    h = (lambda i: digest(f"{i}|", F.col("sid"))) if portable else (lambda i: F.xxhash64("sid", F.lit(i)))
    if portable:
        flat = flat.join(rows.select("sid", *[h(i).alias(f"h{i}") for i in range(sig)]), "sid")
        h = lambda i: F.col(f"h{i}")
    minima = [F.min(h(i)).alias(f"m{i}") for i in range(sig)]
    out = flat.groupBy("gram").agg(F.count("*").alias("n"), *minima)
    return out.select("gram", "n", F.array(*[f"m{i}" for i in range(sig)]).alias("sig"))


def estimate(patterns: DataFrame, table: DataFrame, n: int = 3, sig: int = 64) -> DataFrame:
    """patterns (pid, lit, ...) with est: the resemblance of the literal's grams
    times the size of their union; 1 where a gram is unknown."""
    parts = F.when(F.length("lit") <= n, F.array("lit")).otherwise(grams(F.col("lit"), n))
    flat = patterns.select("pid", F.explode(parts).alias("gram"))
    met = flat.join(table, "gram", "left")
    own = met.groupBy("pid").agg(
        F.count("*").alias("k"), F.count("n").alias("known"), F.max("n").alias("most"), F.max_by("sig", F.struct("n", "gram")).alias("top"),
        F.array(*[F.min(F.col("sig")[i]) for i in range(sig)]).alias("low"), F.array(*[F.max(F.col("sig")[i]) for i in range(sig)]).alias("high"),
    )
    same = F.size(F.filter(F.zip_with("low", "high", lambda a, b: a == b), lambda x: x)) / sig
    part = F.size(F.filter(F.zip_with("low", "top", lambda a, b: a == b), lambda x: x)) / sig
    union = F.col("most") / F.greatest(part, F.lit(1.0 / sig))
    est = F.when(F.col("known") < F.col("k"), 1.0).when(F.col("k") == 1, F.col("most").cast("double")).otherwise(F.greatest(F.lit(1.0), same * union))
    return patterns.join(own.select("pid", est.alias("est")), "pid", "left")
