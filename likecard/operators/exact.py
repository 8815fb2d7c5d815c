"""True counts of patterns."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def count_by_catalog(patterns: DataFrame, catalog: DataFrame) -> DataFrame:
    """patterns (key, ...) with true_n from a catalog of their kind, 0 if absent:
    one equi-join, for literals no longer than the catalog's."""
    return patterns.join(catalog.select("key", F.col("n").alias("true_n")), "key", "left").withColumn("true_n", F.coalesce("true_n", F.lit(0)))


def count_patterns(strings: DataFrame, patterns: DataFrame, max_len: int = 10) -> DataFrame:
    """patterns (pid, kind, lit) with true_n, for literals of any length.

    A literal and a record meet on the literal's first characters, max_len at
    most (its last, for suffixes): records are exploded into their windows of
    the widths that occur, joined by equality, and only then compared whole. So
    a short literal does not widen the join of a long one.
    Kinds and empty literals: an empty literal matches every record.
    """
    rows = strings.filter("s is not null").groupBy("s").agg(F.count("*").alias("w"))
    total = rows.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("all"))
    width = F.least(F.length("lit"), F.lit(max_len))
    widths = {r.kind: sorted(r.w) for r in patterns.filter("lit != ''").groupBy("kind").agg(F.collect_set(width).alias("w")).collect()}
    parts = []
    for kind, some in widths.items():
        own = patterns.filter((F.col("kind") == kind) & (F.col("lit") != ""))
        fitting = F.filter(F.array(*map(F.lit, some)), lambda w: w <= F.length("s"))
        if kind == "C":
            spots = F.array_distinct(F.flatten(F.transform(fitting, lambda w: F.transform(F.sequence(F.lit(1), F.length("s") - w + 1), lambda i: F.col("s").substr(i, w)))))
        else:
            spots = F.transform(fitting, lambda w: F.col("s").substr(F.lit(1), w) if kind == "P" else F.col("s").substr(F.length("s") - w + 1, w))
        keyed = rows.select("s", "w", F.explode(spots).alias("k"))
        k = F.expr(f"right(lit, {max_len})") if kind == "S" else F.expr(f"left(lit, {max_len})")
        fits = {"P": F.col("s").startswith(F.col("lit")), "S": F.col("s").endswith(F.col("lit")), "C": F.col("s").contains(F.col("lit"))}[kind]
        parts.append(keyed.join(own.withColumn("k", k), "k").filter(fits).groupBy("pid").agg(F.sum("w").alias("true_n")))
    out = patterns
    if parts:
        counts = parts[0]
        for more in parts[1:]:
            counts = counts.unionByName(more)
        out = out.join(counts, "pid", "left")
    else:
        out = out.withColumn("true_n", F.lit(None).cast("long"))
    whole = out.filter("lit = ''").drop("true_n").crossJoin(F.broadcast(total)).withColumnRenamed("all", "true_n") if not patterns.filter("lit = ''").isEmpty() else None
    out = out.filter("lit != ''").withColumn("true_n", F.coalesce("true_n", F.lit(0)))
    return out.unionByName(whole) if whole is not None else out
