"""Statistics of string sets and catalogs, and the report of capabilities."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def describe(strings: DataFrame) -> DataFrame:
    """n_rows, n_distinct, vocabulary, avg_len and max_len of a set."""
    rows = strings.groupBy("s").agg(F.count("*").alias("w"))
    vocabulary = rows.select(F.explode(F.split("s", "")).alias("ch")).filter("ch != ''").agg(F.countDistinct("ch").alias("vocabulary"))
    stats = rows.agg(F.sum("w").alias("n_rows"), F.count("*").alias("n_distinct"), F.round(F.sum(F.length("s") * F.col("w")) / F.sum("w"), 6).alias("avg_len"), F.max(F.length("s")).alias("max_len"))
    return stats.join(F.broadcast(vocabulary))


def tier_shares(catalog: DataFrame) -> DataFrame:
    """(kind, tier, n_keys, share): percent of a kind's keys in each tier."""
    counts = catalog.groupBy("kind", "tier").agg(F.count("*").alias("n_keys"))
    return counts.withColumn("share", F.round(100 * F.col("n_keys") / F.sum("n_keys").over(Window.partitionBy("kind")), 6))


def top_per_tier(catalog: DataFrame, k: int = 3) -> DataFrame:
    """The k most frequent keys of each tier, ties by key. Spark turns the filter
    on the rank into a group limit before the shuffle, so each task sends k rows
    a tier at most."""
    rank = F.row_number().over(Window.partitionBy("kind", "tier").orderBy(F.desc("n"), "key"))
    return catalog.withColumn("rank", rank).filter(F.col("rank") <= k).select("kind", "tier", "key", "n", "rank")


#: What each method answers and promises; its measures come from a study.
CAPABILITIES = [
    ("tier_filters", "P,S,C", True), ("dbms_heuristic", "P,S,C", False), ("pruned_suffix_tree", "C", False),
    ("ngram_signature", "C", False), ("sample_bitmap_net", "P,S,C", False), ("embedding_net", "P,S,C", False),
    ("sequence_net", "P,S,C", False), ("hybrid_frequent_gram", "P,S,C", False), ("compact_text_index", "C", False),
]


def capabilities(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(CAPABILITIES, "method string, kinds string, error_bound boolean")
