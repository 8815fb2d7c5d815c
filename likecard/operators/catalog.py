"""Exact enumeration of the literals of a string set, with record counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..sources.scratch import cut


def dedupe(strings: DataFrame) -> DataFrame:
    """(s, w): different strings and their number of records."""
    return strings.filter("s is not null").groupBy("s").agg(F.count("*").alias("w"))


def _prefixes(s: Column, max_len: int) -> Column:
    return F.transform(F.sequence(F.lit(1), F.least(F.length(s), F.lit(max_len))), lambda i: F.substring(s, 1, i))


def literals(s: Column, kind: str, max_len: int) -> Column:
    """Keys of one non-empty record, each once: its prefixes, the prefixes of
    its reverse, or its substrings, up to max_len characters."""
    if kind == "P":
        return _prefixes(s, max_len)
    if kind == "S":
        return _prefixes(F.reverse(s), max_len)
    starts = F.sequence(F.lit(1), F.length(s))
    return F.array_distinct(F.flatten(F.transform(starts, lambda i: F.transform(F.sequence(F.lit(1), F.least(F.lit(max_len), F.length(s) - i + 1)), lambda j: F.substring(s, i, j)))))


#: Characters of the pieces in which long records are enumerated.
PIECE = 512


def enumerate_keys(strings: DataFrame, kind: str, max_len: int = 10, dedupe_first: bool = True) -> DataFrame:
    """(key, len, n) of every literal up to max_len characters; n counts records,
    a record once however often it holds the literal. Counts are summed on the
    map side, so keys that most records share cost a row a task. Substrings of
    long records are taken from pieces that overlap, so no place is sought from
    the start of a long text, and counted once a record."""
    rows = dedupe(strings) if dedupe_first else strings.filter("s is not null").select("s", F.lit(1).alias("w"))
    rows = rows.filter("s != ''")
    whole = rows.filter(F.length("s") <= PIECE) if kind == "C" else rows
    flat = whole.select(F.explode(literals(F.col("s"), kind, max_len)).alias("key"), "w")
    if kind == "C":
        long = rows.filter(F.length("s") > PIECE).withColumn("r", F.monotonically_increasing_id() if not dedupe_first else F.xxhash64("s"))
        starts = F.sequence(F.lit(1), F.length("s"), F.lit(PIECE))
        pieces = long.select("r", "w", F.explode(F.transform(starts, lambda i: F.substring(F.col("s"), i, PIECE + max_len - 1))).alias("s"))
        flat = flat.unionByName(pieces.select("r", "w", F.explode(literals(F.col("s"), kind, max_len)).alias("key")).distinct().select("key", "w"))
    return flat.groupBy("key").agg(F.sum("w").alias("n")).select("key", F.length("key").alias("len"), "n")


def enumerate_prefix_rollup(strings: DataFrame, max_len: int = 10) -> DataFrame:
    """As enumerate_keys for prefixes, by one rollup over the characters at
    places 1 to max_len: each grouping set is a prefix length."""
    places = [f"c{i}" for i in range(1, max_len + 1)]
    rows = dedupe(strings).filter("s != ''").select(*[F.when(F.length("s") >= i, F.substring("s", i, 1)).alias(f"c{i}") for i in range(1, max_len + 1)], "w")
    full = rows.rollup(*places).agg(F.sum("w").alias("n"), F.grouping_id().alias("gid"))
    depth = max_len - F.length(F.regexp_replace(F.bin("gid"), "0", ""))
    have = F.concat_ws("", *places)
    out = full.withColumn("depth", depth.cast("int")).withColumn("key", have).filter((F.col("depth") > 0) & (F.length("key") == F.col("depth")))
    return out.select("key", F.col("depth").alias("len"), "n")


def enumerate_levelwise(strings: DataFrame, kind: str, least: int, max_len: int = 10) -> DataFrame:
    """Keys of a count over `least`, and the frontier: keys with a count up to
    `least` whose parent (one character less) has more. Records are extended
    only below keys with more than `least`, one length a round, so what the
    frontier covers is never made."""
    rows = cut(dedupe(strings).filter("s != ''").withColumn("r", F.monotonically_increasing_id()))
    s = F.reverse("s") if kind == "S" else F.col("s")
    rows = rows.select("r", s.alias("s"), "w")
    live = rows.select("r", "s", "w", F.explode(F.sequence(F.lit(1), F.length("s")) if kind == "C" else F.array(F.lit(1))).alias("at"))
    found = []
    for size in range(1, max_len + 1):
        own = live.filter(F.col("at") + size - 1 <= F.length("s")).withColumn("key", F.substr("s", F.col("at"), F.lit(size)))
        counts = cut(own.select("r", "w", "key").distinct().groupBy("key").agg(F.sum("w").alias("n")))
        found.append(counts.select("key", F.lit(size).alias("len"), "n"))
        rich = counts.filter(F.col("n") > least).select("key")
        if rich.isEmpty():
            break
        live = cut(own.join(rich, "key", "left_semi").drop("key"))
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def with_tiers(keys: DataFrame, scheme) -> DataFrame:
    return keys.withColumn("tier", scheme.tier_col(F.col("n")))


def max_count(keys: DataFrame) -> int:
    return keys.agg(F.max("n")).first()[0] or 1


def changed_keys(old: DataFrame, new: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Keys lost and gained between two catalogs."""
    return old.select("key").exceptAll(new.select("key")), new.select("key").exceptAll(old.select("key"))
