"""Quality rules by hashed n-gram log-likelihood ratio (operator 5), in DataFrame
functions only."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import let, words

#: Buckets of the multinomials, additive smoothing, window of the repeat rule,
#: and the least ratio per n-gram of a document that is kept.
BUCKETS, SMOOTH, WINDOW, LEAST_RATIO = 1 << 14, 1.0, 5, -0.1


def repeat_words(hashes: Column, window: int = WINDOW) -> Column:
    """Number of words inside windows that a text holds twice or more, from the
    hashes of its words. Window hashes are sorted with their places, so equal
    ones stand side by side: n log n steps however often a window recurs.
    Texts whose windows are all different stop at a set of the hashes."""
    n = F.size(hashes)
    starts = F.sequence(F.lit(1), F.greatest(F.lit(1), n - window + 1))

    def covered(rows: Column) -> Column:
        last = F.size(rows)
        same = lambda i, k: F.element_at(rows, i).w == F.element_at(rows, k).w
        hit = F.filter(F.sequence(F.lit(1), last), lambda i: F.when(i > 1, same(F.greatest(i - 1, F.lit(1)), i)).otherwise(False) | F.when(i < last, same(i, F.least(i + 1, last))).otherwise(False))
        at = F.array_sort(F.transform(hit, lambda i: F.element_at(rows, i).at))
        gaps = lambda p: F.aggregate(F.sequence(F.lit(2), F.size(p)), F.lit(window), lambda acc, i: acc + F.least(F.lit(window), F.element_at(p, i) - F.element_at(p, i - 1)))
        return let(at, lambda p: F.when(F.size(p) == 0, 0).when(F.size(p) == 1, window).otherwise(gaps(p)))

    def counted(h: Column) -> Column:
        rows = F.array_sort(F.transform(h, lambda w, i: F.struct(w.alias("w"), i.alias("at"))))
        return F.when(F.size(F.array_distinct(h)) == F.size(h), 0).otherwise(let(rows, covered))

    windows = lambda h: F.transform(starts, lambda i: F.xxhash64(*[F.element_at(h, i + k) for k in range(window)]))
    return F.when(n < window + 1, 0).otherwise(let(let(hashes, windows), counted))


def dup_lines(text: Column) -> Column:
    """Lines with a word that equal an earlier line."""
    own = F.filter(F.split(text, "\n", -1), lambda line: line.rlike(r"[^\x20\x09-\x0D]"))
    return let(own, lambda lines: F.size(lines) - F.size(F.array_distinct(lines)))


def measured(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words,
    base_failed, hashes) of every row; null texts have no words."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"))
    white = F.lit(" \t\n\x0b\f\r")
    rows = rows.select(
        "doc_id",
        F.length(F.translate("text", " \t\n\x0b\f\r", "")).cast("long").alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", "#*$%&|<>", ""))).cast("long").alias("n_symbols"),
        dup_lines(F.col("text")).cast("long").alias("n_dup_lines"),
        F.transform(words(F.col("text")), lambda w: F.xxhash64(w)).alias("hashes"),
    )
    rows = rows.select("*", F.size("hashes").cast("long").alias("n_words"), repeat_words(F.col("hashes")).cast("long").alias("n_repeat_words"))
    return rows.withColumn("base_failed", (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words")))


def grams(hashes: Column, buckets: int = BUCKETS) -> Column:
    """Buckets of the words and word pairs of a text, with repeats."""
    one = F.transform(hashes, lambda h: F.pmod(h, F.lit(buckets)).cast("int"))
    pairs = lambda h: F.transform(F.slice(h, 2, F.greatest(F.lit(0), F.size(h) - 1)), lambda w, i: F.pmod(F.xxhash64(F.element_at(h, i + 1), w), F.lit(buckets)).cast("int"))
    return F.concat(one, let(hashes, pairs))


def marked(docs: DataFrame, trusted: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(_t, _text) of every row of docs, null as the empty text; _t is 1 where the
    document is trusted, else null. Sorted and merged whatever the number of ids,
    so what is shuffled is the texts, once, at every size, and no process holds all ids."""
    ids = trusted.select(F.col("doc_id").cast("long").alias("_id"), F.lit(1).alias("_t")).distinct()
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("_id"), text.alias("_text"))
    return rows.join(ids.hint("merge"), "_id", "left").select("_t", "_text")


def ratios(docs: DataFrame, trusted: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int = BUCKETS, smooth: float = SMOOTH) -> DataFrame:
    """(bucket, ratio): log of the share of each bucket among the n-grams of the
    trusted documents over its share among those of all documents, smoothed.
    trusted: (doc_id), any number. One pass over docs; a bucket is a row a task
    before the shuffle."""
    rows = marked(docs, trusted, id_col, text_col)
    rows = rows.select("_t", F.explode(grams(F.transform(words(F.col("_text")), lambda w: F.xxhash64(w)), buckets)).alias("bucket"))
    counts = rows.groupBy("bucket").agg(F.count("*").alias("r"), F.count("_t").alias("t")).collect()
    every, chosen = sum(c.r for c in counts) + smooth * buckets, sum(c.t for c in counts) + smooth * buckets
    import math

    if not any(c.t for c in counts):
        out = [(c.bucket, 0.0) for c in counts]
    else:
        out = [(c.bucket, math.log((c.t + smooth) / chosen) - math.log((c.r + smooth) / every)) for c in counts]
    return docs.sparkSession.createDataFrame(out, "bucket int, ratio double")


def judge(docs: DataFrame, trusted: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int = BUCKETS, least: float = LEAST_RATIO) -> DataFrame:
    """One row per row of docs: doc_id, the base measures, ratio (mean log ratio
    of its n-grams, rounded so that order of summing cannot move it over the
    threshold) and kept: base rules passed and ratio >= least.

    The ratio table has `buckets` rows at most and is broadcast. Without trusted
    documents every ratio is 0. Null and empty texts have no words and fail the
    base rules; rows repeated are judged each.
    """
    weights = ratios(docs, trusted, id_col, text_col, buckets)
    rows = measured(docs, id_col, text_col).withColumn("row", F.monotonically_increasing_id())
    keys = ["row", "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed"]
    flat = rows.select(*keys, F.explode_outer(grams(F.col("hashes"), buckets)).alias("bucket")).join(F.broadcast(weights), "bucket", "left")
    out = flat.groupBy(*keys).agg(F.round(F.coalesce(F.avg("ratio"), F.lit(0.0)), 9).alias("ratio")).drop("row")
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("ratio") >= least))


def trusted_documents(labels: DataFrame) -> DataFrame:
    """(doc_id) of all documents labelled good."""
    return labels.filter((F.col("quality") == 1) & F.col("doc_id").isNotNull()).select("doc_id").distinct()
