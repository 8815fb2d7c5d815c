"""Mixing sources to target weights by pivotal dependent rounding (operator 3)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import WORD, balanced, cut

WEIGHTS, SHARE, MOST, LEAF, MAX_SOURCES = (5.0, 2.0, 1.0), 1.5, 2.0, 8192, 1_000_000


def _text_hash(text_col: str):
    return F.xxhash64(F.col(text_col).cast("string"))


def sizes(docs: DataFrame, id_col: str, text_col: str, source_col: str) -> DataFrame:
    """(doc_id, source, size, text_hash, nth): a row per row of docs. Rows that are
    equal in the others are told apart by nth, counted with partial sums, so
    that ids which many rows share (null among them) spread over all leaves."""
    n = F.coalesce(F.regexp_count(F.col(text_col), F.lit(WORD)), F.lit(0)).cast("long")
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(source_col).cast("string").alias("source"), n.alias("size"), _text_hash(text_col).alias("text_hash"))
    rows = rows.groupBy("doc_id", "source", "size", "text_hash").agg(F.count("*").alias("_n"))
    return rows.select("doc_id", "source", "size", "text_hash", F.explode(F.sequence(F.lit(1).cast("long"), F.col("_n"))).alias("nth"))


def targets(totals: list[tuple], weights=WEIGHTS, share: float = SHARE, most: float = MOST) -> list[float]:
    """Targets of the sources (name or None, words), in the order given: share
    of all words by weight; a target stops at `most` times its source's words,
    and what is over goes to the others by weight until none is above."""
    n = len(totals)
    w = [weights[i % len(weights)] for i in range(n)]
    top = [most * size for _, size in totals]
    left, out, free = share * sum(size for _, size in totals), [0.0] * n, list(range(n))
    while free:
        whole = sum(w[i] for i in free)
        over = [i for i in free if left * w[i] / whole > top[i]]
        if not over:
            for i in free:
                out[i] = left * w[i] / whole
            break
        for i in over:
            out[i] = top[i]
        left = max(0.0, left - sum(top[i] for i in over))
        free = [i for i in free if i not in set(over)]
    return out


def source_plan(sized: DataFrame, weights=WEIGHTS, share: float = SHARE, most: float = MOST) -> list[tuple]:
    """(source, words, documents, target) of each source, by code point, null
    last. One row a source comes to the driver; over MAX_SOURCES is an error."""
    rows = sized.groupBy("source").agg(F.sum("size").alias("words"), F.count("*").alias("docs")).limit(MAX_SOURCES + 1).collect()
    if len(rows) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources")
    rows = sorted(rows, key=lambda r: (r.source is None, r.source or ""))
    return [(r.source, r.words, r.docs, t) for r, t in zip(rows, targets([(r.source, r.words) for r in rows], weights, share, most))]


def round_leaf(pdf, seed: int):
    """One node of the reduction tree: documents with fractional copies x.

    From the largest document down, two fractions meet; words move from one to
    the other, at random with the odds that keep both expectations, until one
    is whole. At most one fraction is left, and words taken do not change.
    """
    import numpy as np
    import xxhash

    pdf = pdf.sort_values(["size", "tie", "doc_id", "x"], ascending=[False, True, True, True], ignore_index=True)
    x, size, ids, tie = pdf["x"].to_numpy().copy(), pdf["size"].to_numpy(), pdf["doc_id"].fillna(-1).to_numpy(), pdf["tie"].to_numpy()
    eps, held = 1e-12, -1
    for i in range(len(x)):
        if not eps < x[i] < 1 - eps:
            x[i] = round(x[i])
            continue
        if held < 0:
            held = i
            continue
        a, b = held, i
        give = min(x[a] * size[a], (1 - x[b]) * size[b])
        take = min((1 - x[a]) * size[a], x[b] * size[b])
        draw = xxhash.xxh64_intdigest(f"{seed}|{ids[a]}|{ids[b]}|{tie[a]}|{tie[b]}") / 2.0**64
        move = take if draw * (give + take) < give else -give
        x[a] += move / size[a]
        x[b] -= move / size[b]
        for k in (a, b):
            if not eps < x[k] < 1 - eps:
                x[k] = np.round(x[k])
        held = next((k for k in (a, b) if eps < x[k] < 1 - eps), -1)
    return pdf.assign(x=x)


def _rounder(seed: int):
    return lambda pdf: round_leaf(pdf, seed)


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", weights=WEIGHTS, share: float = SHARE, most: float = MOST, leaf: int = LEAF, seed: int = 17) -> DataFrame:
    """One row per row of docs: doc_id, source, size, source_size, target (of
    its source), copies (whole, 0 to `most`), taken = copies * size, text_hash.

    Each document gets target / source_size copies in expectation: the whole
    part for certain, the fraction by pivotal rounding weighted by words, so a
    source's taken words keep to its target but for the last fraction of its
    tree, which one draw makes whole. Leaves of about `leaf` documents round
    on their own and pass one fraction each up the tree. All draws are hashes
    of seed and ids: reruns and other partitionings agree. Null or empty texts
    have size 0 and are never taken; a null source is a source; rows repeated
    count each; no rows give none.
    """
    sized = cut(sizes(docs, id_col, text_col, source_col))
    plan = source_plan(sized, weights, share, most)
    spark = docs.sparkSession
    schema = T.StructType([T.StructField("source", T.StringType()), T.StructField("source_size", T.LongType()), T.StructField("leaves", T.IntegerType()), T.StructField("target", T.DoubleType())])
    by = spark.createDataFrame([(s, w, max(1, -(-n // leaf)), t) for s, w, n, t in plan], schema)
    rows = sized.join(F.broadcast(by), sized.source.eqNullSafe(by.source)).select(sized["*"], "source_size", "target", "leaves")
    mean = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    base = F.when(F.col("size") > 0, F.floor(mean + 1e-12)).otherwise(0).cast("long")
    rows = rows.withColumns({"base": base, "x": F.when(F.col("size") > 0, F.greatest(F.lit(0.0), mean - F.floor(mean + 1e-12))).otherwise(0.0), "tie": F.xxhash64("doc_id", "text_hash", "nth", F.lit(seed))})
    rows = rows.withColumn("leaf", F.pmod(F.xxhash64("doc_id", "text_hash", "nth", F.lit(seed + 1)), F.col("leaves")).cast("int"))
    columns = ["doc_id", "text_hash", "source", "size", "source_size", "target", "base", "x", "tie", "leaf", "leaves"]
    rows, done = rows.select(columns), []
    fractional = (F.col("x") > 1e-12) & (F.col("x") < 1 - 1e-12)
    done.append(rows.filter(~fractional))
    rows, depth = rows.filter(fractional), 0
    most_leaves = max([max(1, -(-n // leaf)) for _, _, n, _ in plan], default=0)
    while most_leaves:
        out = cut(balanced(rows, "source", "leaf").groupBy("source", "leaf").applyInPandas(_rounder(seed + depth), rows.schema))
        if most_leaves == 1:
            last = F.when(fractional & (F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), "doc_id", "text_hash", "size")), 1, 8), 16, 10).cast("double") / 2.0**32 < F.col("x")), 1.0)
            done.append(out.withColumn("x", F.coalesce(last, F.when(fractional, 0.0), F.col("x"))))
            break
        done.append(out.filter(~fractional))
        rows = out.filter(fractional).withColumns({"leaf": (F.col("leaf") / leaf).cast("int"), "leaves": F.ceil(F.col("leaves") / leaf).cast("int")})
        most_leaves, depth = -(-most_leaves // leaf), depth + 1
    out = done[0]
    for more in done[1:]:
        out = out.unionByName(more)
    copies = F.col("base") + F.round("x").cast("long")
    return out.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).alias("taken"), "text_hash")


def materialise(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **options) -> DataFrame:
    """docs with each row as many times as the mix takes it; all columns stay.
    Rows are known by id (null is one) and text; those that share both, and the
    source, all follow the largest number of copies that one of them got."""
    copies = mix(docs, id_col, text_col, source_col, **options).filter("copies > 0").groupBy("doc_id", "source", "text_hash").agg(F.max("copies").alias("_copies"))
    copies = copies.toDF("_doc", "_source", "_text", "_copies")
    same = F.col(id_col).cast("long").eqNullSafe(F.col("_doc")) & F.col(source_col).cast("string").eqNullSafe(F.col("_source")) & (_text_hash(text_col) == F.col("_text"))
    out = docs.join(copies, same).withColumn("_copies", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int"))))
    return out.drop("_doc", "_source", "_text", "_copies")
