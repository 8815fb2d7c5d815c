"""Registered queries of this subpackage and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import embedding_dedup, line_dedup, mixing, packing, quality_classifier, quality_rules, secrets, simhash, substring_dedup, toxicity
from .common import is_held_out, table


def op1_embedding_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dedup.near_duplicates(table(spark, sf_dir, "embeddings"))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: its lines, and the numbers of those that repeat or nearly
    repeat an earlier one."""
    return line_dedup.report(table(spark, sf_dir, "documents"))


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents"))


def _scored(rows: DataFrame, at_least: float) -> DataFrame:
    return rows.select(F.col("id").alias("doc_id"), is_held_out(F.col("id")).alias("held_out"), "score", (F.col("score") >= at_least).cast("int").alias("predicted"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return _scored(toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels"))), 0.5)


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    trusted = quality_rules.trusted_documents(table(spark, sf_dir, "labels"))
    return quality_rules.judge(table(spark, sf_dir, "documents"), trusted)


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = quality_classifier.fit(docs, table(spark, sf_dir, "labels"))
    return _scored(quality_classifier.score(docs, model), quality_classifier.ACCEPT)


def tokenizer_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op8_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.groups(table(spark, sf_dir, "documents"))
    return out.select(F.col("id").alias("doc_id"), F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), F.col("component").alias("component_id"))


def op9_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = secrets.scan(table(spark, sf_dir, "documents"))
    joined = lambda kept: F.array_join(F.transform(kept, lambda s: F.concat_ws(":", s.kind, s.start.cast("string"), s.end.cast("string"))), ",")
    base = F.filter("spans", lambda s: s.kind.isin(*secrets.BASE))
    kinds = F.transform("spans", lambda s: s.kind)
    counts = [(F.size(kinds) - F.size(F.array_remove(kinds, k))).cast("long").alias(f"n_{k}") for k in secrets.BASE]
    return found.select(F.col("id").alias("doc_id"), *counts, F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per document: its chunks, those that other documents hold too, the
    passages of about fifty words or more among them, their spans in UTF-8
    bytes, the documents that have them first, and the passages that the
    document itself holds twice or more."""
    found = substring_dedup.repeats(table(spark, sf_dir, "documents"))
    total = lambda f: F.aggregate("passages", F.lit(0).cast("long"), lambda acc, p: acc + p[f])
    spans = F.array_join(F.transform("passages", lambda p: F.concat_ws(":", p["start"].cast("string"), p["end"].cast("string"))), ",")
    firsts = F.array_sort(F.array_distinct(F.flatten(F.transform("passages", lambda p: p["first_docs"]))))
    return found.select(
        F.col("id").alias("doc_id"), "n_chunks", "n_repeated", F.size("passages").cast("long").alias("n_passages"), total("words").alias("repeat_words"), total("removed").alias("removed_words"), spans.alias("spans"), firsts.alias("first_docs"), (F.size("passages") > 0).alias("repeats"),
        F.size("within").cast("long").alias("n_within"), F.aggregate("within", F.lit(0).cast("long"), lambda acc, p: acc + p["removed"]).alias("within_removed_words"),
    )


def queries() -> dict:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}


def oracle_sql() -> dict[str, str]:
    """SQL where it can say the same; the other queries are tested against brute force."""
    bad = "list_sum(list_transform(e, lambda x: case when x is null or not isfinite(x) then 1 else 0 end)) = 0"
    some = "list_sum(list_transform(e, lambda x: case when x <> 0 then 1 else 0 end)) > 0"
    near = f"list_cosine_similarity(a.e, b.e) >= {embedding_dedup.THRESHOLD}"
    return {
        "op1_embedding_dedup": f"""
            with recursive v as materialized (select vec_id, label, e from (select vec_id, label, embedding::double[] as e from embeddings) where label is not null and e is not null and {bad} and {some}),
            links as materialized (select a.vec_id as a, b.vec_id as b from v a join v b on a.label = b.label and a.vec_id <> b.vec_id and len(a.e) = len(b.e) where {near}),
            reach as (select vec_id, vec_id as c from embeddings union select l.a, r.c from reach r join links l on l.b = r.vec_id),
            named as (select vec_id, min(c) as component_id from reach group by vec_id)
            select n.vec_id, (select count(*) from links l where l.a = n.vec_id) as n_links, n.component_id, n.vec_id = n.component_id as kept from named n""",
    }
