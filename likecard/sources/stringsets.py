"""The string sets of the given tables: (sid LONG, s STRING), one row a record."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .io import table

SETS = ("doc_words", "doc_openers", "turn_openers", "doc_lines", "page_urls", "customer_names", "part_names", "event_props")


#: Whole columns that join filters ask about: table, key and column.
COLUMNS = {"part_types": ("part", "p_partkey", "p_type"), "supplier_names": ("supplier", "s_suppkey", "s_name"), "nation_names": ("nation", "n_nationkey", "n_name"), "doc_texts": ("documents", "doc_id", "text")}


def _pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    flat = table(spark, sf_dir, "documents", "doc_id", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    flat = flat.select((F.col("doc_id") * 1_000_000 + F.col("pos")).alias("sid"), F.trim("line").alias("line"))
    return flat.filter("line != ''")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The named set. Null records match nothing and are left out."""
    if name == "doc_openers":
        out = _pieces(spark, sf_dir).select("sid", F.array_join(F.slice(F.split("line", " ", -1), 1, 3), " ").alias("s"))
    elif name == "doc_lines":
        out = _pieces(spark, sf_dir).select("sid", F.substring("line", 1, 40).alias("s"))
    elif name == "doc_words":
        found = table(spark, sf_dir, "documents", F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"\p{L}+"), F.lit(0))).alias("s"))
        out = found.distinct().select(F.xxhash64("s").alias("sid"), "s")
    elif name == "turn_texts":
        out = table(spark, sf_dir, "conversations", (F.col("conv_id") * 1000 + F.col("turn")).alias("sid"), F.col("text").alias("s"))
    elif name == "turn_openers":
        out = table(spark, sf_dir, "conversations", (F.col("conv_id") * 1000 + F.col("turn")).alias("sid"), F.substring("text", 1, 30).alias("s"))
    else:
        source, key, column = {**COLUMNS, "page_urls": ("pages", "page_id", "url"), "customer_names": ("customer", "c_custkey", "c_name"), "part_names": ("part", "p_partkey", "p_name"), "event_props": ("events", "event_id", "props")}[name]
        out = table(spark, sf_dir, source, F.col(key).cast("long").alias("sid"), F.col(column).alias("s"))
    return out.filter("s is not null")


def sql(name: str) -> str:
    """The same set as a DuckDB select."""
    piece = "select doc_id * 1000000 + pos - 1 as sid, trim(line, ' ') as line from (select doc_id, unnest(string_split(text, chr(10))) as line, generate_subscripts(string_split(text, chr(10)), 1) as pos from documents) where trim(line, ' ') <> ''"
    return {
        "doc_openers": f"select sid, array_to_string(list_slice(string_split(line, ' '), 1, 3), ' ') as s from ({piece})",
        "doc_lines": f"select sid, substr(line, 1, 40) as s from ({piece})",
        "doc_words": r"select row_number() over () as sid, s from (select distinct unnest(regexp_extract_all(lower(text), '\p{L}+')) as s from documents)",
        "turn_openers": "select conv_id * 1000 + turn as sid, substr(text, 1, 30) as s from conversations where text is not null",
        "page_urls": "select page_id as sid, url as s from pages where url is not null",
        "customer_names": "select c_custkey as sid, c_name as s from customer where c_name is not null",
        "part_names": "select p_partkey as sid, p_name as s from part where p_name is not null",
        "event_props": "select event_id as sid, props as s from events where props is not null",
    }[name]
