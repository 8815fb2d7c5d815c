"""The estimator from SQL: views, functions and a table function."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from ..functions.patterns import _shape
from .estimator import Estimator
from .serve import LocalModel


def register(spark: SparkSession, estimator: Estimator, prefix: str = "like") -> None:
    """Creates views {prefix}_tiers and {prefix}_catalog_{kind}, functions
    {prefix}_estimate(pattern) and {prefix}_kind(pattern), and the table
    function {prefix}_enumerate(s, max_len)."""
    edges = [(k, i, lo, hi, s.value(i)) for k, s in estimator.schemes.items() for i, (lo, hi) in enumerate(s.edges, 1)]
    spark.createDataFrame(edges, "kind string, tier int, lo long, hi long, rep double").createOrReplaceTempView(f"{prefix}_tiers")
    for kind, catalog in estimator.catalogs.items():
        catalog.createOrReplaceTempView(f"{prefix}_catalog_{kind.lower()}")
    model = spark.sparkContext.broadcast(LocalModel(Estimator(estimator.config, estimator.n_records, estimator.schemes, estimator.models)))

    @pandas_udf("double")
    def estimate(patterns: Iterator[pd.Series]) -> Iterator[pd.Series]:
        local = model.value
        for batch in patterns:
            yield batch.map(lambda p: local.estimate(p) if p is not None else None).astype("float64")

    spark.udf.register(f"{prefix}_estimate", estimate)
    shape = _shape("\\").replace("\\", "\\\\")  # a string literal of SQL, where a backslash stands for two
    ends = f"concat(regexp_extract(p, '{shape}', 1), '|', regexp_extract(p, '{shape}', 3))"
    spark.sql(f"create or replace temporary function {prefix}_kind(p string) returns string return case when p is null or p not rlike '{shape}' then 'O' else case {ends} when '|%' then 'P' when '%|' then 'S' when '%|%' then 'C' else 'O' end end")
    spark.udtf.register(f"{prefix}_enumerate", enumerate_literals())


def enumerate_literals():
    """A table function of (s, max_len): a row per distinct substring."""

    @udtf(returnType="key string, len int")
    class Enumerate:
        def eval(self, s: str, max_len: int):
            if s:
                for key in sorted({s[i : i + j] for i in range(len(s)) for j in range(1, max_len + 1) if i + j <= len(s)}):
                    yield key, len(key)

    return Enumerate
