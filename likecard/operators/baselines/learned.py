"""Learned baselines as families: gradient-boosted trees or a linear model stand
in for the networks, over each family's own features."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.ml.feature import FeatureHasher, VectorAssembler, Word2Vec
from pyspark.ml.regression import GBTRegressor, LinearRegression
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ...functions.patterns import matches
from ...plans.workloads import digest
from ...sources.scratch import cut


def _shape(df: DataFrame) -> DataFrame:
    return df.withColumns({"f_len": F.length("lit").cast("double"), **{f"f_{k}": (F.col("kind") == k).cast("double") for k in "PSC"}})


#: Families of which one model answers all kinds.
JOINT = ("sample_bitmap_net", "sequence_net", "hybrid_frequent_gram")
SHAPE = ["f_len", "f_P", "f_S", "f_C"]


def bitmap_features(sample: list[str], buckets: int = 32) -> Callable[[DataFrame], tuple[DataFrame, list[str]]]:
    """Which records of a fixed sample match, folded into bucket counts."""

    def make(df: DataFrame) -> tuple[DataFrame, list[str]]:
        parts = {}
        for b in range(buckets):
            own = F.array(*[F.lit(s) for s in sample[b::buckets]]) if sample[b::buckets] else F.array().cast("array<string>")
            hit = F.when(F.col("kind") == "P", F.size(F.filter(own, lambda s: matches("P", s, F.col("lit"))))).when(F.col("kind") == "S", F.size(F.filter(own, lambda s: matches("S", s, F.col("lit")))))
            parts[f"b{b}"] = hit.otherwise(F.size(F.filter(own, lambda s: matches("C", s, F.col("lit"))))).cast("double")
        df = _shape(df).withColumns(parts)
        total = sum((F.col(f"b{b}") for b in range(1, buckets)), F.col("b0"))
        return df.withColumn("b_all", F.log1p(total)), [*SHAPE, *parts, "b_all"]

    return make


def _characters(n: int):
    padded = F.concat(F.lit("^"), "lit", F.lit("$"))
    return F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(padded) - n + 1)), lambda i: F.substring(padded, i, n))


def embedding_features(train: DataFrame, dim: int = 16) -> Callable:
    """Mean embedding of the literal's character pairs."""
    model = Word2Vec(vectorSize=dim, minCount=1, maxIter=2, seed=42, inputCol="grams", outputCol="vec").fit(train.select(_characters(2).alias("grams")))

    def make(df: DataFrame) -> tuple[DataFrame, list[str]]:
        return model.transform(_shape(df).withColumn("grams", _characters(2))), [*SHAPE, "vec"]

    return make


def looked_up(df: DataFrame, parts: Column, table: DataFrame, name: str, missing: float = -10.0) -> DataFrame:
    """df (lit, ...) with the values of the parts of each literal, in their order, by
    a join with table (part, value): no plan or process holds the table."""
    flat = df.select("lit").distinct().select("lit", F.posexplode(parts).alias("at", "part")).join(table, "part", "left")
    values = flat.groupBy("lit").agg(F.sort_array(F.collect_list(F.struct("at", F.coalesce("value", F.lit(missing)).alias("v")))).alias("_v"))
    return df.join(values, "lit").withColumn(name, F.col("_v.v")).drop("_v")


def _pairs(col: str) -> Column:
    return F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.length(col) - 1)), lambda i: F.substring(F.col(col), i, 2))


def language_features(strings: DataFrame) -> Callable:
    """Log-probability of the literal under a character-pair model of the set."""
    pairs = strings.select(F.explode(_pairs("s")).alias("part")).groupBy("part").count()
    first = F.sum("count").over(Window.partitionBy(F.substring("part", 1, 1)))
    known = cut(pairs.select("part", F.log(F.col("count") / first).alias("value")))

    def make(df: DataFrame) -> tuple[DataFrame, list[str]]:
        out = looked_up(_shape(df), _pairs("lit"), known, "_g")
        return out.withColumn("lp", F.aggregate("_g", F.lit(0.0), lambda acc, x: acc + x)).drop("_g"), [*SHAPE, "lp"]

    return make


def sequence_features(places: int = 12, width: int = 64) -> Callable:
    """Characters by place, wildcards as symbols, hashed."""

    def make(df: DataFrame) -> tuple[DataFrame, list[str]]:
        text = F.concat(F.when(F.col("kind") != "P", "%").otherwise(""), "lit", F.when(F.col("kind") != "S", "%").otherwise(""))
        cols = {f"p{i}": F.substring(text, i + 1, 1) for i in range(places)}
        hasher = FeatureHasher(inputCols=list(cols), outputCol="seq", numFeatures=width)
        return hasher.transform(_shape(df).withColumns(cols)), [*SHAPE, "seq"]

    return make


def gram_features(singles: dict[str, float]) -> Callable:
    """Least, mean and summed log share of the literal's characters, and its ends."""

    def make(df: DataFrame) -> tuple[DataFrame, list[str]]:
        known = df.sparkSession.createDataFrame(list(singles.items()), "part string, value double")
        df = looked_up(_shape(df), F.split("lit", ""), known, "_l")
        total = F.aggregate("_l", F.lit(0.0), lambda a, x: a + x)
        return df.withColumns({"g_min": F.array_min("_l"), "g_sum": total, "g_mean": total / F.size("_l"), "g_first": F.ascii("lit").cast("double"), "g_last": F.ascii(F.expr("right(lit, 1)")).cast("double")}).drop("_l"), [*SHAPE, "g_min", "g_sum", "g_mean", "g_first", "g_last"]

    return make


@dataclass
class Regression:
    """log(true_n) from features; estimates are 1 at least. exact, if given, has
    (kind, lit, n) of frequent short literals that bypass the regression."""

    make: Callable
    model: object
    exact: DataFrame | None = field(default=None, repr=False)
    extra_bytes: float = 0.0

    @property
    def bytes(self) -> float:
        """Tree nodes at 20 bytes (or a double a coefficient), and what the features and the exact part hold."""
        nodes = getattr(self.model, "totalNumNodes", None)
        listed = self.exact.agg(F.coalesce(F.sum(F.octet_length("lit") + 9), F.lit(0))).first()[0] if self.exact is not None else 0
        return (nodes * 20 if nodes is not None else 8 * self.model.numFeatures) + listed + self.extra_bytes

    def estimate(self, patterns: DataFrame) -> DataFrame:
        df, cols = self.make(patterns)
        out = self.model.transform(VectorAssembler(inputCols=cols, outputCol="features").transform(df))
        out = out.select(*patterns.columns, F.greatest(F.lit(1.0), F.exp(F.least(F.col("prediction"), F.lit(40.0)))).alias("est"))
        if self.exact is None:
            return out
        short = self.exact.withColumnRenamed("n", "_n")
        return out.join(F.broadcast(short), ["kind", "lit"], "left").withColumn("est", F.coalesce(F.col("_n").cast("double"), "est")).select(*patterns.columns, "est")


def train(rows: DataFrame, make: Callable, linear: bool = False, exact: DataFrame | None = None, iterations: int = 20, depth: int = 5, extra_bytes: float = 0.0) -> Regression:
    """rows: (kind, lit, true_n) of training patterns."""
    df, cols = make(rows)
    data = VectorAssembler(inputCols=cols, outputCol="features").transform(df).select("features", F.log(F.col("true_n").cast("double")).alias("label"))
    learner = LinearRegression(regParam=0.01) if linear else GBTRegressor(maxIter=iterations, maxDepth=depth, seed=42)
    return Regression(make, learner.fit(data), exact, extra_bytes)


def families(rows: DataFrame, strings: DataFrame, short: DataFrame, sample_size: int = 200, iterations: int = 20) -> dict[str, Callable[..., Regression]]:
    """Trainers by name: those of JOINT take all rows (kind, lit, true_n), the
    others those of a kind, if one is named. short: (kind, lit, n) of literals up
    to two characters."""
    sample = [r.s for r in strings.orderBy(digest("smp|", F.col("sid")), "sid").limit(sample_size).collect()]
    singles = {r.lit: float(r.p) for r in short.filter("kind = 'C' and length(lit) = 1").select("lit", F.log(F.col("n") / F.max("n").over(Window.partitionBy("kind"))).alias("p")).collect()} or {"": 0.0}
    of = lambda kind: rows if kind is None else rows.filter(F.col("kind") == kind)
    held = float(sum(len((s or "").encode()) for s in sample))
    return {
        "sample_bitmap_net": lambda: train(rows, bitmap_features(sample), extra_bytes=held),
        "embedding_net": lambda kind=None: train(of(kind), embedding_features(of(kind)), extra_bytes=4.0 * 16 * len(singles) ** 1.5),
        "embedding_net_lm": lambda kind=None: train(of(kind), language_features(strings), extra_bytes=10.0 * len(singles) ** 1.5),
        "sequence_net": lambda: train(rows, sequence_features()),
        "hybrid_frequent_gram": lambda: train(rows, gram_features(singles), exact=short.filter("n >= 10"), iterations=iterations, extra_bytes=10.0 * len(singles)),
        "flat_regression": lambda kind=None: train(of(kind), gram_features(singles), linear=True, extra_bytes=10.0 * len(singles)),
    }
