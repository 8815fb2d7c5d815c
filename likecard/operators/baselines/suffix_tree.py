"""pruned_suffix_tree: counts of the most frequent substrings; others from overlapping parts."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ...sources.scratch import cut
from ..catalog import literals


def kept_nodes(catalog: DataFrame, keep: float = 0.02) -> DataFrame:
    """The ceil(keep * K) most frequent substrings (ties by length, then key). A
    histogram of counts finds the count at the edge; only keys of that count
    are ordered."""
    counts = catalog.groupBy("n").count().toArrow()
    hist = sorted(zip(counts["n"].to_pylist(), counts["count"].to_pylist()), reverse=True)
    left = ceil(keep * sum(c for _, c in hist))
    for edge, c in hist:
        if c >= left:
            break
        left -= c
    else:
        return catalog
    ties = catalog.filter(F.col("n") == edge).orderBy("len", "key").limit(left)
    return catalog.filter(F.col("n") > edge).unionByName(ties)


@dataclass(frozen=True)
class SuffixTree:
    """counts of a few kept parts, or a table (key, n) of any number, which nobody gathers."""

    records: int
    counts: dict[str, int] = field(repr=False)
    floor: float = 1.0
    parse: str = "overlap"
    table: DataFrame | None = field(default=None, repr=False, compare=False)

    @property
    def bytes(self) -> int:
        """The kept parts, with eight bytes for each count."""
        if self.table is None:
            return sum(len(k.encode()) + 8 for k in self.counts)
        return self.table.agg(F.coalesce(F.sum(F.octet_length("key") + 8), F.lit(0))).first()[0]

    def estimate_py(self, lit: str) -> float:
        """The first longest kept part, then the part that begins earliest among
        those reaching further, each by its count over that of the overlap
        ('independent': over all records). Products come before quotients, so that
        other engines round alike."""
        counts, at, end, out = self.counts, 0, 0, float(self.records)
        while end < len(lit):
            step = None
            for s in range(at, end + 1):
                e = next((e for e in range(len(lit), end, -1) if lit[s:e] in counts), None)
                if e:
                    step = (s, e)
                    break
            if step is None:
                out = out * self.floor / max(1, self.records)
                at = end = end + 1
                continue
            s, e = step
            overlap = counts.get(lit[s:end], self.records) if s < end and self.parse == "overlap" else self.records
            if self.parse == "independent" and s < end:
                s, e = end, next((x for x in range(len(lit), end, -1) if lit[end:x] in counts), end + 1)
                out = out * counts.get(lit[s:e], self.floor) / max(1, self.records)
            else:
                out = out * counts[lit[s:e]] / max(1, overlap)
            at, end = s + 1, e
        return max(self.floor, out)

    def estimate(self, patterns: DataFrame) -> DataFrame:
        """patterns (lit, ...) with est. Each literal meets the kept parts that it holds."""
        table = self.table
        if table is None:
            table = patterns.sparkSession.createDataFrame(list(self.counts.items()), "key string, n long")
        longest = table.agg(F.coalesce(F.max(F.length("key")), F.lit(1))).first()[0]
        flat = patterns.select("lit").filter("lit != ''").distinct().select("lit", F.explode(literals(F.col("lit"), "C", longest)).alias("key")).join(table, "key")
        held = flat.groupBy("lit").agg(F.collect_list(F.struct("key", "n")).alias("_held"))
        met = patterns.join(held, "lit", "left").select(*patterns.columns, F.col("_held.key").alias("_key"), F.col("_held.n").alias("_n"))
        records, floor, parse = self.records, self.floor, self.parse

        def one(lit, keys, n) -> float:
            return SuffixTree(records, dict(zip(keys, n)) if keys is not None else {}, floor, parse).estimate_py(lit)

        def run(batches: Iterator) -> Iterator:
            for pdf in batches:
                est = [one(*x) for x in zip(pdf["lit"], pdf["_key"], pdf["_n"])]
                yield pdf.drop(columns=["_key", "_n"]).assign(est=est).astype({"est": "float64"})

        return met.mapInPandas(run, ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in patterns.schema) + ", est double")


def fit(catalog: DataFrame, records: int, keep: float = 0.02, parse: str = "overlap") -> SuffixTree:
    return SuffixTree(records, {}, 1.0, parse, cut(kept_nodes(catalog, keep).select("key", "n")))
