"""Bloom filters as tables of 64-bit words, built and probed by expressions."""

from __future__ import annotations

from array import array
from collections.abc import Iterator
from dataclasses import dataclass, field
from math import ceil, log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import FAMILIES, LOCAL, fast_all, fast_base, portable_all

#: Words that may come to the driver (32 MB of bits), and words up to which
#: filters travel in the plan, as constants; larger ones go to the tasks as arrays.
MAX_WORDS, MAX_INLINE = 4_000_000, 8_192


@dataclass(frozen=True)
class Filter:
    """One Bloom filter: its size and salt, and its words where they were gathered."""

    salt: str
    n_keys: int
    n_bits: int
    n_hashes: int
    fpr: float
    family: str = "portable"
    words: array | tuple = field(default=(), repr=False)

    def has(self, key: str) -> bool:
        """The probe in plain Python."""
        a, b = LOCAL[self.family](self.salt, key)
        step = b % self.n_bits
        for j in range(self.n_hashes):
            p = (a + j * step) % self.n_bits
            if not self.words[p >> 6] >> (p & 63) & 1:
                return False
        return True

    def has_col(self, key: Column) -> Column:
        """The probe as an expression over the words as a folded constant; the
        hash is taken once, and the first unset bit ends the probe."""
        words = F.split(F.lit(",".join(map(str, self.words))), ",").cast("array<bigint>")
        a, b = FAMILIES[self.family](self.salt, key)
        pair = F.struct(a.alias("a"), (b % self.n_bits).alias("b"))
        at = lambda h, j: F.pmod(h.a + j * h.b, F.lit(self.n_bits))
        bit = lambda p: F.getbit(F.element_at(words, F.floor(p / 64).cast("int") + 1), (p % 64).cast("int")) == 1
        probe = lambda h: F.forall(F.sequence(F.lit(0), F.lit(self.n_hashes - 1)), lambda j: bit(at(h, j)))
        return F.element_at(F.transform(F.array(pair), probe), 1)


def sized(n_keys: int, fpr: float) -> tuple[int, int]:
    """(bits, hashes): -ln f / (ln 2)^2 bits a key, 64 at least."""
    bits = max(64, ceil(-log(fpr) / log(2) ** 2 * n_keys))
    return bits, max(1, round(bits / max(1, n_keys) * log(2)))


def positions(key: Column, f: Filter) -> Column:
    a, b = FAMILIES[f.family](f.salt, key)
    pair = F.struct(a.alias("a"), (b % f.n_bits).alias("b"))
    return F.element_at(F.transform(F.array(pair), lambda h: F.transform(F.sequence(F.lit(0), F.lit(f.n_hashes - 1)), lambda j: F.pmod(h.a + j * h.b, F.lit(f.n_bits)))), 1)


def word_table(keys: DataFrame, filters: dict[int, Filter]) -> DataFrame:
    """(tier, word_idx, word) of the filters of all tiers in one job. keys: (tier, key)."""
    spots = F.lit(None).cast("array<bigint>")
    for tier, f in filters.items():
        spots = F.when(F.col("tier") == tier, positions(F.col("key"), f)).otherwise(spots)
    flat = keys.select("tier", F.explode(spots).alias("p"))
    one = F.lit(1).cast("bigint")
    return flat.groupBy("tier", F.floor(F.col("p") / 64).cast("int").alias("word_idx")).agg(F.bit_or(F.call_function("shiftleft", one, (F.col("p") % 64).cast("int"))).alias("word"))


def gather(table: DataFrame, filters: dict[int, Filter]) -> dict[int, Filter]:
    """The filters with their words; refuses more than MAX_WORDS."""
    from dataclasses import replace

    if sum(-(-f.n_bits // 64) for f in filters.values()) > MAX_WORDS:
        raise ValueError("filters too large for the driver; fit with by_join")
    import numpy as np

    words = {t: np.zeros(-(-f.n_bits // 64), np.int64) for t, f in filters.items()}
    tier, at, word = (c.to_numpy() for c in table.select("tier", "word_idx", "word").toArrow().columns)
    for t, w in words.items():
        w[at[tier == t]] = word[tier == t]
    return {t: replace(f, words=array("q", words[t].tobytes())) for t, f in filters.items()}


def prepared(keys: list[str], filters: list[Filter]):
    """The keys as an array for hits: their first hashes under the fast family."""
    import numpy as np

    if all(f.family == "fast" for f in filters):
        return np.array([fast_base(k) if k is not None else 0 for k in keys], np.uint64)
    return np.array(keys, object)


def _spots(f: Filter, keys):
    """First place and step of each of the prepared keys in a filter."""
    import numpy as np

    if keys.dtype == np.uint64:
        at, step = fast_all(f.salt, keys)
    elif f.family == "portable":
        at, step = portable_all(f.salt, keys)
    else:
        at, step = np.array([LOCAL[f.family](f.salt, k) for k in keys], np.int64).T
    return at, step % f.n_bits


def hits(f: Filter, keys):
    """Which of the prepared keys a gathered filter holds, as an array."""
    import numpy as np

    if not len(keys):
        return np.zeros(0, bool)
    (at, step), words, ok = _spots(f, keys), np.frombuffer(f.words, np.int64), np.ones(len(keys), bool)
    for j in range(f.n_hashes):
        p = (at + j * step) % f.n_bits
        ok &= (words[p >> 6] >> (p & 63)) & 1 == 1
    return ok


def filled(f: Filter, keys) -> Filter:
    """The filter with the words of the prepared keys."""
    from dataclasses import replace

    import numpy as np

    words = np.zeros(-(-f.n_bits // 64), np.uint64)
    at, step = _spots(f, keys)
    for j in range(f.n_hashes):
        p = (at + j * step) % f.n_bits
        np.bitwise_or.at(words, p >> 6, np.uint64(1) << (p & 63).astype(np.uint64))
    return replace(f, words=array("q", words.tobytes()))


def dealt(keys: DataFrame) -> DataFrame:
    """keys over all shuffle partitions: probes cost far more than the few bytes a
    key by which Spark sizes its tasks."""
    return keys.repartition(int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions")), "key")


def passing(keys: DataFrame, filters: dict[int, Filter]) -> DataFrame:
    """keys (tier, key) that their tier's gathered filter holds: by expression for
    small filters, in Arrow batches over broadcast words for others."""
    if sum(len(f.words) for f in filters.values()) <= MAX_INLINE:
        hit = F.lit(False)
        for t, f in filters.items():
            hit = F.when(F.col("tier") == t, f.has_col(F.col("key"))).otherwise(hit)
        return keys.filter(hit)
    shared = keys.sparkSession.sparkContext.broadcast(filters)

    def run(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            tier = batch.column("tier").to_numpy(zero_copy_only=False)
            key, ok = prepared(batch.column("key").to_pylist(), shared.value.values()), np.zeros(len(tier), bool)
            for t, f in shared.value.items():
                own = np.flatnonzero(tier == t)
                ok[own] = hits(f, key[own])
            yield batch.filter(pa.array(ok))

    own = keys.select("tier", "key")
    return own.mapInArrow(run, own.schema)


def probe_by_join(keys: DataFrame, table: DataFrame, filters: dict[int, Filter]) -> DataFrame:
    """keys (tier, key, all columns) that their tier's filter holds, by a join
    of bit positions with the word table: nothing is gathered, whatever the
    size of the filters."""
    spots = F.lit(None).cast("array<bigint>")
    for tier, f in filters.items():
        spots = F.when(F.col("tier") == tier, positions(F.col("key"), f)).otherwise(spots)
    flat = keys.select(*keys.columns, F.explode(F.array_distinct(spots)).alias("_p")).withColumn("word_idx", F.floor(F.col("_p") / 64).cast("int"))
    met = flat.join(table, ["tier", "word_idx"], "left")
    bit = F.coalesce(F.expr("getbit(word, cast(_p % 64 as int))"), F.lit(0).cast("tinyint"))
    return met.groupBy(*keys.columns).agg(F.min(bit).alias("_all")).filter("_all = 1").drop("_all")
