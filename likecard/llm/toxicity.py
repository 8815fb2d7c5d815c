"""Toxicity scores by FTRL-proximal logistic regression over hashed word
n-grams and skip-grams (operator 4)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import is_held_out
from .hashed import Codes, word_and_skip_grams

BITS, MAX_TRAIN, EPOCHS, MAX_FEATURES = 20, 10_000, 6, 8192
#: The least log loss of twenty settings on a quarter of sf0.1's learnable labelled
#: rows, trained on the other three; held-out rows took no part in this choice.
ALPHA, BETA, L1, L2, LENGTH, BIAS = 3.0, 1.0, 5.0, 0.01, 10.0, 0.3


def weighted(buckets):
    """(bucket, value): 1 + log of the count, scaled to one length for all texts."""
    import numpy as np

    return scaled(*np.unique(buckets, return_counts=True))


def scaled(at, n):
    import numpy as np

    v = 1 + np.log(n)
    return at.astype(np.int32), v * (LENGTH / max(1e-12, float(np.sqrt((v * v).sum()))))


def counted(buckets, most: int = MAX_FEATURES):
    """Different buckets with their counts; of a text with more than `most`, those
    first by a hash of the bucket."""
    import numpy as np

    at, n = np.unique(buckets, return_counts=True)
    if len(at) > most:
        h = at.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        keep = np.sort(np.argsort(h ^ (h >> np.uint64(31)), kind="stable")[:most])
        at, n = at[keep], n[keep]
    return at.astype(np.int32), n.astype(np.int32)


def features(rows: DataFrame, make, columns: str):
    """Feature buckets and counts as int32 bytes, beside the label, of (text, y)
    rows. MAX_FEATURES a text bound what a training row sends to the driver."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        codes = Codes()
        for batch in batches:
            found = [np.concatenate(counted(make(t.as_py() or "", codes))).tobytes() for t in batch.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.binary()), batch.column(1)], names=["x", "y"])

    return rows.select("text", "y").mapInArrow(run, columns)


def training_rows(docs: DataFrame, labels: DataFrame, label_col: str, most: int) -> DataFrame:
    """(text, y) of labelled documents that may be learnt from; `most` of them at
    most, the least by a hash of the id (the documented bound of the sample, and
    so of what is broadcast). Of rows that share an id one text is taken."""
    y = labels.filter(F.col(label_col).isin(0, 1) & F.col("doc_id").isNotNull() & ~is_held_out(F.col("doc_id")))
    y = y.groupBy("doc_id").agg(F.max(label_col).cast("int").alias("y"))
    key = F.xxhash64(F.col("doc_id").cast("long"), F.lit(5))
    y = y.orderBy(key, "doc_id").limit(most)
    rows = docs.select("doc_id", "text").join(F.broadcast(y), "doc_id")
    return rows.groupBy("doc_id", "y").agg(F.min_by("text", F.xxhash64("text")).alias("text")).select("text", "y")


def in_order(rows) -> list:
    """[(buckets, counts, y)] of rows (x, y) of `features`, in an order set by hashes alone."""
    import numpy as np
    import xxhash

    rows = [(*np.frombuffer(x, np.int32).reshape(2, -1), y) for x, y in rows]
    return sorted(rows, key=lambda r: (xxhash.xxh64_intdigest(r[0].tobytes() + r[1].tobytes()), r[2]))


def collect_sample(docs: DataFrame, labels: DataFrame, label_col: str, most: int, make) -> list:
    """[(buckets, counts, y)] of the bounded sample, in an order set by hashes alone."""
    return in_order((r.x, r.y) for r in features(training_rows(docs, labels, label_col, most), make, "x binary, y int").toLocalIterator())


def train(rows: list, bits: int = BITS, epochs: int = EPOCHS, alpha: float = ALPHA, beta: float = BETA, l1: float = L1, l2: float = L2):
    """(indices, weights, bias) of the nonzero coordinates after FTRL-proximal
    passes over [(buckets, counts, y)]: each coordinate has its own learning rate from
    its squared gradients, and stays zero until its sum passes l1."""
    import numpy as np

    size = 1 << bits
    z, n = np.zeros(size + 1), np.zeros(size + 1)
    data = []
    for at, n_of, y in rows:
        at, v = scaled(at, n_of)
        data.append((np.append(at, size).astype(np.int32), np.append(v, BIAS).astype(np.float32), y))

    def weights(at):
        free = np.where(at == size, 0.0, l1)
        over = np.maximum(np.abs(z[at]) - free, 0)
        return -np.sign(z[at]) * over / ((beta + np.sqrt(n[at])) / alpha + l2)

    for _ in range(epochs):
        for at, v, y in data:
            w = weights(at)
            p = 1 / (1 + np.exp(-np.clip(w @ v, -35, 35)))
            g = (p - y) * v
            sigma = (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / alpha
            z[at] += g - sigma * w
            n[at] += g * g
    used = np.flatnonzero(n)
    w = weights(used)
    keep = (w != 0) & (used != size)
    bias = float(weights(np.array([size]))[0] * BIAS)
    return used[keep].astype(np.int32), w[keep], bias


def score(docs: DataFrame, model, id_col: str = "doc_id", text_col: str = "text", bits: int = BITS) -> DataFrame:
    """(id, score double) of every row; null texts count as empty and get the
    score of the bias alone. The broadcast weights have 2**bits entries at most."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        import numpy as np
        import pyarrow as pa

        at, w, bias = shared.value
        dense, codes = np.zeros(1 << bits), Codes()
        dense[at] = w
        for batch in batches:
            out = []
            for text in batch.column(1):
                i, v = weighted(word_and_skip_grams(text.as_py() or "", codes, bits))
                out.append(1 / (1 + np.exp(-np.clip(dense[i] @ v + bias, -35, 35))))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.float64())], names=["id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "id long, score double")


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "toxic", most: int = MAX_TRAIN, bits: int = BITS):
    """Weights from the labelled rows that may be learnt from, MAX_TRAIN at
    most. Without any label every score is 0.5."""
    return train(collect_sample(docs, labels, label_col, most, lambda text, codes: word_and_skip_grams(text, codes, bits)), bits)
