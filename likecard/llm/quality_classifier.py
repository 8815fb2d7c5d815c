"""Quality scores by naive Bayes support vectors (operator 6)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .hashed import Codes, token_and_form_grams
from .toxicity import features, in_order, training_rows

#: Labelled rows that the counts and the support vectors learn from at most.
MAX_COUNTED, MAX_TRAIN = 20_000, 6000
BITS, EPOCHS, SMOOTH, COST, BLEND, ACCEPT = 18, 12, 1.0, 1.0, 0.25, 0.3


def _grams(bits: int):
    return lambda text, codes: token_and_form_grams(text, codes, bits)


def log_count_ratios(docs: DataFrame, labels: DataFrame, label_col: str = "quality", bits: int = BITS):
    """Per bucket the log ratio of smoothed shares between label 1 and 0, from
    the indicators of labelled rows that may be learnt from, MAX_COUNTED at
    most. Counts are summed on the executors; 2**bits rows at most come to the
    driver."""
    import numpy as np

    make = _grams(bits)

    def run(batches):
        import numpy as np
        import pyarrow as pa

        n, codes = np.zeros((2, 1 << bits), np.int64), Codes()
        for batch in batches:
            for text, y in zip(batch.column(0), batch.column(1).to_pylist()):
                n[y][make(text.as_py() or "", codes)] += 1
        at = np.flatnonzero(n.sum(0))
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(n[0][at]), pa.array(n[1][at])], names=["at", "n0", "n1"])

    rows = training_rows(docs, labels, label_col, MAX_COUNTED).select("text", "y").mapInArrow(run, "at long, n0 long, n1 long")
    n = np.full((2, 1 << bits), SMOOTH)
    for r in rows.groupBy("at").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1")).toLocalIterator():
        n[0][r["at"]] += r.n0
        n[1][r["at"]] += r.n1
    return np.log(n[1] / n[1].sum()) - np.log(n[0] / n[0].sum())


def _scaled(buckets, ratios):
    """Indicator vector scaled by the ratios, at unit length; a bias entry ends it."""
    import numpy as np

    v = ratios[buckets]
    return np.append(v / max(1e-12, float(np.sqrt((v * v).sum()))), 0.5)


def fit_hinge(rows: list, ratios, epochs: int = EPOCHS, cost: float = COST, blend: float = BLEND):
    """Weights (buckets, then bias) of an L1-loss linear support vector machine,
    by dual coordinate descent: each dual variable in turn takes its exact
    optimum inside [0, cost]. Weights are blended with their mean size, as
    naive Bayes would have them. Costs are scaled so that both classes weigh
    the same."""
    import numpy as np

    size = len(ratios)
    w = np.zeros(size + 1)
    if not rows:
        return w
    data = [(np.append(x, size), _scaled(x, ratios), 1.0 if y else -1.0) for x, _, y in rows]
    ones = sum(s > 0 for _, _, s in data)
    top = {1.0: cost * len(data) / max(1, 2 * ones), -1.0: cost * len(data) / max(1, 2 * (len(data) - ones))}
    a, norm = np.zeros(len(data)), [float(v @ v) for _, v, _ in data]
    order = np.random.default_rng(3)
    for _ in range(epochs):
        for i in order.permutation(len(data)):
            at, v, s = data[i]
            new = min(max(a[i] - (s * (w[at] @ v) - 1) / norm[i], 0.0), top[s])
            if new != a[i]:
                w[at] += (new - a[i]) * s * v
                a[i] = new
    mean = np.abs(w[:size][w[:size] != 0]).mean() if (w[:size] != 0).any() else 0.0
    w[:size] = np.where(w[:size] != 0, (1 - blend) * w[:size] + blend * mean * np.sign(w[:size]), 0)
    return w


def calibrate(margins, y):
    """(slope, offset) of the logistic curve through margins and labels, by
    Newton steps with a small ridge."""
    import numpy as np

    x = np.column_stack([margins, np.ones(len(y))])
    b = np.array([1.0, 0.0])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ b, -35, 35)))
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag([1e-2, 1e-2])
        b = b - np.linalg.solve(h, x.T @ (p - y) + 1e-2 * (b - np.array([1.0, 0.0])))
    return float(b[0]), float(b[1])


def learnt(rows: list, ratios):
    """(weights, slope, offset) of rows [(buckets, counts, y)] in their order."""
    import numpy as np

    apart = len(rows) >= 50
    fifth = rows[::5] if apart else rows
    w = fit_hinge([r for i, r in enumerate(rows) if i % 5] if apart else rows, ratios)
    margins = np.array([w[np.append(x, len(ratios))] @ _scaled(x, ratios) for x, _, _ in fifth])
    return (w, *calibrate(margins, np.array([y for _, _, y in fifth], float)))


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "quality", most: int = MAX_TRAIN, bits: int = BITS):
    """(ratios, weights, slope, offset). The counts see MAX_COUNTED labelled rows
    at most, the support vector machine MAX_TRAIN of them, a fifth of which only
    sets the logistic curve. One task holds those rows and learns; the driver gets
    the weights. Without any label every score is 0.5."""
    import numpy as np

    ratios = log_count_ratios(docs, labels, label_col, bits)
    shared = docs.sparkSession.sparkContext.broadcast(ratios)

    def run(batches):
        import pyarrow as pa

        rows = in_order((x, y) for batch in batches for x, y in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()))
        if rows:
            w, slope, offset = learnt(rows, shared.value)
            yield pa.RecordBatch.from_arrays([pa.array([w.tobytes()], pa.binary()), pa.array([slope]), pa.array([offset])], names=["w", "slope", "offset"])

    rows = features(training_rows(docs, labels, label_col, most), _grams(bits), "x binary, y int")
    got = rows.repartition(1).mapInArrow(run, "w binary, slope double, offset double").first()
    if got is None:
        return ratios, np.zeros(len(ratios) + 1), 1.0, 0.0
    return ratios, np.frombuffer(got.w), got.slope, got.offset


def _scores(model, texts, codes, make):
    import numpy as np

    ratios, w, slope, offset = model
    out = np.empty(len(texts))
    for k, text in enumerate(texts):
        x = make(text.as_py() or "", codes)
        margin = w[np.append(x, len(ratios))] @ _scaled(x, ratios)
        out[k] = 1 / (1 + np.exp(-np.clip(slope * margin + offset, -35, 35)))
    return out


def score(docs: DataFrame, model, id_col: str = "doc_id", text_col: str = "text", bits: int = BITS) -> DataFrame:
    """(id, score) of every row. Null texts count as empty; empty texts get the
    score of the bias. The broadcast model has 2**bits entries."""
    shared, make = docs.sparkSession.sparkContext.broadcast(model), _grams(bits)

    def run(batches):
        import pyarrow as pa

        codes = Codes()
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(_scores(shared.value, batch.column(1), codes, make))], names=["id", "score"])

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).mapInArrow(run, "id long, score double")


def reject(docs: DataFrame, model, text_col: str = "text", accept: float = ACCEPT, bits: int = BITS) -> DataFrame:
    """The rows of docs, all columns, whose score is at least `accept`."""
    shared, make = docs.sparkSession.sparkContext.broadcast(model), _grams(bits)

    def run(batches):
        import pyarrow as pa

        codes = Codes()
        for batch in batches:
            texts = batch.column(batch.schema.get_field_index(text_col))
            yield batch.filter(pa.array(_scores(shared.value, texts, codes, make) >= accept))

    return docs.mapInArrow(run, docs.schema)
