"""Embedding near-duplicates by PCA-ordered tiled comparison (operator 1)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import balanced, cut
from .components import components, forest

THRESHOLD, TILE = 0.93, 2048
#: Leading principal coordinates that may cut a label into cells, and how many
#: tiles of a label each of them should part.
LEADING, FAN = 3, 8
#: Leading dimensions after which residual products are bounded.
STEPS = (6, 12, 24, 40)


def _usable(vectors: DataFrame, id_col: str, vector_col: str, label_col: str) -> DataFrame:
    v = F.col(vector_col).cast("array<double>")
    bad = F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    some = F.exists(v, lambda x: x != 0)
    rows = vectors.filter(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & F.col(vector_col).isNotNull())
    return rows.filter(~bad & some).select(F.col(id_col).cast("long").alias("id"), F.col(label_col).alias("label"), v.alias("v"))


def principal_axes(unique: DataFrame) -> dict:
    """{dimension: orthogonal matrix, columns by falling second moment}. Second
    moments of the unit vectors are summed over all rows on the executors; d * d
    sums a dimension come to the driver."""
    import numpy as np

    def moments(batches):
        import numpy as np
        import pyarrow as pa

        sums = {}
        for batch in batches:
            lists = batch.column(0)
            flat, lengths = lists.flatten().to_numpy(zero_copy_only=False), np.diff(lists.offsets.to_numpy())
            ends = np.cumsum(lengths)
            for d in np.unique(lengths):
                pick = np.flatnonzero(lengths == d)
                m = flat[(ends[pick] - d)[:, None] + np.arange(d)]
                m = m / np.abs(m).max(1, keepdims=True)
                m = m / np.linalg.norm(m, axis=1, keepdims=True)
                sums[int(d)] = sums.get(int(d), 0) + m.T @ m
        for d, m in sums.items():
            yield pa.RecordBatch.from_arrays([pa.array([d] * d * d, pa.int32()), pa.array(range(d * d), pa.int32()), pa.array(m.ravel())], names=["d", "cell", "s"])

    cells = unique.select("v").mapInArrow(moments, "d int, cell int, s double").groupBy("d", "cell").agg(F.sum("s").alias("s")).collect()
    axes: dict = {}
    for d in {r.d for r in cells}:
        m = np.zeros(d * d)
        for r in cells:
            if r.d == d:
                m[r.cell] = r.s
        _, vectors = np.linalg.eigh(m.reshape(d, d))
        axes[d] = vectors[:, ::-1].copy()
    return axes


def close_pairs(a, b, axes, threshold: float, steps=STEPS):
    """(i, j) with cosine(a[i], b[j]) >= threshold, exactly as the full double
    product decides. a and b are matrices of unit rows. Products accumulate over
    leading principal dimensions; a pair is left as soon as what is summed plus
    the product of its suffix norms cannot reach the threshold."""
    import numpy as np

    d, out_i, out_j = a.shape[1], [], []
    ra, rb = a @ axes, b @ axes
    steps = [s for s in steps if s < d]
    slack = threshold - 1e-9
    tail = lambda m, s: np.sqrt(np.maximum(0, (m[:, s:] ** 2).sum(1)))
    for at in range(0, len(a), 128):
        x, rx = a[at : at + 128], ra[at : at + 128]
        if not steps:
            i, j = map(np.ravel, np.indices((len(x), len(b))))
        else:
            s = steps[0]
            i, j = np.nonzero(rx[:, :s] @ rb[:, :s].T + tail(rx, s)[:, None] * tail(rb, s)[None, :] >= slack)
            low = s
            part = np.einsum("ij,ij->i", rx[i, :s], rb[j, :s]) if len(i) else np.zeros(0)
            for s in steps[1:]:
                if not len(i):
                    break
                part = part + np.einsum("ij,ij->i", rx[i, low:s], rb[j, low:s])
                ok = part + tail(rx, s)[i] * tail(rb, s)[j] >= slack
                i, j, part, low = i[ok], j[ok], part[ok], s
        for lo in range(0, len(i), 1 << 16):
            p, q = i[lo : lo + (1 << 16)], j[lo : lo + (1 << 16)]
            ok = np.einsum("ij,ij->i", x[p], b[q]) >= threshold
            out_i.append(p[ok] + at)
            out_j.append(q[ok])
    none = np.zeros(0, np.int64)
    return (np.concatenate(out_i), np.concatenate(out_j)) if out_i else (none, none)


def located(unique: DataFrame, axes: dict, threshold: float) -> DataFrame:
    """unique with d (dimension) and at, the cell of its unit vector on the
    LEADING principal axes: cells are as wide as two vectors at the threshold can
    be apart, so linked vectors lie in the same or in neighbouring cells."""
    width = (2 - 2 * threshold) ** 0.5 + 1e-6
    shared = unique.sparkSession.sparkContext.broadcast({d: m[:, :LEADING] for d, m in axes.items()})
    label = unique.schema["label"].dataType.simpleString()

    def run(batches):
        import numpy as np
        import pyarrow as pa

        for batch in batches:
            lists = batch.column(1)
            flat, lengths = lists.flatten().to_numpy(zero_copy_only=False), np.diff(lists.offsets.to_numpy())
            ends, at = np.cumsum(lengths), np.zeros((len(lengths), LEADING), np.int32)
            for d in np.unique(lengths):
                pick = np.flatnonzero(lengths == d)
                m = flat[(ends[pick] - d)[:, None] + np.arange(d)]
                m = m / np.abs(m).max(1, keepdims=True)
                y = (m / np.linalg.norm(m, axis=1, keepdims=True)) @ shared.value[int(d)]
                at[pick, : y.shape[1]] = np.floor(y / width)
            cells = pa.FixedSizeListArray.from_arrays(pa.array(at.ravel()), LEADING).cast(pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(lengths.astype(np.int32)), cells], names=[*batch.schema.names, "d", "at"])

    return unique.select("label", "v", "node", "copies").mapInArrow(run, f"label {label}, v array<double>, node long, copies long, d int, at array<int>")


def tiled(rows: DataFrame, threshold: float, tile: int) -> tuple[DataFrame, DataFrame]:
    """(rows with own, their tile; pairs (low, high) of tiles to compare). A label
    of one tile is whole; larger ones are cut into cells by as many leading
    coordinates as their size asks for, and cells into tiles by hash. Only tiles
    of the same or neighbouring cells are paired."""
    place = [f"c{i}" for i in range(LEADING)]
    size = rows.groupBy("label", "d").agg(F.count("*").alias("n"))
    rows = rows.join(F.broadcast(size) if size.count() < 100_000 else size, ["label", "d"])
    rows = rows.select("*", *[F.when(F.col("n") > tile * FAN**i, F.col("at")[i]).otherwise(0).alias(c) for i, c in enumerate(place)])
    key = ["label", "d", *place]
    cells = cut(rows.groupBy(*key).agg(F.ceil(F.count("*") / tile).cast("int").alias("tiles")))
    name = lambda t: F.xxhash64(*key, t)
    rows = rows.join(cells, key).select("label", "d", "node", "copies", "v", name(F.pmod(F.xxhash64("node"), F.col("tiles")).cast("int")).alias("own"))
    every = cells.select(*key, F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)).alias("t")).withColumn("a", name(F.col("t")))
    step = F.array(*[F.lit(i) for i in (-1, 0, 1)])
    near = every.select("a", *[F.col(c).alias(f"_{c}") for c in key])
    for c in place:
        near = near.withColumn("_s", F.explode(step)).withColumn(f"_{c}", F.col(f"_{c}") + F.col("_s")).drop("_s")
    met = near.join(every.select(*[F.col(c).alias(f"_{c}") for c in key], F.col("a").alias("b")), [f"_{c}" for c in key]).filter("a <= b")
    return rows, cut(met.select(F.col("a").alias("low"), F.col("b").alias("high")).distinct())


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", threshold: float = THRESHOLD, tile: int = TILE) -> DataFrame:
    """One row per vector: id, n_links (other vectors with the same label and
    cosine >= threshold), component_id (smallest id reachable over links) and
    kept (id = component_id).

    Vectors that are null, all zero, or hold null or non-finite components, and
    rows with a null label, link with nothing; so do vectors of different
    length. Equal vectors of a label meet once, with their number. Each label's
    distinct vectors lie in tiles of about `tile` rows in the order of their
    leading principal coordinates; tiles too far apart there never meet, every
    two others meet in a group of their own, whose task returns one count a
    vector and a spanning forest of its links: never the pairs. Rows with a null
    id come back with no links and a null component; an empty table gives no rows.
    """
    usable = _usable(vectors, id_col, vector_col, label_col)
    unique = cut(usable.groupBy("label", "v").agg(F.min("id").alias("node"), F.count("*").alias("copies")))
    axes = principal_axes(unique)
    rows, pairs = tiled(cut(located(unique, axes, threshold)), threshold, tile)
    own = pairs.select(F.explode(F.array_distinct(F.array("low", "high"))).alias("own"), "low", "high")
    dealt = rows.join(own, "own").select(F.xxhash64("low", "high").alias("group"), "label", "own", "low", "high", "node", "copies", "v")

    def compare(pdf):
        import numpy as np
        import pandas as pd

        found = []
        kinds = pd.DataFrame({"label": pdf["label"], "low": pdf["low"], "high": pdf["high"], "d": pdf["v"].map(len)})
        for (_, low, high, d), rows in kinds.groupby(["label", "low", "high", "d"], sort=True):
            part = pdf.loc[rows.index].sort_values("node")
            m = np.stack(part["v"].to_numpy()).astype(np.float64)
            m = m / np.abs(m).max(1, keepdims=True)
            m = m / np.linalg.norm(m, axis=1, keepdims=True)
            own, node, copies = part["own"].to_numpy(), part["node"].to_numpy(), part["copies"].to_numpy()
            a = np.flatnonzero(own == low)
            b = np.flatnonzero(own == high)
            i, j = close_pairs(m[a], m[b], axes[d], threshold)
            i, j = a[i], b[j]
            if low == high:
                keep = i < j
                i, j = i[keep], j[keep]
            n = np.zeros(len(m), np.int64)
            np.add.at(n, i, copies[j])
            np.add.at(n, j, copies[i])
            src, dst = forest(node[i], node[j])
            hit = np.flatnonzero(n)
            found.append(pd.DataFrame({"node": node[hit], "n": n[hit], "dst": pd.array([None] * len(hit), "Int64")}))
            found.append(pd.DataFrame({"node": src, "n": np.zeros(len(src), np.int64), "dst": pd.array(dst, "Int64")}))
        return pd.concat(found) if found else pd.DataFrame({"node": [], "n": [], "dst": []})

    met = cut(balanced(dealt, "group").groupBy("group").applyInPandas(compare, "node long, n long, dst long"))
    counts = met.groupBy("node").agg(F.sum("n").alias("n"))
    linked = components(met.filter("dst is not null").select(F.col("node").alias("src"), "dst"))
    named = unique.join(counts, "node", "left").join(linked, "node", "left")
    named = cut(named.select("label", "v", (F.coalesce("n", F.lit(0)) + F.col("copies") - 1).alias("n"), F.coalesce("component", "node").alias("component")))
    found = usable.join(named, ["label", "v"]).select("id", "n", "component")
    out = vectors.select(F.col(id_col).cast("long").alias("_id")).join(found.dropDuplicates(["id"]), F.col("_id") == F.col("id"), "left")
    component = F.coalesce("component", "_id")
    return out.select(F.col("_id").alias(id_col), F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), (F.col("_id") == component).alias("kept"))
