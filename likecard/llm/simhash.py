"""SimHash near-duplicates by pivot distance tables (operator 8)."""

from __future__ import annotations

from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import balanced, cut
from .components import components, forest

SHINGLE, MAX_BITS, PIVOTS, BUCKET_TILE = 4, 4, 24, 4096


#: Bytes of a sketch: one min-hash each.
MINIMA = 16
#: Bands of minima: sets at a similarity of 0.8 share one with probability
#: 0.9996. Rows with sets that meet in one group are two such tiles at most.
BANDS, WIDTH, SET_TILE = 20, 5, 1024


def _multipliers(seed: int, count: int):
    import numpy as np

    return np.random.default_rng(seed).integers(0, 2**63, count, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def _minima(h, odd):
    """The least of the shingle hashes under each of the odd multipliers."""
    import numpy as np

    low = np.full(len(odd), 2**64 - 1, np.uint64)
    for at in range(0, len(h), 1024):
        x = h[at : at + 1024]
        x = (x ^ (x >> np.uint64(31)))[:, None] * odd
        low = np.minimum(low, (x ^ (x >> np.uint64(32))).min(0))
    return low


def _sketch(h) -> bytes:
    """A byte of each of MINIMA minima of the shingle hashes under odd multipliers."""
    import numpy as np

    odd = _multipliers(77, MINIMA)
    low = _minima(h, odd) * odd
    return ((low ^ (low >> np.uint64(29))) >> np.uint64(7)).astype(np.uint8).tobytes()


def _bands(h, odd) -> list[int]:
    """A signed key of each band of minima; none for no shingles."""
    import xxhash

    low = _minima(h, odd).reshape(BANDS, WIDTH)
    return [int.from_bytes(xxhash.xxh64_digest(row.tobytes(), i), "little", signed=True) for i, row in enumerate(low)] if len(h) else []


def _shingle_hashes(text: str | None, shingle: int):
    """XXH64 values (seed 42) of the word shingles of a text, repeats included."""
    import numpy as np
    import xxhash

    digest, found = xxhash.xxh64_intdigest, (text or "").encode().lower().split()
    if not found:
        return np.zeros(0, np.uint64)
    line, n = b" ".join(found), len(found)
    lengths = np.fromiter(map(len, found), np.int64, n)
    ends = np.cumsum(lengths + 1) - 1
    k = min(shingle, n)
    starts, stops = (ends - lengths)[: n - k + 1].tolist(), ends[k - 1 :].tolist()
    return np.fromiter((digest(line[p:q], 42) for p, q in zip(starts, stops)), np.uint64, len(starts))


def _set_of(h) -> tuple[bytes, tuple[int, int]]:
    """The different shingle hashes in order, and two halves of their digest."""
    import numpy as np
    import xxhash

    data = np.unique(h).tobytes()
    digest = xxhash.xxh3_128_digest(data)
    return data, tuple(np.frombuffer(digest, "<i8").tolist())


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, sketch: bool = False) -> DataFrame:
    """(id, fp long, s0 long, s1 long) for every row; s0 and s1 hold a min-hash
    sketch of the shingles if asked for, else 0. fp: bit i is set where over half of the XXH64
    values (seed 42) of the word shingles, repeats included, have it set.
    With a sketch also d0, d1 (a digest of the shingle set) and bands (keys of
    its bands of minima).

    A-Z are lower-cased; words are split at ASCII white space; fewer words than
    a shingle: the whole sequence is one. Null, empty and blank texts: 0.
    """
    schema = "id long, fp long, s0 long, s1 long" + (", d0 long, d1 long, bands array<long>" if sketch else "")

    def run(batches):
        import numpy as np
        import pyarrow as pa

        odd = _multipliers(78, BANDS * WIDTH)
        for batch in batches:
            ids, out, sketches, digests, bands = batch.column(0), [], [], [], []
            for text in batch.column(1):
                h = _shingle_hashes(text.as_py(), shingle)
                ones = np.zeros(64, np.int64)
                for at in range(0, len(h), 8192):
                    ones += np.unpackbits(h[at : at + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
                out.append(int.from_bytes(np.packbits(2 * ones > len(h), bitorder="little").tobytes(), "little", signed=True))
                sketches.append(_sketch(h) if sketch and len(h) else bytes(MINIMA))
                if sketch:
                    digests.append(_set_of(h)[1])
                    bands.append(_bands(h, odd))
            pair = np.frombuffer(b"".join(sketches), "<i8").reshape(-1, 2)
            columns = {"id": ids.cast(pa.int64()), "fp": pa.array(out, pa.int64()), "s0": pa.array(pair[:, 0]), "s1": pa.array(pair[:, 1])}
            if sketch:
                columns |= {"d0": pa.array([d[0] for d in digests], pa.int64()), "d1": pa.array([d[1] for d in digests], pa.int64()), "bands": pa.array(bands, pa.list_(pa.int64()))}
            yield pa.RecordBatch.from_arrays(list(columns.values()), names=list(columns))

    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text")).mapInArrow(run, schema)


def shingle_sets(docs: DataFrame, text_col: str = "text", shingle: int = SHINGLE) -> DataFrame:
    """(d0, d1, shingles): the digest and the sorted 64-bit shingle hashes, as
    bytes, of each different shingle set."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            found = [_set_of(_shingle_hashes(text.as_py(), shingle)) for text in batch.column(0)]
            columns = [pa.array([d[0] for _, d in found], pa.int64()), pa.array([d[1] for _, d in found], pa.int64()), pa.array([data for data, _ in found], pa.binary())]
            yield pa.RecordBatch.from_arrays(columns, names=["d0", "d1", "shingles"])

    return docs.select(F.col(text_col).alias("text")).mapInArrow(run, "d0 long, d1 long, shingles binary").dropDuplicates(["d0", "d1"])


def _blocks(count: int) -> list[tuple[int, int]]:
    edges = [64 * i // count for i in range(count + 1)]
    return [(low, high - low) for low, high in zip(edges, edges[1:])]


def pivot_table(fps, pivots: int):
    """Hamming distances (uint8, one row per pivot) of fingerprints to fixed
    pseudo-random reference fingerprints."""
    import numpy as np

    refs = np.random.default_rng(20240229).integers(0, 2**64, pivots, dtype=np.uint64)
    return np.bitwise_count(fps[None, :] ^ refs[:, None]).astype(np.int8)


def _close_pairs(groups, fps, sketches, max_bits: int, pivots: int, agree: int):
    """Index pairs (i, j) in arrays sorted by group: same group and at most
    max_bits differing bits. Pairs are met lag by lag, whole arrays at a time;
    pivot after pivot discards those whose table entries differ by more than
    max_bits (the triangle inequality makes that safe), an exclusive-or verifies
    the rest, and so do `agree` equal bytes of the sketches, if over 0."""
    import numpy as np

    far = pivot_table(fps, pivots)
    left, right, at, lag = [], [], np.arange(max(0, len(fps) - 1)), 1
    while True:
        at = at[: np.searchsorted(at, len(fps) - lag)]
        at = at[groups[at] == groups[at + lag]]
        if not len(at):
            break
        near = at
        for row in far:
            near = near[np.abs(row[near] - row[near + lag]) <= max_bits]
            if not len(near):
                break
        near = near[np.bitwise_count(fps[near] ^ fps[near + lag]) <= max_bits]
        if agree and len(near):
            near = near[(sketches[near] == sketches[near + lag]).sum(1) >= agree]
        left.append(near)
        right.append(near + lag)
        lag += 1
    none = np.zeros(0, np.int64)
    return (np.concatenate(left), np.concatenate(right)) if left else (none, none)


def _tiled(rows: DataFrame, tile: int, by: Column) -> DataFrame:
    """rows with a bucket; those over `tile` rows are cut by the hash `by` into
    tiles that meet two by two in buckets of their own."""
    names = rows.columns
    hot = cut(rows.groupBy("bucket").count().filter(F.col("count") > tile).select("bucket", F.ceil(F.col("count") / tile).cast("int").alias("tiles")))
    if hot.isEmpty():
        return rows
    rows = rows.join(hot, "bucket", "left").withColumn("own", F.pmod(by, F.col("tiles")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.when(F.col("tiles").isNull(), F.array(F.lit(0))).otherwise(F.sequence(F.lit(0), F.col("tiles") - 1))))
    low, high = F.least("own", "other"), F.greatest("own", "other")
    return rows.withColumn("bucket", F.when(F.col("tiles").isNull(), F.col("bucket")).otherwise(F.xxhash64("bucket", low, high))).select(names)


def links(unique: DataFrame, max_bits: int = MAX_BITS, pivots: int = PIVOTS, tile: int = BUCKET_TILE, agree: int = 0) -> DataFrame:
    """(src, dst): links that connect exactly what fingerprints at most max_bits
    apart, with `agree` equal bytes of their sketches, connect. unique: (node,
    fp, s0, s1), all long, each combination of the last three once.

    The 64 bits are cut into max_bits + 2 blocks; of a linked pair at least two
    blocks are equal, so the pair meets in the bucket of those two. Buckets over
    `tile` rows are cut into tiles that meet two by two in groups of their own.
    In each group the pivot table discards pairs, and of the verified ones a
    spanning forest leaves the task.
    """
    blocks = _blocks(max_bits + 2)
    part = lambda at, width: F.shiftrightunsigned("fp", at).bitwiseAND(F.lit((1 << width) - 1))
    keys = [F.xxhash64(part(*x), part(*y), F.lit(i)) for i, (x, y) in enumerate(combinations(blocks, 2))]
    rows = unique.select("node", "fp", "s0", "s1", F.explode(F.array(*keys)).alias("bucket"))
    rows = _tiled(rows, tile, F.xxhash64("fp", "s0", F.lit(7)))

    def run(batches):
        import numpy as np
        import pyarrow as pa

        rest = None

        def found(columns):
            group, node, fps, s0, s1 = columns
            sketches = np.column_stack([s0, s1]).view(np.uint8) if agree else None
            i, j = _close_pairs(group, fps.view(np.uint64), sketches, max_bits, pivots, agree)
            src, dst = forest(node[i], node[j])
            return pa.RecordBatch.from_arrays([pa.array(src, pa.int64()), pa.array(dst, pa.int64())], names=["src", "dst"])

        for batch in batches:
            new = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(5)]
            rest = new if rest is None else [np.concatenate(x) for x in zip(rest, new)]
            edge = int(np.searchsorted(rest[0], rest[0][-1])) if len(rest[0]) else 0
            if edge > 60_000:
                yield found([x[:edge] for x in rest])
                rest = [x[edge:] for x in rest]
        if rest is not None and len(rest[0]) > 1:
            yield found(rest)

    rows = rows.select("bucket", "node", "fp", "s0", "s1").repartition(int(unique.sparkSession.conf.get("spark.sql.shuffle.partitions")), "bucket")
    return rows.sortWithinPartitions("bucket").mapInArrow(run, "src long, dst long")


def _alike(sets, similarity: float):
    """Index pairs that connect exactly the sets (sorted uint64 arrays) whose
    Jaccard similarity is at least that; sets connected already meet no more."""
    import numpy as np

    sizes = np.array([len(x) for x in sets])
    flat = np.unique(np.concatenate(sets), return_inverse=True)[1]
    own, mark = np.split(flat, np.cumsum(sizes)[:-1]), np.zeros(flat.max() + 1, np.int32)
    group, found = np.arange(len(sets)), []
    for i in range(len(sets) - 1):
        j = i + 1 + np.flatnonzero(group[i + 1 :] != group[i])
        j = j[np.minimum(sizes[j], sizes[i]) + 1e-9 >= similarity * np.maximum(sizes[j], sizes[i])]
        if not len(j):
            continue
        mark[own[i]] = 1
        common = np.add.reduceat(mark[np.concatenate([own[x] for x in j])], np.cumsum(sizes[j]) - sizes[j])
        mark[own[i]] = 0
        for x in j[common + 1e-9 >= similarity * (sizes[i] + sizes[j] - common)].tolist():
            if group[x] != group[i]:
                found.append((i, x))
                group[group == group[x]] = group[i]
    return found


def verified(rows: DataFrame, sets: DataFrame, similarity: float, tile: int = SET_TILE) -> DataFrame:
    """(src, dst): links that connect exactly what rows of one bucket connect
    whose shingle sets have at least that Jaccard similarity. rows: (bucket,
    node, d0, d1); sets: shingle_sets. Buckets with the same rows count once."""
    ends = rows.groupBy("bucket").agg(F.min("node").alias("low"), F.max("node").alias("high"), F.count("*").alias("k"), F.bit_xor(F.xxhash64("node", "d0", "d1")).alias("mix")).filter("low < high")
    ends = cut(ends.groupBy("low", "high", "k", "mix").agg(F.min("bucket").alias("bucket")))
    rows = cut(rows.join(ends.select("bucket"), "bucket", "left_semi"))
    rows = cut(_tiled(rows, tile, F.xxhash64("node", "d0", F.lit(7))).select("bucket", "node", "d0", "d1"))

    def run(batches):
        import numpy as np
        import pyarrow as pa

        def found(rows):
            if len({n for n, _ in rows}) < 2:
                return []
            return [(rows[i][0], rows[j][0]) for i, j in _alike([np.frombuffer(x, np.uint64) for _, x in rows], similarity)]

        last, rest = None, []
        for batch in batches:
            pairs = []
            for bucket, node, data in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist()):
                if bucket != last:
                    pairs += found(rest)
                    last, rest = bucket, []
                if data:
                    rest.append((node, data))
            yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in pairs], pa.int64()), pa.array([b for _, b in pairs], pa.int64())], names=["src", "dst"])
        pairs = found(rest)
        yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in pairs], pa.int64()), pa.array([b for _, b in pairs], pa.int64())], names=["src", "dst"])

    full = rows.join(sets, ["d0", "d1"]).select("bucket", "node", "shingles")
    return balanced(full, "bucket").sortWithinPartitions("bucket").mapInArrow(run, "src long, dst long")


def groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, max_bits: int = MAX_BITS, similarity: float | None = None) -> DataFrame:
    """(id, fp, component) for every row of docs with an id; component is the
    smallest id linked, directly or through others, by fingerprints at most
    max_bits apart.

    similarity changes what a link is: shingle sets with at least that Jaccard
    similarity, computed on the sets. Candidates are then rows that share a band
    of minima, and the links by fingerprints at most max_bits apart whose
    sketches are not clearly below it. Equal rows count once in the search.
    Rows with a null id come back with a null component; repeated ids keep one
    row each; no rows give none.
    """
    from math import ceil

    exact = similarity is not None
    key, agree = ["fp", "s0", "s1"] + ["d0", "d1"] * exact, ceil(MINIMA * (similarity - 0.25)) if exact else 0
    prints = cut(fingerprints(docs, id_col, text_col, shingle, exact))
    unique = cut(prints.filter("id is not null").groupBy(*key).agg(F.min("id").alias("node"), *[F.first("bands").alias("bands")] * exact))
    linked = links(unique, max_bits, agree=agree)
    if exact:
        near = linked.filter("src != dst").withColumn("bucket", F.xxhash64("src", "dst")).select("bucket", F.explode(F.array("src", "dst")).alias("node"))
        rows = unique.select(F.explode("bands").alias("bucket"), "node", "d0", "d1").unionByName(near.join(unique.select("node", "d0", "d1"), "node"))
        rows = cut(rows.distinct())
        shared = rows.groupBy("bucket").agg(F.min("node").alias("low"), F.max("node").alias("high")).filter("low < high")
        wanted = cut(rows.join(shared, "bucket", "left_semi").select(F.col("node").alias("_node")).distinct())
        some = docs.join(wanted, F.col(id_col).cast("long") == F.col("_node"), "left_semi")
        linked = verified(rows, cut(shingle_sets(some, text_col, shingle)), similarity)
    linked = components(linked)
    named = cut(unique.join(linked, "node", "left").select(*key, F.coalesce("component", "node").alias("component")))
    out = prints.join(named, key, "left")
    return out.select("id", "fp", F.when(F.col("id").isNotNull(), F.col("component")).alias("component"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = SHINGLE, max_bits: int = MAX_BITS, similarity: float | None = None) -> DataFrame:
    """The rows of docs, all columns, whose id is the smallest of its group; of
    rows repeating that id, one. Rows with a null id stay."""
    kept = groups(docs, id_col, text_col, shingle, max_bits, similarity).filter("id = component").select(F.col("id").alias("_id")).distinct()
    once = docs.filter(F.col(id_col).isNotNull()).join(kept, F.col(id_col) == F.col("_id"), "left_semi")
    return once.dropDuplicates([id_col]).unionByName(docs.filter(F.col(id_col).isNull()))
