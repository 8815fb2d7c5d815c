"""Substring dedup by content-defined chunks of a gear rolling hash (operator 10)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut

#: One boundary in CHUNK bytes on average. A passage is reported if its whole
#: chunks hold CERTAIN words, and PASSAGE with the chunks its ends may lie in.
CHUNK, CERTAIN, PASSAGE = 32, 12, 50


def boundaries(data: bytes, chunk: int = CHUNK):
    """Ends of the chunks of data (the last end is its length).

    The gear hash at a byte sums table values of the 16 bytes up to it, each
    doubled once per byte passed, modulo 2**16: a cut depends on those bytes
    alone, so an insertion moves no cut but those next to it. All positions are
    hashed at once, doubling the window four times.
    """
    import numpy as np

    table = np.random.default_rng(1009).integers(0, 2**16, 256, dtype=np.uint16)
    h = table[np.frombuffer(data, np.uint8)]
    for width in (1, 2, 4, 8):
        h[width:] = h[width:] + (h[:-width] << np.uint16(width)) if len(h) > width else h[width:]
    at = np.flatnonzero(h < 65536 // chunk) + 1
    return at if len(at) and at[-1] == len(data) else np.append(at, len(data))


def chunks(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chunk: int = CHUNK) -> DataFrame:
    """(id, digests, words, ends), arrays with an entry a chunk: a 64-bit digest,
    the number of words that start in it, and its end in UTF-8 bytes. Null and
    empty texts have no chunks."""

    def run(batches):
        import numpy as np
        import pyarrow as pa
        import xxhash

        digest, space = xxhash.xxh3_64_digest, np.zeros(256, bool)
        space[[32, 9, 10, 11, 12, 13]] = True
        for batch in batches:
            digests, words, ends = [], [], []
            for text in batch.column(1):
                data = (text.as_py() or "").encode("utf-8", "surrogatepass")
                at = boundaries(data, chunk) if data else np.zeros(0, np.int64)
                starts = np.append(0, at[:-1])[: len(at)]
                white = space[np.frombuffer(data, np.uint8)]
                first = np.append(0, np.cumsum(~white & np.append(True, white)[: len(white)]))
                digests.append(np.frombuffer(b"".join([digest(data[p:q]) for p, q in zip(starts.tolist(), at.tolist())]), ">i8").astype(np.int64))
                words.append((first[at] - first[starts]).astype(np.int32))
                ends.append(at.astype(np.int32))
            arrays = [pa.array(digests, pa.list_(pa.int64())), pa.array(words, pa.list_(pa.int32())), pa.array(ends, pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays([batch.column(0), *arrays], names=["id", "digests", "words", "ends"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "id long, digests array<long>, words array<int>, ends array<int>")


def passages_of(words, ends, digests, seqs, least, own, certain: int = CERTAIN, passage: int = PASSAGE) -> list[dict]:
    """Maximal runs of chunks (seqs, ascending) that are repeated, long enough to
    report. removed: words of chunks that a document with a smaller id (least is
    not own), or an earlier place of this one, has already; cuts: their numbers."""
    found, i, seen = [], 0, set()
    while i < len(seqs):
        j = i
        while j + 1 < len(seqs) and seqs[j + 1] == seqs[j] + 1:
            j += 1
        low, high = int(seqs[i]), int(seqs[j])
        sure = int(sum(words[low : high + 1]))
        most = int(sum(words[max(0, low - 1) : high + 2]))
        if sure >= certain and most >= passage:
            removed, cuts = 0, []
            for k in range(i, j + 1):
                if least[k] != own or digests[seqs[k]] in seen:
                    removed += int(words[seqs[k]])
                    cuts.append(int(seqs[k]))
                seen.add(digests[seqs[k]])
            start = int(ends[low - 1]) if low else 0
            found.append({"start": start, "end": int(ends[high]), "words": sure, "removed": removed, "cuts": cuts, "first_docs": sorted({int(x) for x in least[i : j + 1]})})
        i = j + 1
    return found


def repeated_within(digests):
    """Numbers of the chunks that a document holds twice or more."""
    import numpy as np

    _, at, n = np.unique(digests, return_inverse=True, return_counts=True)
    return np.flatnonzero(n[at] > 1)


def spans_of(chunks: list[int], ends) -> list[dict]:
    """Byte spans of chunk numbers, neighbours joined."""
    out: list[dict] = []
    for k in sorted(set(chunks)):
        start, end = int(ends[k - 1]) if k else 0, int(ends[k])
        if out and out[-1]["end"] == start:
            out[-1]["end"] = end
        else:
            out.append({"start": start, "end": end})
    return out


def without(data: bytes, spans: list[dict]) -> bytes:
    """UTF-8 text without byte spans; a character that a span holds in part stays."""
    out, at = [], 0
    inside = lambda p: p < len(data) and data[p] & 0xC0 == 0x80
    for s in spans:
        low, high = s["start"], s["end"]
        while inside(low):
            low += 1
        while high > low and inside(high):
            high -= 1
        if high > low:
            out.append(data[at:low])
            at = high
    return b"".join([*out, data[at:]])


def repeats(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chunk: int = CHUNK, certain: int = CERTAIN, passage: int = PASSAGE) -> DataFrame:
    """One row per row of docs: id, n_chunks, n_repeated (chunks found in other
    documents too), passages, an array of (start, end in UTF-8 bytes, words,
    removed, first_docs), within, the same for passages that this document
    itself holds twice or more, and spans, the bytes to take out so that one
    copy of each passage stays: the first place in the document with the least id.

    Digests are counted with partial sums, so a chunk in a third of all
    documents is a row a task; repeated digests are written, and the join back
    splits where one is hot. Null and empty texts have no chunks; rows that
    share an id count as one document; rows with a null id match nothing.
    """
    table = cut(chunks(docs, id_col, text_col, chunk).withColumn("row", F.monotonically_increasing_id()))
    flat = table.filter("id is not null").select("row", "id", F.posexplode("digests").alias("seq", "digest"))
    shared = flat.groupBy("digest").agg(F.min("id").alias("least"), F.max("id").alias("most")).filter("least < most")
    shared = cut(shared.select("digest", "least"))
    marks = flat.select("row", "seq", "digest").join(shared, "digest").groupBy("row").agg(F.sort_array(F.collect_list(F.struct("seq", "least"))).alias("marks"))
    rows = table.join(marks, "row", "left").select("id", "digests", "words", "ends", F.col("marks.seq").alias("seqs"), F.col("marks.least").alias("least"))

    def run(batches):
        import numpy as np
        import pyarrow as pa

        cut_kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("words", pa.int64()), ("removed", pa.int64()), ("first_docs", pa.list_(pa.int64()))]))
        for batch in batches:
            sizes, hits, out, inner, spans = [], [], [], [], []
            for own, digests, words, ends, seqs, least in zip(*(batch.column(i) for i in range(6))):
                seqs, least = (np.asarray(x.values.to_numpy(zero_copy_only=False)) if x.is_valid else np.zeros(0, np.int64) for x in (seqs, least))
                sizes.append(len(words.values) if words.is_valid else 0)
                hits.append(len(seqs))
                full = [x.values.to_numpy(zero_copy_only=False) for x in (words, ends, digests)] if sizes[-1] else None
                out.append(passages_of(*full, seqs, least, own.as_py(), certain, passage) if len(seqs) else [])
                again = repeated_within(full[2]) if full and own.is_valid else []
                inner.append(passages_of(*full, again, [own.as_py()] * len(again), own.as_py(), certain, passage) if len(again) else [])
                chosen = [k for p in out[-1] + inner[-1] for k in p["cuts"]]
                spans.append(spans_of(chosen, full[1]) if chosen else [])
            arrays = [pa.array(sizes, pa.int64()), pa.array(hits, pa.int64()), pa.array(out, kind), pa.array(inner, kind), pa.array(spans, cut_kind)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *arrays], names=["id", "n_chunks", "n_repeated", "passages", "within", "spans"])

    found = "array<struct<start: long, end: long, words: long, removed: long, first_docs: array<long>>>"
    return rows.mapInArrow(run, f"id long, n_chunks long, n_repeated long, passages {found}, within {found}, spans array<struct<start: long, end: long>>")


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs, all rows and columns, without repeated passages: of each one copy
    stays, the first place in the document with the least id (see `repeats`).

    Chunk edges are those of the hash, so a few bytes at the ends of a passage
    stay. Null texts stay null; rows with a null id, and rows that share an id,
    stay as they are; an empty table gives no rows.
    """
    found = repeats(docs, id_col, text_col, **options).filter("id is not null").groupBy(F.col("id").alias("_id"))
    found = found.agg(F.count("*").alias("_n"), F.first("spans").alias("_spans")).filter("_n = 1 and size(_spans) > 0").drop("_n")
    rows = docs.join(cut(found), F.col(id_col).cast("long") == F.col("_id"), "left").drop("_id")

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            at, spans = batch.schema.get_field_index(text_col), batch.column(batch.schema.get_field_index("_spans"))
            texts = [
                without(t.as_py().encode("utf-8", "surrogatepass"), s.as_py()).decode("utf-8", "surrogatepass") if t.is_valid and s.is_valid else t.as_py()
                for t, s in zip(batch.column(at), spans)
            ]
            yield batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type)).drop_columns(["_spans"])

    return rows.select(*[F.col(text_col).cast("string").alias(text_col) if c == text_col else c for c in docs.columns], "_spans").mapInArrow(run, docs.schema)
