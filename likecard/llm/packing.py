"""Packing tokenised documents by shortest-pack-first over the length histogram
(operator 7)."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import balanced, cut

SIZE, END_ID, CELL = 1024, 0, 2048


def encoder(path: str):
    """Text to ids of the byte-level BPE in a tokenizers file, special strings
    included. The merges run in a library that keeps the ids and is several
    times faster; tests hold it against the tokenizers library."""
    import tiktoken

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    # The printable stand-ins of bytes in such files: printable bytes stand for themselves, the others follow from 256.
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    byte = {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}
    special = {t["content"]: t["id"] for t in spec.get("added_tokens", [])}
    ranks = {bytes(byte[c] for c in word): i for word, i in spec["model"]["vocab"].items() if word not in special}
    # Fixed value: how this vocabulary splits texts.
    split = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"
    core = tiktoken.Encoding("byte_bpe", pat_str=split, mergeable_ranks=ranks, special_tokens=special)
    return lambda text: core.encode_to_numpy(text, allowed_special="all")


def pieces(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens): each document's ids with
    an end id after them, cut at multiples of size. Null texts are empty: one id."""

    def run(batches):
        import zlib

        import numpy as np
        import pyarrow as pa

        encode = encoder(tokenizer)
        for batch in batches:
            out = [[], [], [], [], []]
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1)):
                text = (text.as_py() or "").encode("utf-8", "replace").decode("utf-8")
                ids = np.append(encode(text), END_ID).astype("<u4")
                for at in range(0, len(ids), size):
                    part = ids[at : at + size]
                    for column, value in zip(out, (doc, at, len(part), zlib.crc32(part.tobytes()), len(ids))):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long")


def patterns(histogram: dict[int, int], size: int = SIZE) -> list[tuple[tuple[int, ...], int]]:
    """(lengths in a pack, number of packs): lengths are placed longest first,
    each on the shortest packs that still have room, as many packs at a time
    as there are; what is over opens packs of its own, as many to a pack as fit."""
    open_packs: dict[int, list] = {}
    full = []

    def put(pattern, fill, count):
        if fill == size:
            full.append((pattern, count))
        else:
            open_packs.setdefault(fill, []).append((pattern, count))

    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left:
            fill = min((f for f in open_packs if f + length <= size), default=None)
            if fill is None:
                held = size // length
                if left >= held:
                    put((length,) * held, length * held, left // held)
                if left % held:
                    put((length,) * (left % held), length * (left % held), 1)
                break
            pattern, count = open_packs[fill].pop()
            if not open_packs[fill]:
                del open_packs[fill]
            n = min(count, left)
            if count > n:
                put(pattern, fill, count - n)
            put((*pattern, length), fill + length, n)
            left -= n
    return full + [p for packs in open_packs.values() for p in packs]


def pack(cut_docs: DataFrame, size: int = SIZE, cell: int = CELL) -> DataFrame:
    """The pieces with sequence_id and offset. The histogram (size entries at
    most) comes to the driver; patterns go back as intervals of ranks within a
    length. Ranks count within hashed cells of about `cell` pieces, cells of a
    length add up in order, so no length, however common, is ranked by one task."""
    spark = cut_docs.sparkSession
    counts = {r.length: r["count"] for r in cut_docs.groupBy("length").count().collect()}
    intervals, base, used = [], 0, dict.fromkeys(counts, 0)
    for pattern, n in patterns(counts, size):
        at = 0
        for length in pattern:
            intervals.append((length, used[length], used[length] + n, base - used[length], at))
            used[length] += n
            at += length
        base += n
    table = spark.createDataFrame(intervals, "length long, low long, high long, shift long, offset long")
    cells = spark.createDataFrame([(k, -(-n // cell)) for k, n in counts.items()], "length long, cells long")
    rows = cut_docs.join(F.broadcast(cells), "length").withColumn("cell", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.col("cells")))
    order = ["doc_id", "start", "ids_crc32", "doc_tokens"]
    before = Window.partitionBy("length").orderBy("cell").rowsBetween(Window.unboundedPreceding, -1)
    first = rows.groupBy("length", "cell").count().withColumn("before", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    ranked = balanced(rows, "length", "cell").withColumn("rank", F.row_number().over(Window.partitionBy("length", "cell").orderBy(*order)) - 1)
    ranked = ranked.join(first, ["length", "cell"]).withColumn("rank", F.col("rank") + F.col("before"))
    near = (ranked.length == table.length) & (F.col("rank") >= F.col("low")) & (F.col("rank") < F.col("high"))
    placed = ranked.join(F.broadcast(table), near).withColumn("sequence_id", F.col("rank") + F.col("shift"))
    return placed.select("doc_id", "start", ranked.length, "ids_crc32", "doc_tokens", "sequence_id", "offset")


def pack_documents(docs: DataFrame, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", size: int = SIZE) -> DataFrame:
    """Each document's pieces with the sequence and the offset they go to;
    sequences hold at most size ids. Rows repeated are packed each; no rows
    give none. Equal pieces of equal documents may trade places between runs."""
    return pack(cut(pieces(docs, tokenizer, id_col, text_col, size)), size)
