import re
import zlib
from collections import Counter, defaultdict
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from .conftest import HARD
from likecard.llm import mixing, packing, queries


def test_targets():
    assert mixing.targets([("a", 100), ("b", 100), ("c", 100)]) == pytest.approx([200, 450 * 0 + 250 * 2 / 3, 250 / 3])
    assert mixing.targets([("a", 10), ("b", 1000)]) == pytest.approx([20, 1495])
    assert mixing.targets([]) == [] and mixing.targets([("a", 0)]) == [0.0]


@pytest.fixture(scope="module")
def many(docs):
    rng = np.random.default_rng(5)
    names = ["b", "a", None, "Z", "é"]
    return [(i, " ".join(["w"] * int(rng.integers(0, 200))), names[int(rng.integers(0, 5))] if i % 3 else "a") for i in range(900)]


def brute_targets(sizes):
    """Targets by water-filling in exact fractions: sources by code point, null last."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    left, free, out = Fraction(3, 2) * sum(sizes.values()), set(names), {}
    while free:
        share = {s: left * weight[s] / sum(weight[x] for x in free) for s in free}
        full = {s for s in free if share[s] > 2 * sizes[s]}
        out |= {s: Fraction(2 * sizes[s]) for s in full} if full else share
        left, free = left - sum(2 * sizes[s] for s in full), (free - full if full else set())
    return {s: float(x) for s, x in out.items()}


def test_op3_against_brute_force(spark, sf, tmp_path):
    """The query on the given documents and on rows that share ids, or have none."""
    given = spark.read.parquet(f"{sf}/documents.parquet")
    more = given.limit(40).withColumn("doc_id", F.lit(None).cast("long")).unionByName(given.limit(30).withColumn("doc_id", F.lit(5).cast("long")))
    given.unionByName(more).unionByName(more).write.parquet(f"{tmp_path}/documents.parquet")
    for d in (sf, str(tmp_path)):
        text = [(r.doc_id, r.source, r.text) for r in spark.read.parquet(f"{d}/documents.parquet").collect()]
        size = Counter()
        for _, s, t in text:
            size[s] += len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
        want, got = brute_targets(size), queries.op3_mixing(spark, d).collect()
        ids = lambda rows: Counter((i, n) for i, n in rows)
        assert ids((r.doc_id, r.size) for r in got) == ids((i, len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))) for i, _, t in text)
        taken = Counter()
        for r in got:
            taken[r.source] += r.taken
            assert r.source_size == size[r.source] and r.target == pytest.approx(want[r.source]) and 0 <= r.taken <= 2 * r.size
        assert all(abs(taken[s] - want[s]) <= max(r.size for r in got if r.source == s) for s in want)


@pytest.mark.parametrize("leaf", [16, 8192])
def test_mix(spark, docs, many, leaf):
    out = mixing.mix(docs(many).withColumn("size", F.lit("clash")).withColumn("x", F.lit(0)), leaf=leaf).collect()
    assert len(out) == len(many)
    by = defaultdict(list)
    for r in out:
        by[r.source].append(r)
        assert r.taken == r.copies * r.size and r.copies in (0, 1, 2)
    total = sum(r.size for r in out)
    order = sorted(by, key=lambda s: (s is None, s or ""))
    want = dict(zip(order, mixing.targets([(s, sum(r.size for r in by[s])) for s in order])))
    assert sum(want.values()) == pytest.approx(1.5 * total)
    for s, rows in by.items():
        assert rows[0].target == pytest.approx(want[s]) and rows[0].source_size == sum(r.size for r in rows)
        assert abs(sum(r.taken for r in rows) - want[s]) <= 200


def test_mix_does_not_depend_on_partitions(spark, docs, many):
    a, b = (sorted(tuple(r) for r in mixing.mix(docs(many).repartition(n), leaf=16).select("doc_id", "taken").collect()) for n in (1, 7))
    assert a == b


def test_rounding_keeps_expectation():
    import pandas as pd

    x = np.array([0.3, 0.6, 0.45, 0.9, 0.1])
    size = np.array([5, 3, 8, 2, 4])
    total = np.zeros(5)
    for seed in range(4000):
        out = mixing.round_leaf(pd.DataFrame({"doc_id": range(5), "size": size, "x": x, "tie": range(5)}), seed)
        total += out.set_index("doc_id").sort_index()["x"].to_numpy()
        assert abs((out["x"] * out["size"]).sum() - (x * size).sum()) < 1e-6 and ((out["x"] % 1) > 1e-9).sum() <= 1
    assert np.abs(total / 4000 - x).max() < 0.03


def test_materialise(spark, docs, many):
    df = docs(many)
    got = {(r.doc_id): r["count"] for r in mixing.materialise(df).groupBy("doc_id").count().collect()}
    want = {r.doc_id: r.copies for r in mixing.mix(df).collect() if r.copies}
    assert got == want and mixing.materialise(df).columns == df.columns


def test_hard_mix(spark, docs):
    out = mixing.mix(docs(HARD)).collect()
    assert len(out) == len(HARD) and all(r.taken <= 2 * r.size for r in out)
    assert mixing.mix(docs([])).count() == 0 and mixing.materialise(docs([])).count() == 0


# packing


def test_patterns_hold_the_histogram():
    rng = np.random.default_rng(6)
    hist = {int(k): int(v) for k, v in zip(rng.choice(np.arange(1, 1025), 300, replace=False), rng.integers(1, 400, 300))}
    used = defaultdict(int)
    for pattern, n in packing.patterns(hist):
        assert sum(pattern) <= 1024
        for length in pattern:
            used[length] += n
    assert used == hist
    packs, words = sum(n for _, n in packing.patterns(hist)), sum(k * v for k, v in hist.items())
    assert packs <= 1.1 * words / 1024 + 1
    assert packing.patterns({}) == [] and sum(n for _, n in packing.patterns({1: 3000})) == 3


def test_shortest_pack_first():
    assert sorted(packing.patterns({6: 1, 5: 1, 4: 2}, 10)) == sorted([((6, 4), 1), ((5, 4), 1)])


TEXTS = ["", None, "Hello world", "<|endoftext|> in text", "x" * 5000, "漢字 émoji 😀 \n\n  spaces   here", "don't we'll I'd 123,456", "a b c d e " * 900]


def test_ids_are_those_of_the_tokenizers_library():
    from tokenizers import Tokenizer

    path = queries.tokenizer_path()
    ours, theirs = packing.encoder(path), Tokenizer.from_file(path)
    for t in TEXTS:
        assert ours(t or "").tolist() == theirs.encode(t or "", add_special_tokens=False).ids


def test_pack(spark, docs):
    rows = [(i, TEXTS[i % len(TEXTS)] if i % 3 else f"text {i} " * (i % 50)) for i in range(120)] + [(777, "twin"), (777, "twin"), (None, "no id")]
    df = docs(rows).withColumn("length", F.lit(0)).withColumn("cell", F.lit("c"))
    path, encode = queries.tokenizer_path(), packing.encoder(queries.tokenizer_path())
    out = packing.pack_documents(df, path).collect()
    slots = defaultdict(list)
    for r in out:
        slots[r.sequence_id].append((r.offset, r.length))
    for s in slots.values():
        at = 0
        for offset, length in sorted(s):
            assert offset == at
            at += length
        assert at <= 1024
    own = defaultdict(list)
    for r in out:
        own[r.doc_id].append(r)
    texts = dict(rows)
    for doc, parts in own.items():
        if doc in (777, None):
            continue
        ids = np.append(encode(texts[doc] or ""), 0).astype("<u4")
        at = 0
        for r in sorted(parts, key=lambda r: r.start):
            assert r.start == at and r.doc_tokens == len(ids) and r.ids_crc32 == zlib.crc32(ids[at : at + r.length].tobytes())
            at += r.length
        assert at == len(ids)
    assert len(own[777]) == 2 and len(own[None]) == 1
    assert packing.pack_documents(docs([]), path).count() == 0


# the pipeline


def test_pipeline_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    counts = [docs.count()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = corpus_pipeline.cut(stage(spark, docs, sf))
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"], name
        counts.append(docs.count())
        if name == "line_dedup":
            assert docs.filter("n_chars != length(text)").count() == 0
        if name == "simhash_near_dedup":
            assert docs.count() == docs.select("doc_id").distinct().count()
    assert counts[0] >= counts[1] == counts[2] >= counts[3] > 0
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert packed.select("doc_id").distinct().count() == docs.select("doc_id").distinct().count()


def test_pipeline_keeps_good_documents(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    good = spark.read.parquet(f"{sf}/labels.parquet").filter("quality = 1")
    kept = corpus_pipeline.keep_quality(spark, docs, sf)
    n = docs.join(good, "doc_id").count()
    assert kept.join(good, "doc_id").count() >= 0.97 * n


def test_pipeline_on_hard_rows(spark, docs, sf):
    """A long good text, its exact copy and a near copy, among the hard rows."""
    rng = np.random.default_rng(8)
    good = [r.text for r in spark.read.parquet(f"{sf}/documents.parquet").join(spark.read.parquet(f"{sf}/labels.parquet").filter("quality = 1"), "doc_id").select("text").filter("length(text) > 600 and text not like '%\n%'").limit(3).collect()]
    words = good[0].split(" ")
    near = " ".join([*words[: len(words) // 2], "changed", *words[len(words) // 2 + 1 :]])
    rows = HARD + [(100, good[0]), (101, good[0]), (102, near), (103, good[1])]
    df = docs([rows[i] for i in rng.permutation(len(rows))])
    for name, stage in corpus_pipeline.STAGES[:-1]:
        df = corpus_pipeline.cut(stage(spark, df, sf))
        kept = {r.doc_id: r.text for r in df.collect()}
        if name == "quality_classifier":
            assert {100, 101, 102, 103} <= set(kept)
        if name == "line_dedup":
            assert kept[100] == good[0] and kept[101] == kept[102] == "" and kept[103] == good[1]
        if name == "simhash_near_dedup":
            assert {100, 103} <= set(kept) and len([i for i, t in kept.items() if i is not None and not t]) <= 1
    packed = corpus_pipeline.STAGES[-1][1](spark, df, sf).collect()
    assert {r.doc_id for r in packed} == {r.doc_id for r in df.collect()} and all(0 < r.length <= 1024 for r in packed)


@pytest.mark.parametrize("name", sorted(queries.queries()))
def test_queries_on_hard_tables(spark, docs, tmp_path, name):
    """Each query over tables of hard rows with more columns of its own names."""
    df = docs(HARD + [(50 + i, f"word{i} " * 30) for i in range(20)])
    for c in ("row", "id", "h", "pos", "line", "label", "node", "component", "bucket", "text_hash", "spans", "y", "x"):
        df = df.withColumn(c, F.lit("clash"))
    df.write.parquet(f"{tmp_path}/documents.parquet")
    labels = [(i, i % 2, (i // 2) % 2) for i in range(50, 70)] + [(1, 1, 0), (None, 1, 1), (4, None, None), (999, 1, 1)]
    spark.createDataFrame(labels, "doc_id long, quality int, toxic int").withColumn("text", F.lit("clash")).write.parquet(f"{tmp_path}/labels.parquet")
    vectors = [(1, [1.0, 0.0], 0), (2, [1.0, 0.01], 0), (3, None, 0), (None, [1.0, 0.0], 0), (4, [], 1), (5, [1.0], None), (2, [1.0, 0.01], 0)]
    spark.createDataFrame(vectors, "vec_id long, embedding array<float>, label int").withColumn("v", F.lit(0)).withColumn("n", F.lit(0)).write.parquet(f"{tmp_path}/embeddings.parquet")
    out = queries.queries()[name](spark, str(tmp_path)).collect()
    if name == "op7_packing":
        assert len({r.doc_id for r in out}) == len({r.doc_id for r in df.select("doc_id").collect()})
    else:
        assert len(out) == (len(vectors) if name == "op1_embedding_dedup" else df.count())
    if name in ("op4_toxicity", "op6_quality_classifier"):
        assert all(0 <= r.score <= 1 for r in out)
