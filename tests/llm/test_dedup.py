import random
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from .conftest import HARD
from likecard.llm import components, embedding_dedup, line_dedup, simhash, substring_dedup


def classes(ids, linked):
    root = {i: i for i in ids}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in linked:
        a, b = sorted((find(a), find(b)))
        root[b] = a
    return {i: find(i) for i in ids}


def sentence(rng, n):
    return " ".join("".join(rng.choice("abcdefghij") for _ in range(rng.randint(2, 7))) for _ in range(n))


# components


def test_components(spark):
    rng = random.Random(1)
    edges = [(i, i + 1) for i in range(0, 60)] + [(100 + rng.randint(0, 80), 100 + rng.randint(0, 80)) for _ in range(50)] + [(5, 5), (300, -7), (1 << 62, -(1 << 62))]
    df = spark.createDataFrame([*edges, (None, 3)], "src long, dst long")
    got = {r.node: r.component for r in components.components(df).collect()}
    want = classes({x for e in edges for x in e}, edges)
    alone = {x for x in want if not any(x in e and e[0] != e[1] for e in edges)}
    assert got == {k: v for k, v in want.items() if k not in alone}


def test_components_of_nothing(spark):
    assert components.components(spark.createDataFrame([], "src long, dst long")).count() == 0


def test_forest_keeps_connection():
    rng = np.random.default_rng(1)
    a, b = rng.integers(0, 50, 400), rng.integers(0, 50, 400)
    x, y = components.forest(a, b)
    assert len(x) < 50 and classes(set(a) | set(b), zip(a, b)) == classes(set(a) | set(b), zip(x, y))


# embeddings


def brute_vectors(rows, threshold):
    ok = {}
    for i, v, lab in rows:
        if v is not None and lab is not None and all(x is not None and np.isfinite(x) for x in v) and any(v):
            ok[i] = (np.array(v, float), lab)
    links = [(i, j) for i in ok for j in ok if i < j and ok[i][1] == ok[j][1] and len(ok[i][0]) == len(ok[j][0]) and ok[i][0] @ ok[j][0] / np.linalg.norm(ok[i][0]) / np.linalg.norm(ok[j][0]) >= threshold]
    return links


@pytest.mark.parametrize("tile", [3, 7, 512])
def test_embeddings(spark, tile):
    rng = np.random.default_rng(3)
    base = rng.normal(size=(12, 20))
    rows = [(i, (base[i % 12] + rng.normal(size=20) * (0.02 if i % 3 else 0.35)).tolist(), i % 2) for i in range(150)]
    rows += [(200, rows[0][1], 0), (201, rows[0][1], 0), (202, None, 1), (203, [0.0] * 20, 0), (204, [float("nan")] * 20, 0), (205, [None] * 20, 0), (206, rows[1][1], None), (207, [1.0, 2.0], 0), (208, [2.0, 4.0], 0), (209, [float("inf")] + [1.0] * 19, 0)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int").withColumn("component", F.lit("x"))
    got = {r.vec_id: r for r in embedding_dedup.near_duplicates(df, tile=tile).collect()}
    links = brute_vectors(rows, 0.93)
    degree = defaultdict(int)
    for a, b in links:
        degree[a] += 1
        degree[b] += 1
    want = classes([r[0] for r in rows], links)
    assert len(links) > 100 and len(got) == len(rows)
    assert all(r.n_links == degree[i] and r.component_id == want[i] and r.kept == (want[i] == i) for i, r in got.items())


def test_far_tiles_never_meet(spark):
    """Vectors around distant directions: most pairs of tiles are left out, no link is."""
    rng = np.random.default_rng(4)
    axis = np.eye(16)[rng.integers(0, 4, 400)] * rng.choice([-1.0, 1.0], 400)[:, None]
    rows = [(i, v, 0) for i, v in enumerate((axis + rng.normal(size=(400, 16)) * 0.06).tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    unique = df.selectExpr("label", "embedding as v", "vec_id as node", "1L as copies")
    axes = embedding_dedup.principal_axes(unique)
    tiles, pairs = embedding_dedup.tiled(embedding_dedup.located(unique, axes, 0.93), 0.93, 10)
    of = {r.node: r.own for r in tiles.collect()}
    met = {(r.low, r.high) for r in pairs.collect()}
    links = brute_vectors(rows, 0.93)
    assert len(links) > 500 and all((min(of[a], of[b]), max(of[a], of[b])) in met for a, b in links)
    n = len(set(of.values()))
    assert len(met) < 0.5 * n * (n + 1) / 2


def test_no_embeddings(spark):
    assert embedding_dedup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>, label int")).count() == 0


# SimHash


def brute_print(text, k=4):
    w = re.findall(rb"[^\x20\x09-\x0D]+", (text or "").encode().lower())
    if not w:
        return 0
    hs = [xxhash.xxh64_intdigest(b" ".join(w[i : i + k]), 42) for i in range(max(1, len(w) - k + 1))]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hs) > len(hs))


def test_fingerprints(spark, docs):
    rng = random.Random(4)
    rows = [*HARD, *[(100 + i, sentence(rng, rng.randint(1, 40)).title()) for i in range(40)]]
    got = sorted((r.id, r.fp & (2**64 - 1)) for r in simhash.fingerprints(docs(rows)).filter("id is not null").collect())
    assert got == sorted((i, brute_print(t)) for i, t in rows if i is not None)


def test_fingerprint_hash_is_sparks_own(spark):
    assert spark.sql("select xxhash64('a b c d') h").first().h & (2**64 - 1) == xxhash.xxh64_intdigest("a b c d", 42)


@pytest.mark.parametrize("tile", [16, 4096])
def test_links_connect_what_brute_force_connects(spark, tile):
    rng = np.random.default_rng(5)
    seeds = rng.integers(0, 2**63, 40, dtype=np.uint64)
    fps = set(int(x) for x in seeds)
    for s in seeds[:20]:
        for _ in range(15):
            fps.add(int(s) ^ sum(1 << int(b) for b in rng.choice(64, rng.integers(1, 8), replace=False)))
    fps = sorted(fps)
    signed = [x - 2**64 if x >= 2**63 else x for x in fps]
    df = spark.createDataFrame([(i, x, 0, 0) for i, x in enumerate(signed)], "node long, fp long, s0 long, s1 long")
    got = [(r.src, r.dst) for r in simhash.links(df, tile=tile).collect()]
    want = [(i, j) for i in range(len(fps)) for j in range(i) if (fps[i] ^ fps[j]).bit_count() <= 4]
    assert len(want) > 100 and classes(range(len(fps)), got) == classes(range(len(fps)), want)
    assert all((fps[a] ^ fps[b]).bit_count() <= 4 or classes(range(len(fps)), want)[a] == classes(range(len(fps)), want)[b] for a, b in got)


def test_groups_and_keep_one(spark, docs):
    df = docs(HARD).withColumn("fp", F.lit(1)).withColumn("node", F.lit("clash"))
    got = {r.id: r.component for r in simhash.groups(df).filter("id is not null").collect()}
    assert got[1] == got[2] == got[3] == 1 and got[5] == got[8] == 5 and got[4] == 4
    kept = simhash.keep_one(df)
    assert kept.columns == df.columns
    assert sorted((r.doc_id is None, r.doc_id) for r in kept.collect() if r.doc_id is not None) == [(False, i) for i in (1, 4, 5, 6, 7, 9)]
    assert kept.filter("doc_id is null").count() == 1
    assert simhash.groups(docs([])).count() == 0


def test_similarity_of_linked_documents(spark, docs):
    """Copies with a word in 200 changed are grouped, unrelated texts are not."""
    rng = random.Random(7)
    rows, copies = [], []
    for i in range(40):
        w = sentence(rng, 200).split()
        rows.append((i, " ".join(w)))
        w[rng.randrange(200)] = "changed"
        copies.append((100 + i, " ".join(w)))
    got = {r.id: r.component for r in simhash.groups(docs(rows + copies), shingle=5, max_bits=8, similarity=0.8).collect()}
    assert all(got[i] == i for i in range(40)) and sum(got[100 + i] == i for i in range(40)) >= 34
    a, b = (np.frombuffer(simhash._sketch(np.array(x, np.uint64) * np.uint64(0x9E3779B97F4A7C15)), np.uint8) for x in (range(1, 901), range(101, 1001)))
    assert 9 <= (a == b).sum() <= 16


def test_similarity_is_that_of_the_shingle_sets(spark, docs):
    """Copies from 0.6 to 0.98: those at 0.8 or more are grouped, the others are not."""
    rng = random.Random(11)
    rows, want = [], {}
    for i in range(120):
        w = sentence(rng, 200).split()
        grams = lambda w: {tuple(w[k : k + 5]) for k in range(len(w) - 4)}
        rows.append((i, " ".join(w)))
        x, near = list(w), grams(w)
        for k in rng.sample(range(0, 200, 6), 1 + i % 10):
            x[k] = "changed"
        rows.append((1000 + i, " ".join(x)))
        want[1000 + i] = len(near & grams(x)) >= 0.8 * len(near | grams(x))
    got = {r.id: r.component for r in simhash.groups(docs(rows), shingle=5, max_bits=8, similarity=0.8).collect()}
    assert 30 < sum(want.values()) < 90
    assert {i: got[i] == i - 1000 for i in want} == want and all(got[i] == i for i in range(120))


def test_alike_connects_what_brute_force_connects():
    rng = np.random.default_rng(12)
    sets = [np.unique(rng.integers(0, 11, 12).astype(np.uint64)) for _ in range(60)]
    near = [(i, j) for i in range(60) for j in range(i) if 5 * len(np.intersect1d(sets[i], sets[j])) >= 4 * len(np.union1d(sets[i], sets[j]))]
    got = simhash._alike(sets, 0.8)
    assert len(near) > 10 and set((j, i) for i, j in got) <= set(near) and classes(range(60), got) == classes(range(60), near)


@pytest.mark.parametrize("tile", [8, 1024])
def test_verified_tiles(spark, tile):
    rng = np.random.default_rng(13)
    sets = [np.unique(rng.integers(0, 12, 12).astype(np.uint64)) for _ in range(60)]
    rows = spark.createDataFrame([(1, i, i, 0) for i in range(60)], "bucket long, node long, d0 long, d1 long")
    data = spark.createDataFrame([(i, 0, bytearray(x.tobytes())) for i, x in enumerate(sets)], "d0 long, d1 long, shingles binary")
    near = [(i, j) for i in range(60) for j in range(i) if 5 * len(np.intersect1d(sets[i], sets[j])) >= 4 * len(np.union1d(sets[i], sets[j]))]
    got = [(r.src, r.dst) for r in simhash.verified(rows, data, 0.8, tile).collect()]
    assert classes(range(60), got) == classes(range(60), near)


# lines


def test_equal_lines_keep_their_first_place(spark, docs):
    df = docs([(2, "same line here\nown line two"), (1, "x y z\nsame line here\n\n"), (3, "same line here"), (4, None), (5, ""), (None, "same line here")]).withColumn("h", F.lit(0)).withColumn("pos", F.lit(0))
    out = {r.doc_id: r.text for r in line_dedup.dedup(df).collect()}
    assert out == {2: "own line two", 1: "x y z\nsame line here\n\n", 3: "", 4: None, 5: "", None: "same line here"}
    rep = {r.doc_id: (r.n_lines, r.n_removed, r.removed) for r in line_dedup.report(df).filter("doc_id is not null").collect()}
    assert rep == {1: (2, 0, []), 2: (2, 1, [0]), 3: (1, 1, [0]), 4: (0, 0, []), 5: (0, 0, [])}


def brute_shingles(line, k=5):
    return frozenset(line[i : i + k] for i in range(max(1, len(line) - k + 1)))


@pytest.mark.parametrize("k", [5, 12])
def test_shingles(spark, k):
    cases = ["one two three four five", "x", "averyverylongwordwithoutspaces again", "漢" * 40, "a\tb  c", "aaaaaaaaaaaaaaaaaa", "😀é" * 9]
    df = spark.createDataFrame([(c,) for c in cases], "line string").select("line", line_dedup.shingle_set(F.col("line"), k).alias("s"))
    got = {r.line: r.s for r in df.collect()}
    assert all(len(got[c]) == len(set(got[c])) == len(brute_shingles(c, k)) for c in cases)
    first, second = (set(got[c]) for c in ("one two three four five", "averyverylongwordwithoutspaces again"))
    assert len(first & second) == len(brute_shingles(cases[0], k) & brute_shingles(cases[2], k))


def test_agreement_of_signatures(spark):
    rng = random.Random(3)
    for bands, width in ((9, 4), (1, 1), (2, 7)):
        text = [sentence(rng, 12) for _ in range(20)]
        rows = spark.createDataFrame([(i, t, 0) for i, t in enumerate(text + [t[:-3] + "xyz" for t in text])], "h long, line string, id long")
        n = bands * width
        sig = line_dedup.signatures(rows, bands=bands, width=width).select("h", "sig")
        a, b = sig.toDF("a", "x"), sig.toDF("b", "y")
        bits = [(8 * (i % 7), i // 7) for i in range(n)]
        for r in a.join(b, F.col("b") == F.col("a") + 20).select("x", "y", line_dedup.agree(F.col("x"), F.col("y"), n).alias("k")).collect():
            assert r.k == sum((r.x[w] >> at & 255) == (r.y[w] >> at & 255) for at, w in bits)
    assert line_dedup.least_agreement(1, 0.8) == 0 and line_dedup.least_agreement(36, 0.8) == 21


def test_minima_of_signatures(spark):
    """Minima against a search of all hashes of a line, without a row per window;
    a long line, repeated windows and lines shorter than a window among them."""
    rng = random.Random(16)
    text = [sentence(rng, n) for n in (1, 2, 5, 12, 40, 900)] + ["x", "ab", "a" * 50, "漢字" * 9 + "😀", "\x00 odd"]
    rows = spark.createDataFrame([(i, t, i) for i, t in enumerate(text)] + [(3, text[3], 1)], "h long, line string, id long")
    sig = line_dedup.signatures(rows)
    assert "Generate" not in sig._jdf.queryExecution().executedPlan().toString()
    sets = {r.h: r.s for r in rows.select("h", line_dedup.shingle_set(F.col("line")).alias("s")).collect()}
    got = {r.h: r for r in sig.collect()}
    assert len(got) == len(text) and (got[3].n, got[3].id) == (2, 1) and (got[4].n, got[4].id) == (1, 4)
    for h, r in got.items():
        for i in range(36):
            mark = (i << 32) // 36 - (1 << 31)
            least = min(sets[h], key=lambda x: (x - mark) % 2**32)
            assert r.sig[i // 7] >> 8 * (i % 7) & 255 == least & 255


def test_likeness_at_its_threshold(spark):
    """Sets that share exactly four fifths are alike, and one element less is not;
    the common part is computed once."""
    rows = [(n, list(range(9 * n)), list(range(n, 10 * n))) for n in range(1, 60)]
    df = spark.createDataFrame(rows, "n int, a array<int>, b array<int>")
    out = df.select("n", line_dedup.alike(F.col("a"), F.col("b"), 0.8).alias("at"), line_dedup.alike(F.slice("a", F.lit(1), F.size("a") - 1), F.col("b"), 0.8).alias("below"), line_dedup.alike(F.slice("a", 1, 1), F.col("b"), 0.8).alias("small"))
    assert {(r.n, r.at, r.below, r.small) for r in out.collect()} == {(n, True, False, False) for n in range(1, 60)}
    assert str(line_dedup.alike(F.col("a"), F.col("b"), 0.8)._jc).count("array_intersect") == 1


@pytest.mark.parametrize("k", [5, 12])
def test_lines_of_the_documents(spark, k):
    """All different lines of the given documents against brute force over all
    their windows: pairs that share a tenth of their windows' least hashes."""
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    text = sorted({x for r in df.collect() for x in (r.text or "").split("\n") if x.strip(" \t\n\x0b\f\r")})
    sets = [brute_shingles(t, k) for t in text]
    by = defaultdict(list)
    for i, s in enumerate(sets):
        # sets at 0.8 share one of the least floor(n / 5) + 1 of each in any one order
        for x in sorted(s, key=lambda w: xxhash.xxh64_intdigest(w.encode()))[: len(s) // 5 + 1]:
            by[x].append(i)
    pairs = {(a, b) for m in by.values() for a in m for b in m if a < b and len(sets[a]) <= 1.25 * len(sets[b]) and len(sets[b]) <= 1.25 * len(sets[a])}
    near = [(a, b) for a, b in pairs if 5 * len(sets[a] & sets[b]) >= 4 * len(sets[a] | sets[b])]
    of = {r["h"] % 2**64: r["class"] for r in line_dedup.classes(df, chars=k).collect()}
    at = [of.get(xxhash.xxh64_intdigest(t.encode(), 42)) for t in text]
    joined = sum(at[a] is not None and at[a] == at[b] for a, b in near)
    whole = classes(range(len(text)), near)
    assert len(near) > 100 and joined >= 0.98 * len(near)
    group = defaultdict(set)
    for i, c in enumerate(at):
        if c is not None:
            group[c].add(whole[i])
    assert all(len(x) == 1 for x in group.values())


def test_near_lines(spark, docs):
    rng = random.Random(6)
    base = [sentence(rng, 30) for _ in range(40)]
    rows = [(i, base[i]) for i in range(40)]
    for i in range(30):
        w = base[i].split()
        w[rng.randrange(30)] = "changed"
        rows.append((100 + i, " ".join(w)))
    rows += [(500, "漢字" * 20 + "終"), (501, "漢字" * 20 + "了")]
    sets = {i: brute_shingles(t) for i, t in rows}
    links = [(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    want = classes(sets, links)
    gone = {r.doc_id for r in line_dedup.report(docs(rows)).filter("n_removed = 1").collect()}
    assert len(links) >= 20 and gone == {i for i in want if want[i] != i}


def test_large_band_of_alike_lines(spark, docs):
    """Variants of one line that are each close to it and not to one another."""
    rng = random.Random(8)
    base = sentence(rng, 40).split()
    rows = [(0, " ".join(base)), (1, " ".join(base))]
    for i in range(80):
        w = list(base)
        for j in rng.sample(range(40), 2):
            w[j] = f"v{i}x{j}"
        rows.append((10 + i, " ".join(w)))
    gone = {r.doc_id for r in line_dedup.report(docs(rows)).filter("n_removed = 1").collect()}
    sets = {i: brute_shingles(t) for i, t in rows}
    want = classes(sets, [(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])])
    assert gone == {i for i in want if want[i] != i}


def test_near_short_lines(spark, docs):
    """Lines of 6 to 36 words with a letter or the words at their end changed, and
    a word that grows from 24 to 25 characters, against all windows of five."""
    rng = random.Random(14)
    rows = []
    for i in range(200):
        w = sentence(rng, 6 + i % 24).split()
        rows.append((i, " ".join(w)))
        if i % 24 > 20 and i % 2:
            rows.append((1000 + i, " ".join(w + ["ab"] * rng.randint(1, 7))))
        else:
            t = rows[-1][1]
            k = rng.randrange(len(t))
            rows.append((1000 + i, t[:k] + "z" + t[k + 1 :]))
    rows += [(3000, "漢字かな交じりの文はここで終わりです。次の文"), (3001, "漢字かな交じりの文はここで終わりです。次の本"), (3002, "abc"), (3003, "abd")]
    tail = sentence(rng, 30)
    rows += [(4000, "x" * 24 + " " + tail), (4001, "x" * 25 + " " + tail)]
    sets = {i: brute_shingles(t) for i, t in rows}
    want = classes(sets, [(a, b) for a in sets for b in sets if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])])
    gone, over = ({r.doc_id for r in line_dedup.report(docs(rows)).filter("n_removed = 1").collect()}, {i for i in want if want[i] != i})
    assert len(over) > 150 and gone <= over and len(over - gone) <= 3 and 3001 in gone and 4001 in gone


def test_links_between_the_classes_of_a_band(spark, docs):
    """Chains of four versions of a line, in one band: where the ends of a chain
    are the band's least and most frequent line, its middle link must be met."""
    rng = random.Random(15)
    rows = []
    for i in range(150):
        w = sentence(rng, 40).split()
        for k in range(4):
            rows.append((10 * i + k, " ".join(w)))
            w[3 + 9 * k] = f"v{k}xyz"
    df = docs(rows)
    of = {t: i for i, t in rows}
    line = {xxhash.xxh64_intdigest(t, 42): t for t in of}
    sets = {i: brute_shingles(t) for i, t in rows}
    bands = defaultdict(list)
    for r in line_dedup.signatures(line_dedup.lines(df), bands=1, width=1).collect():
        if r.h % 2**64 in line:
            bands[r.bands[0]].append(of[line[r.h % 2**64]])
    links = [(a, b) for m in bands.values() for a in m for b in m if a < b and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b])]
    want = classes(sets, links)
    gone = {r.doc_id for r in line_dedup.report(df, bands=1, width=1).filter("n_removed = 1").collect()}
    assert gone == {i for i in want if want[i] != i}
    assert sum(len([i for i in m if i // 10 == c]) == 4 for m in bands.values() for c in {i // 10 for i in m}) > 20


@pytest.mark.parametrize("op", [line_dedup.report, line_dedup.dedup])
def test_hard_lines(spark, docs, op):
    assert op(docs(HARD)).count() == len(HARD) and op(docs([])).count() == 0


# substrings


def test_boundaries_shift_with_the_text():
    rng = random.Random(9)
    data = sentence(rng, 400).encode()
    a, b = set(substring_dedup.boundaries(data)), {x - 7 for x in substring_dedup.boundaries(b"shifted" + data)}
    assert {x for x in a if x > 16} == {x for x in b if x > 16} and len(a) > 30
    assert substring_dedup.boundaries(b"a").tolist() == [1]


def test_passages(spark, docs):
    rng = random.Random(10)
    passage = sentence(rng, 60)
    rows = [(i, sentence(rng, 80) + " " + passage + " " + sentence(rng, 50)) for i in range(12)]
    rows += [(50 + i, sentence(rng, 150)) for i in range(12)] + [(80 + i, sentence(rng, 50) + " short shared words of ten here and no more " + sentence(rng, 60)) for i in range(4)]
    rows += [(200, rows[0][1])]
    got = {r.id: r for r in substring_dedup.repeats(docs(rows + [(None, passage), (300, None), (301, "")])).filter("id is not null").collect()}
    assert {i for i, r in got.items() if r.passages} == {*range(12), 200}
    assert all(35 <= r.passages[0].words <= 60 for i, r in got.items() if 0 < i < 12)
    for i in range(1, 12):
        text = dict(rows)[i].encode()
        p = got[i].passages[0]
        whole = text.index(passage.encode())
        assert whole - 40 < p.start and p.end < whole + len(passage) + 40 and p.first_docs[0] == 0 and p.removed > 30
    assert sum(p.removed for p in got[0].passages) == 0 and got[200].passages[0].removed == len(rows[0][1].split())
    assert got[300].n_chunks == got[301].n_chunks == 0


def test_passages_within_a_document_and_removal(spark, docs):
    """Texts without repeats keep every passage once: brute force over windows of
    sixty words, which no chunk edge can hide."""
    rng = random.Random(12)
    passage, own = sentence(rng, 90), sentence(rng, 80)
    rows = [(i, f"{sentence(rng, 70)} {passage} {sentence(rng, 40)}") for i in range(5)] + [(20, f"{own} {sentence(rng, 60)} é漢 {own}"), (21, sentence(rng, 200)), (30, None), (31, "")]
    df = docs(rows).withColumn("spans", F.lit(1)).withColumn("row", F.lit("x"))
    got = {r.id: r for r in substring_dedup.repeats(df).collect()}
    assert not got[20].passages and len(got[20].within) == 2 and got[20].within[1].removed > 50 and not got[21].within
    out = {r.doc_id: r.text for r in substring_dedup.dedup(df).collect()}
    assert set(out) == set(dict(rows)) and out[30] is None and out[31] == "" and out[0] == rows[0][1] and out[21] == dict(rows)[21]
    seen = Counter()
    for t in out.values():
        w = (t or "").split()
        seen.update(" ".join(w[i : i + 60]) for i in range(max(0, len(w) - 59)))
    assert max(seen.values()) == 1 and "é漢" in out[20]
    kept = " ".join(t or "" for t in out.values())
    assert passage in kept and own in kept


def test_cuts_keep_characters_whole():
    data = "a漢b".encode()
    assert substring_dedup.without(data, [{"start": 0, "end": 2}]) == "漢b".encode()
    assert substring_dedup.without(data, [{"start": 2, "end": 5}]) == "a漢".encode()
    assert substring_dedup.without(data, [{"start": 1, "end": 4}]) == b"ab"


def test_hard_substrings(spark, docs):
    assert substring_dedup.dedup(docs(HARD)).count() == len(HARD) and substring_dedup.dedup(docs([])).count() == 0
    assert substring_dedup.repeats(docs(HARD)).count() == len(HARD) and substring_dedup.repeats(docs([])).count() == 0
