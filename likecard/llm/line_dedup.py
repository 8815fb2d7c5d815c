"""Fuzzy line dedup by MinHash (operator 2), in DataFrame functions only."""

from __future__ import annotations

from functools import reduce
from math import comb

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, let
from .components import components

#: Characters of a shingle, least Jaccard similarity, and banding: lines at 0.8
#: share one of 9 bands of 4 minima with probability 0.991.
CHARS, THRESHOLD, BANDS, ROWS = 5, 0.8, 9, 4
#: Bytes of minima in a number; chances that a pair at the threshold is left out by its signatures,
#: with the ends of a band and with its other lines.
BYTES, MISS, MISS_APART = 7, 0.001, 0.02
#: Lines of a band outside its largest class that meet the band in one task.
TILE = 1024


def _points(line: Column) -> Column:
    """A line at four bytes a code point, so that a window is a slice at a known place."""
    return F.encode(line, "UTF-32")


def _last(points: Column, chars: int) -> Column:
    """Place of the last window; a line shorter than a window has one, itself."""
    return F.greatest(F.lit(0), (F.length(points) / 4).cast("int") - chars)


def windows(line: Column, chars: int = CHARS) -> Column:
    """The hashes (32 bits) of all windows of `chars` characters of a line, with repeats."""
    places = lambda p: F.sequence(F.lit(1), 4 * _last(p, chars) + 1, F.lit(4))
    return let(_points(line), lambda p: F.transform(places(p), lambda at: F.hash(F.substring(p, at, F.lit(4 * chars)))))


def shingle_set(line: Column, chars: int = CHARS) -> Column:
    """The different hashes (32 bits) of all windows of `chars` characters of a line."""
    return F.array_distinct(windows(line, chars))


def lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, pos, line, h) of every line with a visible character in a row with an id."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).filter("id is not null")
    flat = rows.select("id", F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
    return flat.filter(F.col("line").rlike(r"[^\x20\x09-\x0D]")).withColumn("h", F.xxhash64("line"))


def signatures(rows: DataFrame, chars: int = CHARS, bands: int = BANDS, width: int = ROWS) -> DataFrame:
    """(h, n, id, bands, sig) of rows (h, line, id): one row per different line, with
    its number of places, its least id, a key of each band, and the low bytes of
    the minima, packed.

    Every window of a line is hashed. A minimum is the hash that follows a mark
    around the circle of all hashes: the least in the order turned to that mark. Marks lie evenly, those of a band far apart. In the sorted hashes, the
    place of a mark less the marks before it counts the hashes below it.
    """
    total = bands * width
    marks = [(i << 32) // total - (1 << 31) for i in range(total)]
    rows = rows.select("h", "id", F.sort_array(windows(F.col("line"), chars)).alias("s"))
    rows = rows.select("h", "id", "s", F.sort_array(F.concat("s", F.array(*[F.lit(m).cast("int") for m in marks]))).alias("t"))
    rows = rows.select("h", "id", "s", "t", F.reverse("t").alias("r"))  # a search from the nearer end
    place = lambda i, m: F.array_position("t", m) - (i + 1) if 2 * i < total else total - i - F.array_position("r", m)
    first = [F.get("s", F.pmod(place(i, F.lit(m).cast("int")), F.size("s")).cast("int")) for i, m in enumerate(marks)]
    # let() keeps this projection out of whole-stage code, where it would be one
    # method too long for the JVM to compile
    rows = rows.select("h", let(F.col("id"), lambda x: x).alias("id"), F.array(*first).alias("m"))
    at = lambda i: F.get("m", F.lit(i))
    keys = {f"k{b}": F.xxhash64(F.lit(b), *[at(b + bands * i) for i in range(width)]) for b in range(bands)}
    low_byte = lambda i: F.shiftleft(at(i).bitwiseAND(F.lit(255)).cast("long"), i % BYTES * 8)
    packed = {f"g{w}": reduce(Column.bitwiseOR, map(low_byte, range(w * BYTES, min(total, (w + 1) * BYTES)))) for w in range(-(-total // BYTES))}
    rows = rows.select("h", "id", *[x.alias(k) for k, x in (keys | packed).items()])
    rows = rows.groupBy("h").agg(F.count("*").alias("n"), F.min("id").alias("id"), *[F.min(k).alias(k) for k in keys | packed])
    return rows.select("h", "n", "id", F.array(*keys).alias("bands"), F.array(*packed).alias("sig"))


def least_agreement(minima: int, threshold: float, miss: float = MISS) -> int:
    """The most equal minima that a pair at the threshold falls short of with a
    chance of `miss` at most."""
    below, k = 0.0, 0
    while (below := below + comb(minima, k) * threshold**k * (1 - threshold) ** (minima - k)) <= miss:
        k += 1
    return k


def agree(a: Column, b: Column, minima: int) -> Column:
    """Number of equal bytes in two packed signatures of that many minima: bytes
    of an exclusive-or that are zero, told for all bytes of a number at once."""
    ones, tops = (int("01" * BYTES, 16) * x for x in (0x7F, 0x80))
    words, out = -(-minima // BYTES), F.lit(0)
    for i in range(1, words + 1):
        x = F.element_at(a, i).bitwiseXOR(F.element_at(b, i))
        some = (x.bitwiseAND(F.lit(ones)) + F.lit(ones)).bitwiseOR(x)
        out = out + F.bit_count(F.bitwise_not(some).bitwiseAND(F.lit(tops)))
    return out - (words * BYTES - minima)


def alike(sa: Column, sb: Column, threshold: float) -> Column:
    """Whether two shingle sets have at least that Jaccard similarity; sizes that
    rule it out are told first. The common part, asked for once, must be at least
    t / (1 + t) of both sizes (less a hair, for a fraction that is exactly met)."""
    low, high = F.least(F.size(sa), F.size(sb)), F.greatest(F.size(sa), F.size(sb))
    enough = F.size(F.array_intersect(sa, sb)) >= (low + high) * F.lit(threshold / (1 + threshold)) - F.lit(1e-6)
    return (low >= threshold * high) & enough


def similar(pairs: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """The pairs (a, b) whose lines have at least that Jaccard similarity. sets: (h, set)."""
    a, b = (sets.select(F.col("h").alias(x), F.col("set").alias(f"s{x}")) for x in "ab")
    return pairs.join(a, "a").join(b, "b").filter(alike(F.col("sa"), F.col("sb"), threshold)).select("a", "b")


def picked(pairs: DataFrame, sig: DataFrame, minima: int, least: int) -> DataFrame:
    """The pairs (a, b) whose signatures agree in at least that many minima."""
    a, b = (sig.select(F.col("h").alias(x), F.col("sig").alias(f"s{x}")) for x in "ab")
    return pairs.join(a, "a").join(b, "b").filter(agree(F.col("sa"), F.col("sb"), minima) >= least).select("a", "b")


def sets_of(docs: DataFrame, id_col: str, text_col: str, wanted: DataFrame, chars: int) -> DataFrame:
    """(h, set) of the lines wanted (h, id), each read from the least id that has
    it, so a hot line is one row, and other documents are not split."""
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    some = rows.join(wanted.select("id").distinct(), "id", "left_semi")
    rows = lines(some, "id", "text").join(wanted, ["h", "id"], "left_semi").select("h", "line").dropDuplicates(["h"])
    return cut(rows.select("h", shingle_set(F.col("line"), chars).alias("set")))


def apart(members: DataFrame, links: DataFrame, sig: DataFrame, minima: int, least: int) -> tuple[DataFrame, DataFrame]:
    """(a, b): lines of bands (members: band, h; those that met all of their band
    are left out) with several classes by the links found so far. a holds those outside the class with the most lines of the
    band, b all of them; they meet on band and tile, a in one tile of the band, b
    in each. Kept are lines that agree with one of another class."""
    of = components(links, "a", "b").select(F.col("node").alias("h"), "component")
    named = cut(members.join(of, "h", "left").select("band", "h", F.coalesce("component", "h").alias("c")))
    sizes = named.groupBy("band", "c").count().groupBy("band").agg(F.max_by("c", "count").alias("main"), (F.sum("count") - F.max("count")).alias("rest"))
    sizes = cut(sizes.filter("rest > 0").select("band", "main", F.ceil(F.col("rest") / TILE).cast("int").alias("tiles")))
    named = cut(named.join(sizes, "band"))
    own = named.groupBy("h").agg(F.collect_set("band").alias("bands"))
    named = named.join(own, "h").join(sig.select("h", "sig"), "h").withColumn("home", F.pmod(F.xxhash64("h"), F.col("tiles")).cast("int"))
    side = lambda rows, tile, x: rows.select(F.col("band").alias(f"band_{x}"), tile.alias(f"tile_{x}"), F.col("h").alias(x), F.col("c").alias(f"c{x}"), F.col("sig").alias(f"g{x}"), F.col("bands").alias(f"i{x}"))
    a = cut(side(named.filter("c != main"), F.col("home"), "a"))
    b = cut(side(named.withColumn("tile", F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))), F.col("tile"), "b"))
    met = meeting(minima, least)
    a = cut(a.join(b, met, "left_semi"))
    return a, cut(b.join(a, met, "left_semi"))


def meeting(minima: int, least: int) -> Column:
    """Whether two rows of `apart` are of one band and tile, of different classes,
    agree, and share no band before this one."""
    near = (F.col("band_a") == F.col("band_b")) & (F.col("tile_a") == F.col("tile_b")) & (F.col("ca") != F.col("cb")) & (agree(F.col("ga"), F.col("gb"), minima) >= least)
    return near & (F.array_min(F.array_intersect("ia", "ib")) == F.col("band_a"))


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chars: int = CHARS, threshold: float = THRESHOLD, bands: int = BANDS, width: int = ROWS) -> DataFrame:
    """(h, class): the class of each different line that is linked to another.

    Lines that share a band are candidates. In a band all meet its most frequent
    line and its least one; then the others meet where their classes differ (see
    `apart`), verified inside the join, so that only links are rows. No link within a band
    is lost, but for pairs whose signatures agree in too few minima to be at the
    threshold: a chance of MISS there, of MISS_APART between classes. All others
    are verified on all windows of both lines. Bands with the same lines count once.
    """
    sig = cut(signatures(lines(docs, id_col, text_col), chars, bands, width))
    minima, least, later = bands * width, *(least_agreement(bands * width, threshold, x) for x in (MISS, MISS_APART))
    flat = sig.select("h", F.explode("bands").alias("band"))
    ends = flat.groupBy("band").agg(F.min("h").alias("low"), F.max("h").alias("high"), F.count("*").alias("k"), F.bit_xor("h").alias("mix")).filter("low < high")
    ends = cut(ends.groupBy("low", "high", "k", "mix").agg(F.min("band").alias("band")))
    members = cut(flat.join(ends.filter("k > 2").select("band", "low"), "band"))
    twos = ends.filter("k = 2").select(F.col("low").alias("a"), F.col("high").alias("b"))
    shared = members.select("h").union(twos.select(F.explode(F.array("a", "b")).alias("h"))).distinct()
    sig = cut(sig.select("h", "n", "id", "sig").join(shared, "h", "left_semi"))
    often = F.col("n") * 2 + (F.col("h") != F.col("low")).cast("int")  # of equally frequent lines not the least
    most = members.join(sig.select("h", "n"), "h").groupBy("band").agg(F.max_by("h", often).alias("top"))
    members = cut(members.join(most, "band"))
    stars = members.select("h", F.explode(F.array("low", "top")).alias("o")).filter("h != o")
    pairs = stars.select(F.least("h", "o").alias("a"), F.greatest("h", "o").alias("b")).unionByName(twos)
    pairs = cut(picked(pairs.distinct(), sig, minima, least))
    wanted = cut(sig.select("h", "id").join(pairs.select(F.explode(F.array("a", "b")).alias("h")).distinct(), "h", "left_semi"))
    sets = sets_of(docs, id_col, text_col, wanted, chars)
    links = cut(similar(pairs, sets, threshold))
    others = members.filter("h != low and h != top").select("band", "h")
    a, b = apart(others, links, sig, minima, later)
    if not a.isEmpty():
        more = a.select(F.col("a").alias("h")).union(b.select(F.col("b").alias("h"))).distinct().join(wanted, "h", "left_anti")
        more = cut(sig.select("h", "id").join(more, "h", "left_semi"))
        sets = sets.unionByName(sets_of(docs, id_col, text_col, more, chars))
        a, b = a.join(sets.toDF("a", "sa"), "a"), b.join(sets.toDF("b", "sb"), "b")
        links = links.unionByName(a.join(b, meeting(minima, later) & alike(F.col("sa"), F.col("sb"), threshold)).select("a", "b"))
    return components(cut(links), "a", "b").select(F.col("node").alias("h"), F.col("component").alias("class"))


def removed_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", chars: int = CHARS, threshold: float = THRESHOLD, bands: int = BANDS, width: int = ROWS) -> tuple[DataFrame, DataFrame]:
    """((id, pos) of the lines to remove, (id, pos) of all lines). Of each class
    its first occurrence by id, then place, stays; equal lines are one class."""
    every = cut(lines(docs, id_col, text_col).select("id", "pos", "h"))
    named = cut(classes(docs, id_col, text_col, chars, threshold, bands, width))
    rows = cut(every.join(named, "h", "left").select("id", "pos", F.coalesce("class", "h").alias("class")))
    place = F.struct("id", "pos")
    first = rows.groupBy("class").agg(F.min(place).alias("first"), F.count("*").alias("n")).filter("n > 1")
    first = cut(first.select("class", F.col("first.id").alias("first_id"), F.col("first.pos").alias("first_pos")))
    gone = rows.join(first, "class").filter("id != first_id or pos != first_pos").select("id", "pos")
    return gone, every


def report(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """One row per id of docs: doc_id, n_lines (with a visible character),
    n_removed, and removed, the sorted numbers (from 0) of the lines that go."""
    gone, every = removed_lines(docs, id_col, text_col, **options)
    gone = gone.groupBy("id").agg(F.sort_array(F.collect_list("pos")).alias("removed"))
    count = every.groupBy("id").agg(F.count("*").alias("n"))
    own = docs.select(F.col(id_col).cast("long").alias("id"))
    out = own.join(count, "id", "left").join(gone, "id", "left").withColumn("removed", F.coalesce("removed", F.array().cast("array<int>")))
    return out.select(F.col("id").alias("doc_id"), F.coalesce("n", F.lit(0)).alias("n_lines"), F.size("removed").cast("long").alias("n_removed"), "removed")


def dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """docs, all rows and columns, with repeated and near-repeated lines taken
    out of the texts: one line of each class stays, the first by id and place.

    Blank lines stay; null texts stay null; a text whose lines all go becomes
    empty. Rows with a null id are left as they are; ids are expected to be
    unique, and rows that share one lose the same line numbers.
    """
    gone, _ = removed_lines(docs, id_col, text_col, **options)
    gone = gone.groupBy("id").agg(F.collect_set("pos").alias("_gone")).withColumnRenamed("id", "_id")
    kept = F.array_join(F.filter(F.split(F.col(text_col), "\n", -1), lambda x, i: ~F.array_contains("_gone", i)), "\n")
    out = docs.join(gone, F.col(id_col).cast("long") == F.col("_id"), "left")
    return out.withColumn(text_col, F.when(F.col("_gone").isNull(), F.col(text_col)).otherwise(kept)).select(docs.columns)
