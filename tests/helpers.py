from collections import Counter


def brute_keys(records, kind, max_len):
    """Counts of records by literal, suffix literals reversed."""
    out = Counter()
    for s in records:
        if s is None:
            continue
        t = s[::-1] if kind == "S" else s
        starts = range(len(t)) if kind == "C" else [0]
        out.update({t[i : i + j] for i in starts for j in range(1, max_len + 1) if i + j <= len(t)})
    return out


def strings(spark, records):
    return spark.createDataFrame(list(enumerate(records)), "sid long, s string")


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())
