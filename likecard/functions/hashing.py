"""Hash families of the filters: two values a key and salt, positions by double hashing."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F
from xxhash import xxh64_intdigest


def portable(salt: str, key: Column) -> tuple[Column, Column]:
    """Two 60-bit values from the digits of an md5, the second odd; any engine
    and plain Python can repeat them."""
    digest = F.md5(F.concat(F.lit(salt), key))
    part = lambda at: F.conv(F.substring(digest, at, 15), 16, 10).cast("bigint")
    return part(1), part(16).bitwiseOR(F.lit(1).cast("bigint"))


def portable_py(salt: str, key: str) -> tuple[int, int]:
    digest = hashlib.md5((salt + key).encode()).hexdigest()
    return int(digest[:15], 16), int(digest[15:30], 16) | 1


def portable_all(salt: str, keys):
    """portable_py for an array of keys, two arrays."""
    import numpy as np

    raw = np.frombuffer(b"".join([hashlib.md5((salt + k).encode()).digest() for k in keys]), np.uint8).reshape(-1, 16)
    part = lambda at: np.ascontiguousarray(raw[:, at : at + 8]).view(">u8")[:, 0].astype(np.int64)
    return part(0) >> 4 & COVER, part(7) & COVER | 1


def portable_sql(salt: str, key: str, at: int = 1) -> str:
    return f"('0x' || substr(md5('{salt}' || {key}), {at}, 15))::bigint"


def fast(salt: str, key: Column) -> tuple[Column, Column]:
    """Two values from one of Spark's own 64-bit hashes, several times cheaper;
    the second odd, from other bits."""
    h = F.xxhash64(key, F.lit(salt))
    return h.bitwiseAND(F.lit(COVER)), F.shiftrightunsigned(h, 24).bitwiseOR(F.lit(1).cast("bigint"))


def fast_base(key: str) -> int:
    """What the fast hashes of a key under all salts begin with."""
    return xxh64_intdigest(key.encode("utf-8", "surrogatepass"), 42)


def fast_py(salt: str, key: str) -> tuple[int, int]:
    h = xxh64_intdigest(salt.encode(), fast_base(key))
    return h & COVER, h >> 24 | 1


def fast_all(salt: str, bases):
    """fast_py for an array of fast_base values, two arrays: the 64-bit hash of
    the salt, under 32 bytes, with each base as its seed."""
    import numpy as np

    one, two, three, four, five = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    turned = lambda x, n: (x << np.uint64(n)) | (x >> np.uint64(64 - n))
    data, at = salt.encode(), 0
    if len(data) >= 32:
        raise ValueError("the salt is too long")
    with np.errstate(over="ignore"):
        h = bases + five + np.uint64(len(data))
        while at + 8 <= len(data):
            h = turned(h ^ turned(np.uint64(int.from_bytes(data[at : at + 8], "little")) * two, 31) * one, 27) * one + four
            at += 8
        if at + 4 <= len(data):
            h = turned(h ^ np.uint64(int.from_bytes(data[at : at + 4], "little")) * one, 23) * two + three
            at += 4
        for byte in data[at:]:
            h = turned(h ^ np.uint64(byte) * five, 11) * one
        h = (h ^ h >> np.uint64(33)) * two
        h = (h ^ h >> np.uint64(29)) * three
        h = h ^ h >> np.uint64(32)
    return (h & np.uint64(COVER)).astype(np.int64), (h >> np.uint64(24)).astype(np.int64) | 1


COVER = (1 << 60) - 1
FAMILIES = {"portable": portable, "fast": fast}
LOCAL = {"portable": portable_py, "fast": fast_py}


def salt_of(kind: str, tier: int, layer: int, seed: str = "") -> str:
    return f"{seed}{kind}|{tier}|{layer}|"
