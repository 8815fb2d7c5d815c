"""Secret scans with structural confirmation (operator 9)."""

from __future__ import annotations

import base64
import binascii
import json
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# The patterns and least lengths of the base kinds, in the order they are listed.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
LEAST = {"assign": 8, "access": 16, "hex": 32}
#: Kinds that the method adds where the structure is confirmed.
BASE, ADDED = ("assign", "access", "hex"), ("jwt", "pem", "key")
_RANK = {kind: i for i, kind in enumerate(BASE + ADDED)}
# Words of the assignments, names of key kinds in the wire format.
_HINTS = ("passw", "secret", "token", "api")
_WIRE = (b"ssh-rsa", b"ssh-dss", b"ssh-ed25519", b"ecdsa-sha2-nistp256", b"ecdsa-sha2-nistp384", b"ecdsa-sha2-nistp521", b"openssh-key-v1")

# Encoded, a brace begins with ey or, before a tab or a line's end, with ew; the least token has 19 characters.
_JWT = re.compile(r"(?<![A-Za-z0-9_-])(e[yw][A-Za-z0-9_-]+)\.([A-Za-z0-9_-]+)\.([A-Za-z0-9_-]*)")
_PEM = re.compile(r"-----BEGIN ((?:[A-Z0-9]+ )*)PRIVATE KEY-----([A-Za-z0-9+/=\s]+)-----END \1PRIVATE KEY-----")
_B64 = re.compile(r"[A-Za-z0-9+/_-]{40,}={0,2}")
_HEXKEY = re.compile(r"(?:[0-9a-f]{2}){24,}|(?:[0-9A-F]{2}){24,}")


def _decoded(run: str) -> bytes | None:
    body = run.rstrip("=").replace("-", "+").replace("_", "/")
    if len(body) % 4 == 1:
        return None
    try:
        return base64.b64decode(body + "=" * (-len(body) % 4), validate=True)
    except (binascii.Error, ValueError):
        return None


def nested(data: bytes, depth: int = 0) -> int:
    """The number of tag-length-value elements if data is exactly a row of them,
    constructed ones holding such rows in turn; else 0."""
    at, n = 0, 0
    while at < len(data):
        if at + 2 > len(data) or depth > 8:
            return 0
        tag, size = data[at], data[at + 1]
        at += 2
        if size & 0x80:
            more = size & 0x7F
            if not 1 <= more <= 4 or at + more > len(data):
                return 0
            size = int.from_bytes(data[at : at + more], "big")
            at += more
        if at + size > len(data):
            return 0
        inner = 1
        if tag & 0x20:
            inner = 1 + nested(data[at : at + size], depth + 1)
            if size and inner == 1:
                return 0
        n += inner
        at += size
    return n


def is_key(data: bytes | None) -> bool:
    """True for a DER sequence of at least three nested elements that fills the
    data, its first an integer or a sequence, and for the length-prefixed wire
    form of a public key or the container of private ones."""
    if not data or len(data) < 24:
        return False
    if data[0] == 0x30 and nested(data) >= 4:
        head = 2 + (data[1] & 0x7F if data[1] & 0x80 else 0)
        return data[head] in (0x02, 0x30)
    if data.startswith(b"openssh-key-v1\0"):
        data = data[15:]
        fields = 3
    else:
        size = int.from_bytes(data[:4], "big")
        if size > 32 or data[4 : 4 + size] not in _WIRE:
            return False
        fields = 2
    at = 0
    for _ in range(fields):
        if at + 4 > len(data):
            return False
        at += 4 + int.from_bytes(data[at : at + 4], "big")
    return at <= len(data)


def is_signed_token(head: str, body: str) -> bool:
    """True if both parts decode to JSON objects and the first names its algorithm."""
    try:
        first, second = json.loads(_decoded(head) or b"0"), json.loads(_decoded(body) or b"0")
    except (ValueError, RecursionError):
        return False
    return isinstance(first, dict) and isinstance(first.get("alg"), str) and isinstance(second, dict)


def base_spans(text: str) -> list[tuple[int, str, int]]:
    """(start, kind, end) of the base kinds: matches leftmost and without
    overlap in each kind, too short ones dropped."""
    found = []
    low = text.lower()
    if any(h in low for h in _HINTS):
        found += [(m.start(), "assign", m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= LEAST["assign"]]
    if "AKIA" in text:
        found += [(m.start(), "access", m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= LEAST["access"]]
    if max(map(len, text.split()), default=0) >= LEAST["hex"]:
        found += [(m.start(), "hex", m.end()) for m in HEX.finditer(text) if m.end() - m.start() >= LEAST["hex"]]
    return found


def confirmed_spans(text: str) -> list[tuple[int, str, int]]:
    """(start, kind, end) of candidates whose decoded structure is that of a
    signed token, a private key block, or an encoded key."""
    found = []
    longest = max(map(len, text.split()), default=0)
    if longest >= 19 and ("ey" in text or "ew" in text):
        found += [(m.start(), "jwt", m.end()) for m in _JWT.finditer(text) if is_signed_token(m[1], m[2])]
    if "-----BEGIN " in text:
        found += [(m.start(), "pem", m.end()) for m in _PEM.finditer(text) if is_key(_decoded("".join(m[2].split())))]
    if longest >= 40:
        found += [(m.start(), "key", m.end()) for m in _B64.finditer(text) if is_key(_decoded(m[0]))]
        found += [(m.start(), "key", m.end()) for m in _HEXKEY.finditer(text) if is_key(bytes.fromhex(m[0]))]
    return found


def spans(text: str) -> list[tuple[int, str, int]]:
    """All spans (start, kind, end), by start, then kind."""
    return sorted({*base_spans(text), *confirmed_spans(text)}, key=lambda s: (s[0], _RANK[s[1]], s[2]))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, spans array of (kind, start, end)) of every row, in code points, end
    exclusive. Null and empty texts have none; rows repeated come back each."""

    def run(batches):
        import pyarrow as pa

        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            out = [[{"kind": k, "start": a, "end": b} for a, k, b in spans(t.as_py() or "")] for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, kind)], names=["id", "spans"])

    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"))
    return rows.mapInArrow(run, "id long, spans array<struct<kind: string, start: long, end: long>>")
