"""Hashed n-gram features of texts, on the Python workers."""

from __future__ import annotations

import re

#: Runs of letters and digits, or runs of other visible characters.
TOKEN = re.compile(r"\w+|[^\w\s]+")
_A, _B, _C = 0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9


class Codes(dict):
    """64-bit codes of strings, computed once while the table has room."""

    def __missing__(self, key):
        import xxhash

        code = xxhash.xxh64_intdigest(key.encode("utf-8", "surrogatepass"))
        if len(self) < 200_000:
            self[key] = code
        return code


def coded(tokens, codes):
    import numpy as np

    return np.fromiter(map(codes.__getitem__, tokens), np.uint64, len(tokens))


def mixed(parts, salt: int, bits: int):
    """Buckets (0 to 2**bits - 1) of the n-grams whose words are given as equally long arrays."""
    import numpy as np

    h = np.full(len(parts[0]), (salt * _C) & 0xFFFFFFFFFFFFFFFF, np.uint64)
    for p in parts:
        h = (h ^ p) * np.uint64(_A)
        h ^= h >> np.uint64(29)
        h *= np.uint64(_B)
    return (h >> np.uint64(64 - bits)).astype(np.int64)


def word_and_skip_grams(text: str, codes, bits: int):
    """Buckets of lower-cased words, word pairs and pairs with one word between, with repeats."""
    import numpy as np

    h = coded(re.findall(r"\w+", text.lower()), codes)
    return np.concatenate([mixed([h], 1, bits), mixed([h[:-1], h[1:]], 2, bits), mixed([h[:-2], h[2:]], 3, bits)])


def _form(word: str) -> str:
    if not (word[0].isalnum() or word[0] == "_"):
        return word[:3]
    return "up" if word.isupper() and len(word) > 1 else "digit" if word.isdigit() else "title" if word[0].isupper() else "low"


def token_and_form_grams(text: str, codes, bits: int):
    """Buckets of tokens and token pairs, and of runs of one to three token
    forms (case, digits, symbols, or a repeat of the word before), without
    repeats."""
    import numpy as np

    tokens = TOKEN.findall(text)
    h = coded([t.lower() for t in tokens], codes)
    f = coded([_form(t) for t in tokens], codes)
    if len(h) > 1:
        f[1:][h[1:] == h[:-1]] = np.uint64(codes["again"])
    grams = [mixed([h], 1, bits), mixed([h[:-1], h[1:]], 2, bits), mixed([f], 3, bits), mixed([f[:-1], f[1:]], 4, bits), mixed([f[:-2], f[1:-1], f[2:]], 5, bits)]
    return np.unique(np.concatenate(grams))
