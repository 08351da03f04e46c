"""Words of a text as 64-bit codes, shared by the operators that compare texts.

A word is a run of non-space characters, lower-cased, without its non-alphanumeric characters; words of which
nothing is left don't count. Null text is empty text."""

from __future__ import annotations

import re

import numpy as np
import xxhash

_DROP = re.compile(r"[\W_]+")
#: Cached words of a Python worker; beyond it the cache starts anew. Results don't depend on it.
CACHE = 150_000


class Codes(dict):
    """Raw word to code; 0 for a word without letters or digits."""

    def __missing__(self, word: str) -> int:
        if len(self) >= CACHE:
            self.clear()
        plain = _DROP.sub("", word)
        code = self[word] = xxhash.xxh3_64_intdigest(plain) | 1 if plain else 0
        return code


def words(text: str | None, codes: Codes) -> np.ndarray:
    """Codes of the words of a text, in order."""
    parts = (text or "").lower().split()
    found = np.fromiter(map(codes.__getitem__, parts), np.uint64, len(parts))
    return found[found != 0]


def spans(text: str, codes: Codes) -> list[tuple[int, int]]:
    """Character spans of the words that :func:`words` gives."""
    out = []
    for m in re.finditer(r"\S+", text):
        low = m.group().lower().split()
        if any(codes[x] for x in low):
            out.append(m.span())
    return out


_MUL = np.uint64(0x9E3779B97F4A7C15)
_MUL2 = np.uint64(0xC2B2AE3D27D4EB4F)


def mix(x: np.ndarray) -> np.ndarray:
    """Spread the bits of 64-bit codes."""
    x = x ^ (x >> np.uint64(32))
    x = x * _MUL
    x = x ^ (x >> np.uint64(29))
    x = x * _MUL2
    return x ^ (x >> np.uint64(32))


def grams(code: np.ndarray, k: int) -> np.ndarray:
    """64-bit hash of every run of ``k`` codes (empty if there are fewer)."""
    if len(code) < k:
        return code[:0]
    done, at, power = None, 0, code
    size = 1
    while True:  # binary composition: runs of 1, 2, 4, ... are joined to runs of k
        if k & size:
            done = power if done is None else mix(done[: len(power) - at] + _MUL) * _MUL2 + power[at : at + len(done)][: len(power) - at]
            at += size
        size *= 2
        if size > k:
            break
        half = size // 2
        power = mix(power[:-half] * _MUL + _MUL2) + power[half:]
    return mix(done)[: len(code) - k + 1]
