"""Word shingles of texts as sets of 64-bit hashes, with array operations over many texts at a time."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np

#: Words of a shingle, and bytes hashed at a time.
WORDS, CHUNK = 5, 1 << 20

_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_BASE = 0x9E3779B97F4A7C15 | 5
_STEP = np.uint64(0xD1342543DE82EF95)
_BYTES = np.random.Generator(np.random.PCG64(20)).integers(1, 1 << 63, 256, dtype=np.uint64)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


@lru_cache(maxsize=2)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    base, inverse = np.full(n, _BASE, np.uint64), np.full(n, pow(_BASE, -1, 1 << 64), np.uint64)
    base[0] = inverse[0] = 1
    return np.cumprod(base), np.cumprod(inverse)


def word_hashes(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(hash, start) of each word of lower-cased ``data``: differences of running polynomial sums, shifted back to position 0."""
    raw = np.frombuffer(data, np.uint8)
    power, inverse = _powers(CHUNK if len(raw) <= CHUNK else 1 << (len(raw) - 1).bit_length())
    space = np.concatenate([[True], _SPACE[raw], [True]])
    starts = np.flatnonzero(space[:-1] & ~space[1:])
    ends = np.flatnonzero(~space[:-1] & space[1:])
    sums = np.concatenate([[np.uint64(0)], np.cumsum(_BYTES[raw] * power[: len(raw)])])
    return mix((sums[ends] - sums[starts]) * inverse[starts] + (ends - starts).astype(np.uint64)), starts


def _pieces(data: bytes) -> Iterator[bytes]:
    """``data`` in parts of about CHUNK bytes that end before white space; a longer word stays whole."""
    at = 0
    while at < len(data):
        end = at + CHUNK
        while end < len(data) and not _SPACE[data[end]]:
            end += 1
        yield data[at:end]
        at = end


def _shingles(words: np.ndarray) -> np.ndarray:
    out = words[: len(words) - WORDS + 1].copy()
    for k in range(1, WORDS):
        out = out * _STEP + words[k : len(words) - WORDS + 1 + k]
    return mix(out)


def shingle_set(words: np.ndarray) -> np.ndarray:
    """The sorted set of a text's shingles, from its word hashes; a short text is one shingle, one without words has none."""
    if len(words) >= WORDS:
        return np.unique(_shingles(words))
    whole = np.uint64(len(words))
    with np.errstate(over="ignore"):
        for w in words:
            whole = whole * _STEP + w
    return mix(np.array([whole ^ np.uint64(0x5851F42D4C957F2D)])) if len(words) else np.zeros(0, np.uint64)


def shingle_sets(texts: list[str | None]) -> Iterator[np.ndarray]:
    """The set of each text, in order; small texts share the array operations, long ones are hashed in pieces."""
    k = 0
    while k < len(texts):
        group, starts, size = [], [], 0
        while k < len(texts) and (not group or size < CHUNK // 2):
            data = (texts[k] or "").encode("utf-8", "surrogatepass").translate(_LOWER)
            k += 1
            if len(data) > CHUNK // 2:
                if group:
                    k -= 1
                    break
                yield shingle_set(np.concatenate([word_hashes(p)[0] for p in _pieces(data)]))
                continue
            starts.append(size)
            group.append(data)
            size += len(data) + 1
        if group:
            words, at = word_hashes(b" ".join(group))
            bounds = np.append(np.searchsorted(at, starts), len(words))
            for a, b in zip(bounds, bounds[1:]):
                yield shingle_set(words[a:b])
