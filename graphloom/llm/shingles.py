"""Word shingles of whole texts as sets of 64-bit hashes, computed for many texts at once.

Words are runs of bytes other than ASCII white space, with A-Z lower-cased. A word's hash is a
polynomial over its bytes read off prefix sums, so the cost is a few array passes over the bytes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from graphloom.llm.common import joined_bytes

U = np.uint64
_BASE = U(0x9E3779B97F4A7C15)
_INVERSE = U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))
_SLICE = 1 << 20  # bytes of text handled at once, unless one text is longer


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit bijection with good avalanche."""
    x = x ^ (x >> U(30))
    x = x * U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U(27))
    x = x * U(0x94D049BB133111EB)
    return x ^ (x >> U(31))


with np.errstate(over="ignore"):
    _BYTE = mix(np.arange(1, 257, dtype=U) * U(0xD6E8FEB86659FD93))
_RAW_BYTE = _BYTE.copy()
_BYTE[65:91] = _BYTE[97:123]
_SPACE = np.zeros(256, bool)
_SPACE[[32, 9, 10, 11, 12, 13]] = True
_powers: dict[str, np.ndarray] = {"up": np.ones(1, U), "down": np.ones(1, U)}


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers["up"]) < n:
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            p = np.full(n, base, U)
            p[0] = 1
            _powers[name] = np.multiply.accumulate(p)
    return _powers["up"][:n], _powers["down"][:n]


def word_hashes(data: np.ndarray, offsets: np.ndarray, values: np.ndarray = _BYTE) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hash of each word, the number of words before each text (n+1 numbers), and the words' starts and ends."""
    n = len(data)
    if not n:
        return np.zeros(0, U), np.zeros(len(offsets), np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64)
    solid = ~_SPACE[data]
    first = np.zeros(n + 1, bool)
    first[offsets] = True
    before = np.zeros(n, bool)
    before[1:] = solid[:-1]
    start = np.flatnonzero(solid & (~before | first[:n]))
    after = np.zeros(n, bool)
    after[:-1] = solid[1:]
    end = np.flatnonzero(solid & (~after | first[1:])) + 1
    up, down = _power(n)
    sums = np.zeros(n + 1, U)
    np.cumsum(values[data] * up, out=sums[1:])
    words = mix((sums[end] - sums[start]) * down[start] + (end - start).astype(U))
    return words, np.searchsorted(start, offsets), start, end


def shingle_sets(column: pa.Array, k: int) -> Iterator[np.ndarray]:
    """For each text: sorted distinct hashes of its k-word shingles; of all its words if it has fewer; empty without words."""
    data, offsets = joined_bytes(column)
    with np.errstate(over="ignore"):
        lo, n = 0, len(offsets) - 1
        while lo < n:
            hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + _SLICE, "right")) - 1)
            cut = offsets[lo : hi + 1]
            words, at, _, _ = word_hashes(data[cut[0] : cut[-1]], cut - cut[0])
            rolled = np.zeros(max(0, len(words) - k + 1), U)
            for i in range(k):
                rolled = rolled * U(0xC2B2AE3D27D4EB4F) + words[i : len(words) - k + 1 + i]
            rolled = mix(rolled + U(k))
            for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                if b - a >= k:
                    yield np.unique(rolled[a : b - k + 1])
                elif b > a:
                    whole = U(b - a)
                    for w in words[a:b]:
                        whole = whole * U(0xC2B2AE3D27D4EB4F) + w
                    yield mix(np.array([whole * U(2) + U(1)], U))
                else:
                    yield np.zeros(0, U)
            lo = hi


def minwise(hashes: np.ndarray, seeds: np.ndarray) -> np.ndarray:
    """For each odd seed the least hash, of which the upper 32 bits are kept."""
    best = np.full(len(seeds), np.iinfo(U).max, U)
    with np.errstate(over="ignore"):
        for lo in range(0, len(hashes), 2048):
            part = hashes[lo : lo + 2048]
            np.minimum(best, (part[None, :] * seeds[:, None]).min(axis=1), out=best)
    return (best >> U(32)).astype(np.uint32)


def seeds(count: int, salt: int = 1) -> np.ndarray:
    with np.errstate(over="ignore"):
        return mix(np.arange(1, count + 1, dtype=U) + U(salt << 20)) | U(1)
