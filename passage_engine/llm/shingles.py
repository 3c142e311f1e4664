"""Sets of word shingles of whole texts, by numpy over the bytes of many texts at once."""

from __future__ import annotations

import numpy as np

U = np.uint64
#: Fixed odd constants of the rolling hash.
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 1 << 64)
FINAL_A, FINAL_B = U(0xBF58476D1CE4E5B9), U(0x94D049BB133111EB)

_space = np.zeros(256, bool)
_space[[0x20, *range(0x09, 0x0E)]] = True
_rng = np.random.default_rng(20240229)
_bytes = _rng.integers(1, 1 << 63, 256, dtype=np.uint64) * U(2) + U(1)
_places = _rng.integers(1, 1 << 63, 16, dtype=np.uint64) * U(2) + U(1)
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser with full avalanche; the input is not changed."""
    x = x ^ (x >> U(30))
    x = x * FINAL_A
    x ^= x >> U(27)
    x *= FINAL_B
    x ^= x >> U(31)
    return x


def _power(kind: str, n: int) -> np.ndarray:
    have = _powers.get(kind)
    if have is None or len(have) < n:
        base = BASE if kind == "up" else INVERSE
        have = np.cumprod(np.full(max(n, 1 << 16), base, np.uint64), dtype=np.uint64)
        if len(have) <= 1 << 23:
            _powers[kind] = have
    return have[:n]


def distinct(x: np.ndarray) -> np.ndarray:
    """Sorted distinct values."""
    x = np.sort(x)
    return x[np.concatenate([[True], x[1:] != x[:-1]])] if len(x) else x


def shingle_sets(texts: list[str], k: int = 5) -> list[np.ndarray]:
    """Sorted distinct 64-bit hashes of the k-word shingles of each text.

    Words are runs of other than space and \\x09-\\x0D after lower-casing A-Z. A text of fewer than
    k words, but not none, has one shingle: the whole sequence. One without words has none.
    """
    raw = [t.encode("utf-8", "surrogatepass") for t in texts]
    data = np.frombuffer(b"\n".join([b"", *raw, b""]).lower(), np.uint8)
    space = _space[data]
    edge = np.flatnonzero(space[1:] != space[:-1]) + 1
    starts, ends = edge[0::2], edge[1::2]
    none = np.zeros(0, np.uint64)
    if not len(starts):
        return [none] * len(texts)
    sums = np.cumsum(_bytes[data] * _power("up", len(data)), dtype=np.uint64)
    words = mix((sums[ends - 1] - sums[starts - 1]) * _power("down", len(data))[starts] + (ends - starts).astype(np.uint64))
    closes = np.cumsum([len(r) + 1 for r in raw])
    first = np.concatenate([[0], np.searchsorted(starts, closes)])
    if len(words) >= k:
        rolled = words[: len(words) - k + 1] * _places[0]
        for j in range(1, k):
            rolled = rolled + words[j : len(words) - k + 1 + j] * _places[j]
        rolled = mix(rolled)
    out = []
    for a, b in zip(first[:-1], first[1:], strict=True):
        if b - a >= k:
            out.append(distinct(rolled[a : b - k + 1]))
        elif b > a:
            out.append(mix((words[a:b] * _places[: b - a]).sum(dtype=np.uint64, keepdims=True) + U((int(b - a) * BASE) % (1 << 64))))
        else:
            out.append(none)
    return out
