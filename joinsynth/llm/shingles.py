"""Word shingles as 64-bit numbers, computed for a whole Arrow batch at once with numpy.

Words are runs of bytes other than blank and 0x09-0x0D, after lower-casing A-Z.  A text's
shingles are its distinct runs of ``k`` words; a text of fewer words (but some) is one shingle.
"""

from __future__ import annotations

import numpy as np

_U = np.uint64
_BASE = 0x9E3779B97F4A7C15 | 1
_STEP = _U(0xD6E8FEB86659FD93)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64-bit numbers."""
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self) -> None:
        self.up = self.down = np.ones(1, _U)

    def to(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            n = 1 << (n - 1).bit_length()
            both = []
            for base in (_BASE, pow(_BASE, -1, 1 << 64)):
                steps = np.full(n, base, _U)
                steps[0] = 1
                both.append(np.cumprod(steps, dtype=_U))
            self.up, self.down = both
        return self.up[:n], self.down[:n]


POWERS = _Powers()
_BYTE = mix(np.arange(1, 257, dtype=_U) * _STEP)
_BREAK = np.zeros(256, bool)
_BREAK[[0x20, *range(0x09, 0x0E)]] = True


def _word_hashes(raw: bytes) -> np.ndarray:
    """A number for each word of lower-cased UTF-8 text."""
    data = np.frombuffer(raw, np.uint8)
    gap = _BREAK[data]
    edge = np.flatnonzero(np.diff(np.concatenate([[True], gap, [True]]).astype(np.int8)))
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return np.empty(0, _U)
    up, down = POWERS.to(len(data) + 1)
    prefix = np.concatenate([np.zeros(1, _U), np.cumsum(_BYTE[data] * up[: len(data)])])
    return mix((prefix[end] - prefix[start]) * down[start] + (end - start).astype(_U) * _STEP)


def shingle_set(text: str | None, k: int = 5) -> np.ndarray:
    """Sorted distinct shingle numbers of one text."""
    if not text:
        return np.empty(0, _U)
    words = _word_hashes(text.encode().lower())
    if not len(words):
        return words
    size = min(k, len(words))
    n = len(words) - size + 1
    total = np.full(n, size, _U) * _STEP
    for j in range(size):
        total = mix(total + words[j : j + n])
    return np.unique(total)


def set_prints(sets: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit fingerprints of each set (as signed numbers), independent of order."""
    first = np.array([mix(s + _U(1)).sum(dtype=_U) for s in sets], _U)
    second = np.array([mix(s ^ _STEP).sum(dtype=_U) for s in sets], _U)
    return mix(first).view(np.int64), mix(second).view(np.int64)


class MinHasher:
    """``n`` minimum hashes of each set of a batch; 31-bit values."""

    def __init__(self, n: int, seed: int = 20) -> None:
        rng = np.random.default_rng(seed)
        self.a = rng.integers(0, 2**63, n, dtype=np.uint64) * _U(2) + _U(1)
        self.b = rng.integers(0, 2**63, n, dtype=np.uint64)

    def signatures(self, sets: list[np.ndarray]) -> np.ndarray:
        """An (len(sets), n) array; rows of empty sets are -1."""
        out = np.full((len(sets), len(self.a)), -1, np.int32)
        full = [i for i, s in enumerate(sets) if len(s)]
        if full:
            every = np.concatenate([sets[i] for i in full])
            at = np.cumsum([0, *(len(sets[i]) for i in full[:-1])])
            for j, (a, b) in enumerate(zip(self.a, self.b, strict=True)):
                out[full, j] = (np.minimum.reduceat(every * a + b, at) >> _U(33)).astype(np.int32)
        return out
