"""Rolling hashes of fixed windows over symbol arrays, vectorised."""

from __future__ import annotations

import numpy as np

_BASE = 0x9E3779B97F4A7C15
_BLOCK = 1 << 18
_tables: list[np.ndarray] = []


def mix(h: np.ndarray) -> np.ndarray:
    """Spread the bits of a uint64 array (in place where it can)."""
    h ^= h >> np.uint64(30)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def _powers() -> list[np.ndarray]:
    if not _tables:
        for base in (_BASE, pow(_BASE, -1, 1 << 64)):
            p = np.full(_BLOCK, base, np.uint64)
            p[0] = 1
            _tables.append(np.multiply.accumulate(p))
    return _tables


def windows(symbols: np.ndarray, k: int) -> np.ndarray:
    """A uint64 hash for each window of k symbols; it depends on the window's symbols alone. k is below 2**17."""
    n = len(symbols) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.empty(n, np.uint64)
    power, inverse = _powers()
    step = _BLOCK - k
    with np.errstate(over="ignore"):
        for at in range(0, n, step):
            part = symbols[at : at + step + k - 1].astype(np.uint64)
            part += np.uint64(0x632BE59BD9B4E019)
            part *= power[: len(part)]
            total = np.cumsum(part, dtype=np.uint64)
            got = total[k - 1 :].copy()
            got[1:] -= total[:-k]
            got *= inverse[: len(got)]
            out[at : at + len(got)] = mix(got)
    return out
