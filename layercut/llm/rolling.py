"""Polynomial hashes of spans of bytes, from differences of one running sum."""

from __future__ import annotations

import numpy as np

_rng = np.random.default_rng(23)
_BYTE = _rng.integers(1, 2**63, size=256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE = 0x9E3779B97F4A7C15


def _powers(count: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of an odd number and of its inverse, modulo 2^64."""
    up, down = np.ones(count, dtype=np.uint64), np.ones(count, dtype=np.uint64)
    up[1:], down[1:] = np.uint64(_BASE), np.uint64(pow(_BASE, -1, 1 << 64))
    return np.multiply.accumulate(up), np.multiply.accumulate(down)


#: Bytes whose powers are kept; longer buffers make their own.
KEPT = 1 << 20
_UP, _DOWN = _powers(KEPT)


def stir(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def span_hashes(buf: np.ndarray, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
    """A 64-bit hash of buf[start:stop] for each span, the same wherever the span stands."""
    up, down = (_UP, _DOWN) if len(buf) < KEPT else _powers(len(buf) + 1)
    total = np.zeros(len(buf) + 1, dtype=np.uint64)
    np.cumsum(_BYTE[buf] * up[: len(buf)], out=total[1:])
    return stir((total[stop] - total[start]) * down[start] + (stop - start).astype(np.uint64))
