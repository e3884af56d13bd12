"""Vectorised hashes of bytes: running polynomials modulo 2**64 over random byte values."""

from __future__ import annotations

import numpy as np

_rng = np.random.default_rng(0x5EED)
#: Random value of each byte, for two independent hashes, and their odd multipliers with inverses.
VALUES = _rng.integers(0, 1 << 63, (2, 256), dtype=np.uint64) * np.uint64(2) + _rng.integers(0, 2, (2, 256), dtype=np.uint64)
_BASES = (0x9E3779B97F4A7C15, 0xD1342543DE82EF95)
_powers: dict[tuple[int, bool], np.ndarray] = {}


def powers(which: int, inverse: bool, n: int) -> np.ndarray:
    """base**k (or base**-k) for k below n; grown and kept."""
    kept = _powers.get((which, inverse))
    if kept is None or len(kept) < n:
        base = pow(_BASES[which], -1, 1 << 64) if inverse else _BASES[which]
        steps = np.full(max(n, 1 << 16), base, np.uint64)
        steps[0] = 1
        kept = _powers[which, inverse] = np.multiply.accumulate(steps)
    return kept[:n]


def running(data: np.ndarray, which: int = 0) -> np.ndarray:
    """Prefix sums whose differences are hashes of the bytes between, up to a shift by base**start."""
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(VALUES[which][data] * powers(which, False, len(data)), out=out[1:])
    return out


def between(prefix: np.ndarray, start: np.ndarray, end: np.ndarray, which: int = 0) -> np.ndarray:
    """Hashes of bytes [start, end), the same wherever they stand."""
    return (prefix[end] - prefix[start]) * powers(which, True, len(prefix))[start]


def mix(x: np.ndarray) -> np.ndarray:
    """Spreads what differs over all bits."""
    x = (x ^ x >> np.uint64(33)) * np.uint64(0xFF51AFD7ED558CCD)
    x = (x ^ x >> np.uint64(33)) * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ x >> np.uint64(33)


def word_hashes(text: bytes, is_word: np.ndarray, slice_bytes: int = 1 << 20) -> np.ndarray:
    """A hash for each maximal run of word bytes, in order; is_word says which of the 256 byte values belong to words."""
    data = np.frombuffer(text, np.uint8)
    parts, at = [], 0
    while at < len(data):
        end = min(len(data), at + slice_bytes)
        while end < len(data) and is_word[data[end]] and is_word[data[end - 1]]:  # never inside a word
            gap = np.flatnonzero(~is_word[data[end : end + slice_bytes]])
            end = end + int(gap[0]) if len(gap) else min(len(data), end + slice_bytes)
        own = data[at:end]
        inside = np.zeros(len(own) + 2, bool)
        inside[1:-1] = is_word[own]
        edge = np.flatnonzero(inside[1:] != inside[:-1])
        start, stop = edge[::2], edge[1::2]
        # the length goes in, so a word and its continuation differ whatever the byte values
        parts.append(mix(between(running(own), start, stop) + (stop - start).astype(np.uint64)))
        at = end
    return np.concatenate(parts) if parts else np.zeros(0, np.uint64)
