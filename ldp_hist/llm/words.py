"""Vectorised words and shingles of whole texts (NumPy), for the operators on word shingles."""

from __future__ import annotations

import numpy as np

_U = np.uint64
#: An odd base has an inverse modulo 2**64, so a word's hash is a difference of prefix sums, shifted back.
_BASE, _INVERSE = 0x9E3779B97F4A7C15 | 1, pow(0x9E3779B97F4A7C15 | 1, -1, 1 << 64)
_powers = {"up": np.ones(1, _U), "down": np.ones(1, _U)}

SPACE_SEPARATED = np.ones(256, bool)
SPACE_SEPARATED[[0x20, *range(0x09, 0x0E)]] = False
#: Letters, digits and all bytes of other alphabets; punctuation separates.
ALPHANUMERIC = np.array([b >= 0x80 or chr(b).isalnum() for b in range(256)])


def _power(name: str, base: int, n: int) -> np.ndarray:
    if len(_powers[name]) < n:
        full = np.full(max(n, 2 * len(_powers[name])), base, _U)
        full[0] = 1
        _powers[name] = np.cumprod(full, dtype=_U)
    return _powers[name][:n]


def mix(h: np.ndarray) -> np.ndarray:
    """A finalising bit mixer on 64-bit integers (two multiply-xorshift rounds)."""
    h = (h ^ (h >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> _U(27))) * _U(0x94D049BB133111EB)
    return h ^ (h >> _U(31))


def word_hashes(data: bytes, word_bytes: np.ndarray = SPACE_SEPARATED) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end offsets and a 64-bit hash of every maximal run of ``word_bytes``."""
    raw = np.frombuffer(data, np.uint8)
    inside = np.zeros(len(raw) + 2, np.int8)
    inside[1:-1] = word_bytes[raw]
    step = np.diff(inside)
    start, end = np.flatnonzero(step == 1), np.flatnonzero(step == -1)
    prefix = np.zeros(len(raw) + 1, _U)
    np.cumsum((raw.astype(_U) + _U(1)) * _power("up", _BASE, len(raw)), out=prefix[1:])
    hashes = (prefix[end] - prefix[start]) * _power("down", _INVERSE, len(raw) + 1)[start]
    return start, end, mix(hashes + (end - start).astype(_U) * _U(0xD6E8FEB86659FD93))


def shingle_hashes(words: np.ndarray, k: int) -> np.ndarray:
    """A hash for every k consecutive words; fewer words make one shingle of them all, none make none."""
    k = min(k, len(words))
    if not k:
        return np.zeros(0, _U)
    n = len(words) - k + 1
    out = np.full(n, k, _U)
    for i in range(k):
        out = mix(out * _U(0xC2B2AE3D27D4EB4F) + words[i : i + n])
    return out


def majority_bits(hashes: np.ndarray, weights: np.ndarray | None = None) -> int:
    """The SimHash of 64-bit hashes: bit b is set if over half of them (by weight) have it; 0 for none."""
    if not len(hashes):
        return 0
    ones, total = np.zeros(64, np.int64), len(hashes) if weights is None else int(weights.sum())
    for at in range(0, len(hashes), 1 << 16):
        bits = np.unpackbits(np.ascontiguousarray(hashes[at : at + (1 << 16)], "<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        ones += bits.sum(axis=0, dtype=np.int64) if weights is None else weights[at : at + (1 << 16)] @ bits
    return int.from_bytes(np.packbits(2 * ones > total, bitorder="little").tobytes(), "little")
