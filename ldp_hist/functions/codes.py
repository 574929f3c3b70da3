"""Binary codes for the bit-by-bit protocol: none, threefold repetition, and a concatenated code.

The concatenated code is a Reed-Solomon code over GF(32) of length 2K and dimension K whose symbols go through
the first-order Reed-Muller code [16, 5, 8]: 5K bits become 32K, distance 8(K+1), and generalised
minimum-distance decoding corrects any eighth of the bits, as the protocol asks.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

POLYNOMIAL = 0b100101  # x^5 + x^2 + 1 is primitive over GF(2)
_EXP = [1]
for _ in range(61):
    _EXP.append(_EXP[-1] << 1 ^ (POLYNOMIAL if _EXP[-1] & 16 else 0))
_LOG = {v: i for i, v in enumerate(_EXP[:31])}


def _mul(a: int, b: int) -> int:
    return _EXP[_LOG[a] + _LOG[b]] if a and b else 0


def _inv(a: int) -> int:
    return _EXP[31 - _LOG[a]] if a != 1 else 1


def _value(poly: list[int], x: int) -> int:
    out = 0
    for c in reversed(poly):
        out = _mul(out, x) ^ c
    return out


def _solve(rows: list[list[int]]) -> list[int] | None:
    """A solution of the augmented linear system over GF(32), free unknowns zero; None if there is none."""
    rows, n, pivots = [list(r) for r in rows], len(rows[0]) - 1, []
    at = 0
    for c in range(n):
        p = next((i for i in range(at, len(rows)) if rows[i][c]), None)
        if p is None:
            continue
        rows[at], rows[p] = rows[p], rows[at]
        inverse = _inv(rows[at][c])
        rows[at] = [_mul(x, inverse) for x in rows[at]]
        for i in range(len(rows)):
            if i != at and rows[i][c]:
                k = rows[i][c]
                rows[i] = [x ^ _mul(k, y) for x, y in zip(rows[i], rows[at], strict=True)]
        pivots.append(c)
        at += 1
    if any(r[n] for r in rows[at:]):
        return None
    out = [0] * n
    for i, c in enumerate(pivots):
        out[c] = rows[i][n]
    return out


def _divide(top: list[int], bottom: list[int]) -> list[int] | None:
    """The exact quotient of polynomials over GF(32), or None."""
    while bottom and not bottom[-1]:
        bottom = bottom[:-1]
    if not bottom:
        return None
    top, out = list(top), [0] * max(1, len(top) - len(bottom) + 1)
    lead = _inv(bottom[-1])
    for i in range(len(top) - len(bottom), -1, -1):
        q = _mul(top[i + len(bottom) - 1], lead)
        out[i] = q
        for j, b in enumerate(bottom):
            top[i + j] ^= _mul(q, b)
    return None if any(top) else out


@dataclass(frozen=True)
class Code:
    """``none`` and ``repeat3`` take any number of message bits, ``concat`` a multiple of five (80 at most)."""

    kind: str
    width: int

    def __post_init__(self):
        if self.kind == "concat" and (self.width % 5 or not 0 < self.width <= 75):
            raise ValueError("the concatenated code takes 5 to 75 bits, a multiple of five")

    @property
    def length(self) -> int:
        return {"none": self.width, "repeat3": 3 * self.width, "concat": 32 * self.width // 5}[self.kind]

    @property
    def corrects(self) -> int:
        """How many wrong bits are always put right."""
        return {"none": 0, "repeat3": 1, "concat": 4 * self.width // 5 + 3}[self.kind]

    def encode(self, message: int) -> np.ndarray:
        bits = np.array([message >> (self.width - 1 - i) & 1 for i in range(self.width)], np.uint8)
        if self.kind != "concat":
            return bits if self.kind == "none" else np.tile(bits, 3)
        k = self.width // 5
        poly = [message >> 5 * (k - 1 - i) & 31 for i in range(k)]
        return np.concatenate([_inner(_value(poly, _EXP[i])) for i in range(2 * k)])

    def masks(self) -> list[int]:
        """For each code bit the message bits whose parity it is (all three codes are linear)."""
        units = [self.encode(1 << b) for b in range(self.width)]
        return [sum(int(units[b][i]) << b for b in range(self.width)) for i in range(self.length)]

    def decode(self, word: np.ndarray) -> int | None:
        """The message of a word of 0, 1 and -1 for an erasure; an erased word has none.

        An erasure has no vote: where no vote or a tie is left, the short codes read 0. To the concatenated code an erasure does half
        the harm of a wrong bit.
        """
        word = np.asarray(word, np.int8)
        if not (word >= 0).any():
            return None
        if self.kind != "concat":
            votes = np.where(word < 0, 0, 2 * word - 1).reshape(-1, self.width).sum(axis=0)
            return int("".join("1" if v > 0 else "0" for v in votes), 2)
        return self._decode_concat(word)

    def _decode_concat(self, word: np.ndarray) -> int | None:
        k, known = self.width // 5, word >= 0
        scores = np.where(known, 1 - 2 * word, 0).reshape(2 * k, 16).astype(int) @ _INNER_SIGNS.T
        symbols, trust = scores.argmax(axis=1), np.sort(scores, axis=1)
        order = np.argsort(trust[:, -1] - trust[:, -2], kind="stable")
        best, least = None, None
        for erased in range(0, k + 1):
            found = self._decode_outer([int(s) for s in symbols], set(order[:erased].tolist()), k)
            if found is not None:
                distance = int(np.count_nonzero((self.encode(found) != word) & known))
                if least is None or distance < least:
                    best, least = found, distance
        return best

    @staticmethod
    def _decode_outer(symbols: list[int], erased: set[int], k: int) -> int | None:
        """Welch-Berlekamp on the places that aren't erased: find Q and E with Q(x) = y E(x) everywhere."""
        places = [i for i in range(2 * k) if i not in erased]
        wrong = (len(places) - k) // 2
        rows = []
        for i in places:
            x, y = _EXP[i], symbols[i]
            powers = [1]
            for _ in range(k + wrong):
                powers.append(_mul(powers[-1], x))
            rows.append([*powers[: k + wrong], *(_mul(y, p) for p in powers[:wrong]), _mul(y, powers[wrong])])
        solved = _solve(rows)
        if solved is None:
            return None
        poly = _divide(solved[: k + wrong], [*solved[k + wrong :], 1])
        if poly is None or any(poly[k:]):
            return None
        poly = (poly + [0] * k)[:k]
        return sum(c << 5 * (k - 1 - i) for i, c in enumerate(poly))


def _inner(symbol: int) -> np.ndarray:
    """First-order Reed-Muller: the constant and four linear terms at 16 points."""
    low = symbol & 15
    return np.array([(symbol >> 4 ^ (low & x).bit_count()) & 1 for x in range(16)], np.uint8)


_INNER_SIGNS = np.array([1 - 2 * _inner(s).astype(int) for s in range(32)])
