"""Tail bounds that the analyses rest on, as numbers that runs can be held against."""

from __future__ import annotations

import math


def limited_independence(n: int, k: int, alpha: float) -> float:
    """The chance that a sum of ``n`` k-wise independent values in 0..1 is ``alpha`` or more off its mean; k even, 6 at least."""
    if k < 6 or k % 2:
        raise ValueError("k has to be even and 6 at least")
    return min(1.0, (n * k / alpha**2) ** (k / 2))


def poissonised(p: float, n: int) -> float:
    """The chance of an event over the loads of bins that ``n`` balls fall in, from its chance under independent Poisson loads."""
    return min(1.0, p * math.e * math.sqrt(n))


def poisson_lower(mu: float, alpha: float) -> float:
    """The chance that a Poisson value is at most (1 - alpha) times its mean."""
    return math.exp(-(alpha**2) * mu / 2)


def poisson_upper(mu: float, alpha: float) -> float:
    """The chance that it is at least (1 + alpha) times its mean, alpha up to 1 (the constant is 3 here, not 2)."""
    return math.exp(-(alpha**2) * mu / 3)


def hash_degree(items: int, beta: float) -> int:
    """How independent the columns of the sign matrix have to be for ``items`` queries to be right with probability 1 - beta."""
    return max(2, math.ceil(3 * math.log(items / beta)))
