"""Local randomisers of one sign, and their debiasing constants."""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

from ldp_hist.functions.randomness import fell_below, limit


def keep_probability(eps: float, kind: str = "binary") -> float:
    """With which probability the true sign is sent."""
    if kind == "binary":
        return math.exp(eps) / (math.exp(eps) + 1)
    if not 0 < eps < 1:
        raise ValueError("the linear randomiser needs 0 < eps < 1")
    return 0.5 + eps / 2


def debias(eps: float, kind: str = "binary") -> float:
    """What a report is multiplied by to be right on average."""
    return (math.exp(eps) + 1) / (math.exp(eps) - 1) if kind == "binary" else 1 / eps


def privacy_loss(eps: float, kind: str = "binary") -> float:
    """The exact log-ratio of a single report; for the linear kind it is above ``eps``."""
    p = keep_probability(eps, kind)
    return math.log(p / (1 - p))


def randomised(x: Column, eps: float, coin: Column, kind: str = "binary") -> Column:
    """The sign ``x``, kept or turned by the user's coin."""
    return (x * F.when(fell_below(coin, limit(keep_probability(eps, kind))), 1).otherwise(-1)).cast("int")


def binary_rr(x: Column, eps: float, coin: Column) -> Column:
    return randomised(x, eps, coin)


def linear_rr(x: Column, eps: float, coin: Column) -> Column:
    return randomised(x, eps, coin, "linear")
