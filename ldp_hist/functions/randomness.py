"""Public draws that partition the users, and the private coins of their reports."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.hashing import digest, hex_slice, sign_digit


def draws(seed, user: Column, levels: int = 1, t: int = 1, m: int = 1, subsets: int = 1, columns: int = 1) -> dict[str, Column]:
    """level (from 1), pair, row, subset, col and col_sign of a user: slices of one public digest.

    Server and client recompute it from the user's public index, so nothing is stored or sent.
    """
    d = digest("pub", seed, user)
    return {
        "level": (hex_slice(d, 1, 8) % levels + 1).cast("int"),
        "pair": (hex_slice(d, 9, 8) % t).cast("int"),
        "row": hex_slice(d, 17, 8) % m,
        "subset": (hex_slice(d, 25, 8) % subsets).cast("int"),
        "col": hex_slice(d, 33, 8) % columns,
        "col_sign": sign_digit(d, 41),
    }


def assign(pop: DataFrame, seed, **sizes: int) -> DataFrame:
    """``pop`` with the draws that ``sizes`` asks for; no shuffle."""
    names = {"levels": ["level"], "t": ["pair"], "m": ["row"], "subsets": ["subset"], "columns": ["col", "col_sign"]}
    every = draws(seed, pop["user_key"], **sizes)
    return pop.withColumns({n: every[n] for k in sizes for n in names[k]})


def coin(phase: int, user: Column, key: int | str, run: Column | None = None) -> Column:
    """52 uniform bits a user and phase, as 13 hex digits: repeated or retried tasks throw the same coin.

    ``key`` has to be a secret of the user's side. A public number in its place makes the results
    reproducible and removes the privacy: for tests only. Repetitions over the same users pass their number as ``run``, beside
    the key, never in its place.
    """
    return F.substring(digest(f"coin{phase}", key, *([] if run is None else [run]), user), 1, 13)


def fell_below(thrown: Column, bound: int) -> Column:
    """Whether a coin is below ``bound``: hex digits of one length compare as their numbers do."""
    return F.lit(True) if bound >= 1 << 52 else thrown < F.lit(f"{bound:013x}")


def limit(p: float) -> int:
    """The bound below which a coin falls with probability ``p``."""
    return math.floor(p * (1 << 52))
