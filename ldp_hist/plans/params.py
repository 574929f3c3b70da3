"""Parameters of the protocols: experiment profiles, the analysis' formulas, and their preconditions."""

from __future__ import annotations

import logging
import math
from dataclasses import dataclass, replace


def pow2(x: float) -> int:
    """The least power of two that is at least ``x``: transforms need one."""
    return 1 << max(0, math.ceil(math.log2(max(1.0, x))))


#: The coin key of test runs; both engines know it.
PUBLIC_COINS = 42


@dataclass(frozen=True)
class Params:
    """eps: the whole budget of a user; t hash pairs of m cells; R subsets of T cells; the public seed.

    ``coin_key`` is the secret that the users' coins are drawn with. There is no default: without it no report is made, unless
    ``public_coins`` says that the run is a test whose coins anybody can throw again, which has no privacy.
    ``strict`` turns preconditions of the analysis that don't hold into errors.
    """

    eps: float = 2.0
    t: int = 15
    m: int = 64
    R: int = 15
    T: int = 64
    seed: int = 42
    coin_key: int | str | None = None
    public_coins: bool = False
    strict: bool = False

    def __post_init__(self):
        if self.eps <= 0:
            raise ValueError("eps has to be positive")
        if self.m & (self.m - 1) or self.T & (self.T - 1):
            raise ValueError("m and T have to be powers of two; see pow2")
        if self.coin_key is not None and (self.public_coins or str(self.coin_key) == str(self.seed)):
            raise ValueError("the coin key has to be a secret, not the public seed or public coins")

    @property
    def coins(self) -> int | str:
        """What coins are drawn with."""
        if self.coin_key is None and not self.public_coins:
            raise ValueError("a secret coin_key is needed (public_coins=True is for tests only)")
        return PUBLIC_COINS if self.coin_key is None else self.coin_key

    def but(self, **changes) -> Params:
        return replace(self, **changes)


# Settings of the query catalogue, whose coins are public so that DuckDB can throw them too.
TINY = Params(public_coins=True)
WORDS_SF001 = TINY.but(eps=4.0, t=31, m=1024)
WORDS_SF01 = TINY.but(t=99, m=2048)
LN3 = TINY.but(eps=math.log(3))


def experiment(n: int, eps: float = 2.0, **coins) -> Params:
    """The experiment's setting: 285 pairs of about sqrt(n) cells."""
    return Params(eps=eps, t=285, m=pow2(math.sqrt(n)), **coins)


def theory_tree(n: int, log_d: int, eps: float, beta: float = 0.05) -> dict[str, float]:
    """The analysis' choice for the tree: pairs, cells, and the half-threshold eta."""
    log = math.log(n / beta)
    return {"t": round(110 * log), "m": pow2(48 * math.sqrt(n / log)), "eta": 147 * math.sqrt(n * log * log_d) / eps,
            "list_error": 147 * math.sqrt(n * log) / eps}


def partitioned_small(n: int, queries: int, beta: float, eps: float) -> dict[str, float]:
    """Parameters A: few queries."""
    R = math.ceil(132 * math.log(4 * queries / beta))
    log = math.log(queries / beta)
    return {"R": R, "T": pow2(eps**2 * log + eps * math.sqrt(n / log)), "min_n": 8 * R * math.log(8 * queries / beta),
            "error": 27 / eps * math.sqrt(n * R * math.log(2 * R * queries / beta))}


def partitioned_full(n: int, queries: int, beta: float, eps: float) -> dict[str, float]:
    """Parameters B: the final estimates."""
    R = math.ceil(300 * math.log(12 * n * queries / beta))
    return {"R": R, "T": pow2(eps * math.sqrt(n / math.log(n * queries / beta))), "min_n": 43 * R,
            "error": 400 / eps * math.sqrt(n * math.log(12 * n * queries / beta))}


def sign_matrix_error(n: int, queries: int, beta: float, eps: float) -> float:
    return 3 / eps * math.sqrt(n * math.log(4 * queries / beta))


def warm_up(n: int, log_d: int, eps: float) -> dict[str, float]:
    """The simple bit-by-bit protocol: least frequency w found, cells T, error of estimates (beta 0.05)."""
    w = 32 * log_d * math.log(16 * log_d) + 48 / eps * math.sqrt(2 * n * log_d * math.log(64 * log_d))
    T = max(1.0, 32 * n / w)
    return {"w": w, "T": T, "error": 6 / eps * math.sqrt(n * math.log(4 * T / 0.05)), "min_n": 12 * log_d * math.log(12 * log_d)}


def cells_for(n: int, regime: str) -> int:
    """Cells against collisions: n squared, n, or sqrt(n) with repetition."""
    return pow2({"n2": n * n, "n": n, "sqrt": math.sqrt(n)}[regime])


def check(method: str, n: int, p: Params, log_d: int = 1, beta: float = 0.05) -> list[str]:
    """The analysis' preconditions that do not hold (experiments break some on purpose)."""
    log, broken = math.log(max(n, 2) / beta), []

    def need(ok: bool, what: str) -> None:
        if not ok:
            broken.append(what)

    if method == "sketch":
        need(p.t >= 110 * log, "t >= 110 ln(n/beta)")
        need(p.m >= 48 * math.sqrt(n / log), "m >= 48 sqrt(n/ln(n/beta))")
        need(n >= 48 * p.t * log_d, "n >= 48 t log d")
    elif method == "tree":
        need(n > log * log_d, "n > ln(n/beta) log d")
    elif method == "sign_matrix":
        need(p.eps <= 1, "eps <= 1")
    elif method == "warm_up":
        need(p.eps <= 1, "eps <= 1")
        need(n >= 12 * log_d * math.log(12 * log_d), "n >= 12 log d ln(12 log d)")
    elif method == "partitioned":
        need(n >= 43 * p.R, "n >= 43 R")
        need(p.R >= 132 * math.log(4 / beta), "R >= 132 ln(4/beta)")
    elif method == "coded":
        need(p.R >= 48 * math.log(1 / beta), "R >= 48 ln(1/beta)")
        need(n >= 10 * p.R * log_d, "n >= 10 R log d'")
        need(p.T <= p.eps * n / (326 * math.sqrt(p.R * log_d)), "T <= eps n/(326 sqrt(R log d'))")
        need(log_d >= 850 * log, "log d' >= 850 ln(n/beta)")
    else:
        raise ValueError(method)
    return broken


def note(method: str, n: int, p: Params, log_d: int = 1, beta: float = 0.05) -> list[str]:
    """``check``, called by the protocols: broken preconditions are logged, or raised if the run is ``strict``."""
    broken = check(method, n, p, log_d, beta)
    if broken and p.strict:
        raise ValueError(f"{method}: {'; '.join(broken)} does not hold")
    if broken:
        logging.getLogger("ldp_hist").info("%s, n=%d: not guaranteed by the analysis: %s", method, n, "; ".join(broken))
    return broken


def suggest_pairs(n: int, levels: int = 1) -> int:
    """An odd number of pairs small enough that the median is not a choice among a few multiples of the scale."""
    t = int(math.sqrt(n / levels) / 8)
    return max(3, min(285, t | 1))
