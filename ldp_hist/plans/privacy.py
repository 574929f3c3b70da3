"""Privacy loss by enumeration, and the budget of a protocol."""

from __future__ import annotations

import math
from itertools import product

from ldp_hist.functions.codes import Code
from ldp_hist.functions.randomizers import keep_probability
from ldp_hist.plans.params import Params


def max_log_ratio(distributions: list[dict]) -> float:
    """The greatest log-ratio of any outcome's probabilities under two items."""
    worst = 0.0
    for a, b in product(distributions, repeat=2):
        for outcome, p in a.items():
            worst = max(worst, math.inf if not b.get(outcome) else math.log(p / b[outcome]))
    return worst


def report_distributions(signs: list[tuple[int, ...]], eps: float, kind: str = "binary") -> list[dict]:
    """For each item the distribution of all its reports, given its true signs under fixed public draws."""
    keep = keep_probability(eps, kind)
    return [{out: math.prod(keep if o == s else 1 - keep for o, s in zip(out, own, strict=True)) for out in product((-1, 1), repeat=len(own))} for own in signs]


def mechanism_loss(mechanism: str, eps: float) -> float:
    """Loss of one user's participation, over all sign patterns two items can have."""
    if mechanism == "single_report":
        return max_log_ratio(report_distributions([(1,), (-1,)], eps))
    if mechanism == "half_report":
        return max_log_ratio(report_distributions([(1,), (-1,)], eps / 2))
    if mechanism == "two_reports":
        return max_log_ratio(report_distributions(list(product((1, -1), repeat=2)), eps / 2))
    if mechanism == "linear_report":
        return max_log_ratio(report_distributions([(1,), (-1,)], eps, "linear"))
    if mechanism == "doubled_report":
        return max_log_ratio(report_distributions(list(product((1, -1), repeat=2)), eps))
    raise ValueError(mechanism)


class Ledger:
    """Sequential composition: what each report of a user costs, and whether the coins are private at all."""

    def __init__(self, total: float, secret_coins: bool = True):
        self.total, self.secret, self.spent = total, secret_coins, []

    def spend(self, what: str, eps: float) -> None:
        if sum(e for _, e in self.spent) + eps > self.total + 1e-12:
            raise ValueError(f"{what} would exceed the budget of {self.total}")
        self.spent.append((what, eps))

    @classmethod
    def of(cls, p: Params) -> Ledger:
        """A user's budget in a run; asks for the coins, so that a run without a key ends here."""
        p.coins  # noqa: B018
        return cls(p.eps, secret_coins=p.coin_key is not None)

    @property
    def loss(self) -> float:
        """Infinite with public coins, which anybody can replay."""
        return sum(e for _, e in self.spent) if self.secret else math.inf


def ledger_of(method: str, eps: float, windows: int = 1) -> Ledger:
    """The reports each method asks of a user."""
    reports = {"dictionary": [1.0], "sign_matrix": [1.0], "partitioned": [1.0], "tree": [0.5, 0.5], "warm_up": [0.5, 0.5], "coded": [0.5, 0.5]}[method]
    ledger = Ledger(windows * eps)
    for w in range(windows):
        for i, share in enumerate(reports):
            ledger.spend(f"window {w} report {i + 1}", share * eps)
    return ledger


def code_fixes(code: Code) -> float:
    """The share of wrong bits that a code always corrects."""
    return code.corrects / code.length
