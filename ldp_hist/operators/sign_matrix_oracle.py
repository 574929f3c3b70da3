"""Oracles over a public sign matrix: the plain one, and the partitioned one that needs few sums.

Every user sends the randomised entry of a public sign matrix at (own item, own column). In the plain
oracle every query sums over all users. The partitioned oracle deals users into R subsets, hashes items
to T cells in each, and answers with the median; its columns are drawn from a linear family, so a subset's
reports add up to one counter for each column name, and a transform turns these into all T answers.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.hadamard import fwht_groups, had_sign
from ldp_hist.functions.hashing import PRIME, digest, hex_slice, sign_digit, sign_of
from ldp_hist.functions.randomizers import debias, randomised
from ldp_hist.functions.randomness import coin, draws
from ldp_hist.plans.params import Params
from ldp_hist.plans.privacy import Ledger

DEGREE = 4
#: The longest dictionary of the plain oracle.
SHORT = 10_000


def matrix_sign(family: str, seed: int, x: Column, user: Column) -> Column:
    """Z[x, user] of a family: ``sha`` (as if uniform), ``affine`` (pairwise), ``poly`` (k-wise), ``linear``.

    The latter three have short descriptions: two, ``DEGREE`` or no coefficients an item.
    """
    if family == "sha":
        return sign_digit(digest("z", seed, x, user), 1)
    if family == "linear":
        d = digest("lin", seed, user)
        return had_sign(hex_slice(digest("key", seed, x), 1, 8) + 1, hex_slice(d, 1, 8)) * sign_digit(d, 9)
    u, d = hex_slice(digest("usr", seed, user), 1, 8) % PRIME, digest(family, seed, x)
    value = F.lit(0).cast("long")
    for i in range(2 if family == "affine" else DEGREE):
        value = (value * u + hex_slice(d, 1 + 8 * i, 8) % PRIME) % PRIME
    return sign_of(value % 2)


def plain_reports(pop: DataFrame, p: Params, family: str = "sha", kind: str = "binary") -> DataFrame:
    """(user_key, y): the user's column is public, so the server knows whose report it is."""
    Ledger.of(p).spend("item", p.eps)
    z = matrix_sign(family, p.seed, F.col("item"), F.col("user_key"))
    return pop.select("user_key", randomised(z, p.eps, coin(1, F.col("user_key"), p.coins), kind).alias("y"))


def plain_estimates(pop: DataFrame, items: DataFrame, p: Params, family: str = "sha", kind: str = "binary") -> DataFrame:
    """(item, est): each user meets each candidate once; for short dictionaries (one pass, map-side sums).

    Users times candidates is what this oracle costs by its nature. A dictionary of over ``SHORT`` items is refused; the
    partitioned oracle answers those. The candidates, a row of them, are what is sent to the users' tasks.
    """
    asked = items.select("item").distinct().limit(SHORT + 1).agg(F.collect_list("item").alias("asked"))
    few = F.when(F.size("asked") <= SHORT, F.col("asked")).otherwise(F.raise_error(F.lit(f"the plain oracle takes {SHORT} items at most")))
    reports = plain_reports(pop, p, family, kind).join(F.broadcast(asked.select(few.alias("asked")))).select("user_key", "y", F.explode("asked").alias("item"))
    value = F.col("y") * matrix_sign(family, p.seed, F.col("item"), F.col("user_key"))
    return reports.groupBy("item").agg(F.round(F.lit(debias(p.eps, kind)) * F.sum(value), 4).alias("est"))


# --- the partitioned oracle ---------------------------------------------------------------------------------


def cell_of(seed: int, subset: Column, x: Column, T: int) -> Column:
    return hex_slice(digest("cell", seed, subset, x), 1, 8) % T


def linear_sign(index: Column, col: Column, col_sign: Column) -> Column:
    """Entry of the linear family; the index is shifted so that no row is constant."""
    return had_sign(index + 1, col) * col_sign


def partitioned_reports(pop: DataFrame, p: Params, eps: float | None = None, phase: int = 1, keep: tuple[str, ...] = (), ledger: Ledger | None = None) -> DataFrame:
    """(subset, col, y): a report times the user's column sign, which the server can take off right away."""
    (ledger or Ledger.of(p)).spend("item", eps or p.eps)
    d = draws(p.seed, F.col("user_key"), subsets=p.R, columns=2 * p.T)
    own = pop.withColumns({"subset": d["subset"], "col": d["col"], "col_sign": d["col_sign"]})
    z = linear_sign(cell_of(p.seed, F.col("subset"), F.col("item"), p.T), F.col("col"), F.col("col_sign"))
    y = randomised(z, eps or p.eps, coin(phase, F.col("user_key"), p.coins))
    return own.select(*keep, "subset", "col", (y * F.col("col_sign")).alias("y"))


def partitioned_counters(reports: DataFrame) -> DataFrame:
    """(subset, col, s): at most R times 2T sums."""
    return reports.groupBy("subset", "col").agg(F.sum(F.col("y").cast("long")).alias("s"))


def partitioned_sums(table: DataFrame, items: DataFrame, p: Params, mode: str = "transform") -> DataFrame:
    """(item, subset, v) for every item and subset, by transform, by columns, or report by report."""
    each = items.select("item", F.explode(F.sequence(F.lit(0), F.lit(p.R - 1))).alias("subset"))
    each = each.withColumn("cell", cell_of(p.seed, F.col("subset"), F.col("item"), p.T) + 1)
    if mode == "transform":
        cells = fwht_groups(table, ["subset"], "col", 2 * p.T)
        return each.join(cells, ["subset", "cell"], "left").select("item", "subset", F.coalesce("v", F.lit(0)).alias("v"))
    value = F.col("y" if mode == "direct" else "s").cast("long")
    sums = table.join(each, "subset").groupBy("item", "subset").agg(F.sum(value * had_sign(F.col("cell"), F.col("col"))).alias("v"))
    return each.select("item", "subset").join(sums, ["item", "subset"], "left").select("item", "subset", F.coalesce("v", F.lit(0)).alias("v"))


def partitioned_estimates(pop: DataFrame, items: DataFrame, p: Params, mode: str = "transform", eps: float | None = None, phase: int = 1, ledger: Ledger | None = None) -> DataFrame:
    """(item, est): R times the median over the subsets."""
    eps = eps or p.eps
    reports = partitioned_reports(pop, p, eps, phase, ledger=ledger)
    table = reports if mode == "direct" else partitioned_counters(reports)
    sums = partitioned_sums(table, items.select("item"), p, mode)
    return sums.groupBy("item").agg(F.round(F.lit(p.R * debias(eps)) * F.median("v"), 4).alias("est"))


def full_histogram(pop: DataFrame, dictionary: DataFrame, p: Params) -> DataFrame:
    """All frequencies of a dictionary smaller than the square root of the users: just ask for each."""
    return partitioned_estimates(pop, dictionary, p)
