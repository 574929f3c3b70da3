"""What the protocols are compared with: exact counts, a trusted curator, Bloom-filter reports, earlier methods."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.hashing import digest, hex_slice
from ldp_hist.operators.sign_matrix_oracle import plain_estimates
from ldp_hist.plans.params import Params
from ldp_hist.plans.privacy import Ledger


def exact_frequencies(pop: DataFrame) -> DataFrame:
    """(item, f). Map-side sums leave one row an item and task, so a hot item is no hot task."""
    return pop.groupBy("item").agg(F.count("*").alias("f"))


def exact_heavy_hitters(pop: DataFrame, factor: float = 15.0) -> DataFrame:
    """(item, f, n) with f at least ``factor`` times the square root of n."""
    n = pop.agg(F.count("*").alias("n"))
    return exact_frequencies(pop).join(F.broadcast(n)).where(F.col("f") >= factor * F.sqrt("n"))


def curator_laplace(pop: DataFrame, eps: float, seed: int = 42) -> DataFrame:
    """(item, f, est): a trusted party adds Laplace noise to each count; one user changes two counts by one."""
    u = (hex_slice(digest("lap", seed, F.col("item")), 1, 13) + 0.5) / float(1 << 52) - 0.5
    noise = -(2 / eps) * F.signum(u) * F.log(1 - 2 * F.abs(u))
    return exact_frequencies(pop).select("item", "f", F.round(F.col("f") + noise, 4).alias("est"))


# --- randomised Bloom-filter reports (stand-in for a deployed system, from published descriptions) -----------

COHORTS, BITS, HASHES = 64, 32, 2


def bloom_place(seed, cohort: Column, i: int, item: Column) -> Column:
    return hex_slice(digest("bloom", seed, cohort, F.lit(i), item), 1, 8) % BITS


def bloom_flip(eps: float) -> float:
    """Each of the bits that two items may differ in gets an equal share of the budget."""
    return 1 / (math.exp(eps / (2 * HASHES)) + 1)


def bloom_reports(pop: DataFrame, p: Params) -> DataFrame:
    """(cohort, bit, s, n): ones and users by cohort and bit. A user's bits are flipped by four hex digits of a digest each.

    Digits are compared as text, which orders them as their numbers.
    """
    Ledger.of(p).spend("filter", p.eps)
    cohort = (hex_slice(digest("coh", p.seed, F.col("user_key")), 1, 8) % COHORTS).cast("int")
    flips = [digest("flip", p.coins, F.lit(block), F.col("user_key")).alias(f"d{block}") for block in range(-(-BITS // 16))]
    own = pop.select("item", cohort.alias("cohort"), *flips)
    own = own.withColumns({f"p{i}": bloom_place(p.seed, F.col("cohort"), i, F.col("item")) for i in range(HASHES)})
    below = f"{math.floor(bloom_flip(p.eps) * (1 << 16)):04x}"

    def one(b: int) -> Column:
        is_set = F.col("p0") == b
        for i in range(1, HASHES):
            is_set = is_set | (F.col(f"p{i}") == b)
        return F.sum((is_set != (F.substring(f"d{b // 16}", 1 + 4 * (b % 16), 4) < below)).cast("long")).alias(f"b{b}")

    sums = own.groupBy("cohort").agg(*[one(b) for b in range(BITS)], F.count("*").alias("n"))
    pairs = F.explode(F.array(*[F.struct(F.lit(b).alias("bit"), F.col(f"b{b}").alias("s")) for b in range(BITS)]))
    return sums.select("cohort", "n", pairs.alias("x")).select("cohort", F.col("x.bit").alias("bit"), F.col("x.s").alias("s"), "n")


def bloom_constants(eps: float) -> dict[str, float]:
    """q: a bit's flip; q0: the share of other items that set a given bit; spread: a cohort user's variance in an estimate from one bit."""
    q, q0 = bloom_flip(eps), 1 - (1 - 1 / BITS) ** HASHES
    return {"q": q, "q0": q0, "spread": (q * (1 - q) / (1 - 2 * q) ** 2 + q0 * (1 - q0)) / (1 - q0) ** 2}


def bloom_decode(reports: DataFrame, items: DataFrame, p: Params, z: float = 3.0) -> DataFrame:
    """(item, est) for every item of a known dictionary of any length.

    A cohort's debiased counts of an item's bits, less what other items put there on average, estimate its users in the
    cohort; cohorts add up. Estimates under ``z`` standard errors become zero, which is why rare items vanish.
    """
    k = bloom_constants(p.eps)
    debiased = (F.col("s") - k["q"] * F.col("n")) / (1 - 2 * k["q"])
    bits = reports.select("cohort", "bit", "n", ((debiased - k["q0"] * F.col("n")) / (1 - k["q0"])).alias("users"))
    asked = items.select("item").distinct().select("item", F.explode(F.sequence(F.lit(0), F.lit(COHORTS - 1))).alias("cohort"))
    asked = asked.select("item", "cohort", F.explode(F.array_distinct(F.array(*[bloom_place(p.seed, F.col("cohort"), i, F.col("item")).cast("int") for i in range(HASHES)]))).alias("bit"))
    cohort = asked.join(bits, ["cohort", "bit"]).groupBy("item", "cohort").agg(F.avg("users").alias("users"), (F.first("n") * k["spread"] / F.count("*")).alias("variance"))
    sums = cohort.groupBy("item").agg(F.sum("users").alias("est"), F.sum("variance").alias("variance"))
    return sums.select("item", F.when(F.col("est") >= z * F.sqrt("variance"), F.round("est", 4)).otherwise(0.0).alias("est"))


def bloom_refine(reports: DataFrame, found: DataFrame, p: Params, limit: int = 2_000) -> DataFrame:
    """(item, est) of the items that ``bloom_decode`` left above zero, fitted together by non-negative least squares.

    Users of all other items are a background that sets every bit of a cohort alike; it is fitted with them. Survivors are
    few by the test (n users can't put more than about sqrt(n) items above it); over ``limit`` of them are refused before the work.
    """
    spark, k = reports.sparkSession, bloom_constants(p.eps)
    names = sorted(r["item"] for r in found.where("est > 0").select("item").limit(limit + 1).collect())
    if len(names) > limit:
        raise ValueError(f"over {limit} items to fit")
    if not names:
        return found.where("est > 0").select("item", "est")
    place = {x: i for i, x in enumerate(names)}
    asked = spark.createDataFrame([(n,) for n in names], "item string").select("item", F.explode(F.sequence(F.lit(0), F.lit(COHORTS - 1))).alias("cohort"))
    asked = asked.select("item", "cohort", F.array(*[bloom_place(p.seed, F.col("cohort"), i, F.col("item")) for i in range(HASHES)]).alias("set"))
    design, target = np.zeros((COHORTS * BITS, len(names) + 1)), np.zeros(COHORTS * BITS)
    design[:, -1] = k["q0"] / COHORTS
    for r in asked.collect():  # limit * COHORTS rows at most
        for b in set(r["set"]):
            design[r["cohort"] * BITS + b, place[r["item"]]] = 1 / COHORTS
    for r in reports.collect():  # COHORTS * BITS rows
        target[r["cohort"] * BITS + r["bit"]] = (r["s"] - k["q"] * r["n"]) / (1 - 2 * k["q"])
    x, gram, pull = np.zeros(len(names) + 1), design.T @ design, design.T @ target
    for _ in range(300):  # coordinate descent
        for i in range(len(x)):
            x[i] = max(0.0, x[i] + (pull[i] - gram[i] @ x) / gram[i, i])
    return spark.createDataFrame([(n, round(float(v), 4)) for n, v in zip(names, x[:-1], strict=True)], "item string, est double")


# --- earlier local protocols ----------------------------------------------------------------------------------


def predecessor(pop: DataFrame, dictionary: DataFrame, p: Params) -> DataFrame:
    """The earlier optimal protocol's estimates for a small dictionary: a sum over all users for every query.

    Its discovery is ``hashed_bits.discover_predecessor``. Its cost is what matters (``plans.cost``); use both where users
    times queries is affordable.
    """
    return plain_estimates(pop, dictionary, p)
