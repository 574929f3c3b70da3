"""Which protocol for which dictionary."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ldp_hist.functions.encoding import Encoding
from ldp_hist.operators import hashed_bits, prefix_tree, sign_matrix_oracle, sketch_oracle
from ldp_hist.plans.params import Params, note, suggest_pairs


def choose_method(n: int, log_d: int, dictionary: bool = False, one_round: bool = False) -> str:
    """``enumerate`` below sqrt(n) items, ``dictionary`` if it is known, else the tree, or the coded protocol in one round."""
    if log_d * 2 <= math.log2(max(n, 2)):
        return "enumerate"
    if dictionary:
        return "dictionary"
    return "coded" if one_round else "tree"


def all_items(spark: SparkSession, encoding: Encoding) -> DataFrame:
    """(item): every item that an encoding has a code for, made by the executors."""
    code = F.lit(0).cast("long")
    for i in range(encoding.levels):
        code = code + (F.floor(F.col("id") / encoding.symbols**i) % encoding.symbols).cast("long") * (1 << encoding.bits * i)
    return spark.range(encoding.symbols**encoding.levels).select(encoding.decode(code).alias("item"))


def histogram(
    pop: DataFrame, eps: float, encoding: Encoding | None = None, dictionary: DataFrame | None = None, one_round: bool = False,
    coin_key: int | str | None = None, for_tests: bool = False,
) -> DataFrame:
    """(item, est) by the method that suits; the one call for users who don't want to choose.

    ``coin_key`` is the secret that the users' coins are drawn with and has to be given; only ``for_tests`` runs, whose coins are
    public and which have no privacy, do without. A dictionary of fewer than sqrt(n) items is asked for whole, and if none is given
    but the encoding has as few codes, these are.
    """
    p = Params(eps=eps, coin_key=coin_key, public_coins=for_tests)
    p.coins  # noqa: B018 (ends here without a key)
    n = pop.count()
    size = dictionary.count() if dictionary is not None else encoding.symbols**encoding.levels
    log_d = math.ceil(math.log2(max(2, size)))
    method = choose_method(n, log_d, dictionary is not None, one_round)
    p = p.but(t=suggest_pairs(n), m=1024)
    if method == "enumerate":
        note("partitioned", n, p)
        if dictionary is not None:
            return sign_matrix_oracle.full_histogram(pop, dictionary, p)
        fitted = pop.select("user_key", encoding.decode(encoding.encode(F.col("item"))).alias("item"))
        return sign_matrix_oracle.full_histogram(fitted, all_items(pop.sparkSession, encoding), p)
    if dictionary is not None:
        note("sketch", n, p)
        return sketch_oracle.dictionary_frequencies(pop, dictionary, p)
    if method == "coded":
        return hashed_bits.coded(pop, p, encoding).select("item", "est")
    return prefix_tree.tree_heavy_hitters(pop, p.but(t=suggest_pairs(n, encoding.levels)), encoding).select("item", "est")
