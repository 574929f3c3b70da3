"""The compressed private count sketch: one-bit reports, counters, and frequency queries.

A report multiplies the sign hash of the user's item by one entry of the sign matrix and flips it by the
user's coin. The server sums reports by (pair, row); the sums are linear, so sites, days and streams add up. A query
either sums a counter row by row (``counters``) or looks one cell up after a fast transform (``transform``);
both give the same integers, and ``direct`` sums the reports themselves, as a baseline of cost.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.encoding import Encoding
from ldp_hist.functions.hadamard import fwht_groups, had_sign
from ldp_hist.functions.hashing import bucket_hash, digest, sign_hash
from ldp_hist.functions.randomizers import debias, randomised
from ldp_hist.functions.randomness import assign, coin
from ldp_hist.plans.params import Params
from ldp_hist.plans.privacy import Ledger

def _bit(seed, pair: Column, x: Column, row: Column, m: int) -> Column:
    return sign_hash(seed, pair, x) * had_sign(row, bucket_hash(seed, pair, x, m))


def dictionary_reports(pop: DataFrame, p: Params, seed: int | Column | None = None, eps: float | None = None, run: Column | None = None) -> DataFrame:
    """(pair, row, y): one report a user with the whole budget. No shuffle; the item is dropped here.

    ``seed`` replaces the public seed and nothing else; repetitions over the same users throw coins of their own by their ``run``.
    """
    ledger, eps = Ledger.of(p), eps or p.eps
    ledger.spend("item", eps)
    seed = p.seed if seed is None else seed
    own = assign(pop, seed, t=p.t, m=p.m)
    y = randomised(_bit(seed, F.col("pair"), F.coalesce("item", F.lit("")), F.col("row"), p.m), eps, coin(1, F.col("user_key"), p.coins, run))
    keep = [c for c in pop.columns if c not in ("user_key", "item")]
    return own.select(*keep, "pair", "row", y.alias("y"))


def budget_reports(pop: DataFrame, p: Params, budgets: list[float], seed: int | Column, run: Column) -> DataFrame:
    """(pair, row, y0, y1, ...): what ``dictionary_reports`` sends at each of ``budgets``; draws, hashes and coins, which no budget changes, are made once.

    Every budget is an experiment of its own; reports of several together would spend their sum.
    """
    for eps in budgets:
        Ledger.of(p.but(eps=eps)).spend("item", eps)
    own = assign(pop, seed, t=p.t, m=p.m)
    keep = [c for c in pop.columns if c not in ("user_key", "item")]
    own = own.select(*keep, "pair", "row", _bit(seed, F.col("pair"), F.coalesce("item", F.lit("")), F.col("row"), p.m).alias("bit"), coin(1, F.col("user_key"), p.coins, run).alias("coin"))
    return own.select(*keep, "pair", "row", *[randomised(F.col("bit"), eps, F.col("coin")).alias(f"y{i}") for i, eps in enumerate(budgets)])


def node_name(level: Column, prefix: Column) -> Column:
    """How a node of the prefix tree is hashed."""
    return F.concat_ws(".", level.cast("string"), prefix.cast("string"))


def tree_reports(pop: DataFrame, p: Params, encoding: Encoding, keep_user: bool = False, run: str | None = None) -> DataFrame:
    """(level, pair, row, y1, y2): the two reports of each user, half the budget each, sent in one round.

    y1 speaks of the prefix at the user's level, y2 of the whole item, with a fresh coin. ``run`` names a column of public
    seeds, one for each repetition over the same users; it is kept.
    """
    ledger = Ledger.of(p)
    ledger.spend("prefix", p.eps / 2)
    ledger.spend("item", p.eps / 2)
    seed, runs = (p.seed, None) if run is None else (F.col(run), F.col(run))
    own = assign(pop.withColumn("code", encoding.encode(F.col("item"))), seed, levels=encoding.levels, t=p.t, m=p.m)
    names = (node_name(F.col("level"), encoding.prefix(F.col("code"), F.col("level"))), node_name(F.lit(encoding.levels), F.col("code")))
    ys = [randomised(_bit(seed, F.col("pair"), x, F.col("row"), p.m), p.eps / 2, coin(i + 1, F.col("user_key"), p.coins, runs)) for i, x in enumerate(names)]
    return own.select(*["user_key"] * keep_user, *([] if run is None else [run]), "level", "pair", "row", ys[0].alias("y1"), ys[1].alias("y2"))


def count(reports: DataFrame, keys: list[str], y: str = "y") -> DataFrame:
    """Sums by ``keys``: map-side sums first, so that cells are shuffled rather than users."""
    return reports.groupBy(*keys).agg(F.sum(F.col(y).cast("long")).alias("s"))


def _places(cands: DataFrame, p: Params, seed: int) -> DataFrame:
    """Every candidate ``x`` with its cell and sign in every pair."""
    each = cands.select("*", F.explode(F.sequence(F.lit(0), F.lit(p.t - 1))).alias("pair"))
    return each.withColumns({"cell": bucket_hash(seed, F.col("pair"), F.col("x"), p.m), "g": sign_hash(seed, F.col("pair"), F.col("x"))})


def signed_sums(table: DataFrame, cands: DataFrame, p: Params, mode: str = "transform", seed: int | None = None) -> DataFrame:
    """Columns of ``cands`` (which has ``x``), pair, v: the signed sum for every candidate and pair; 0 if no user.

    ``table`` has reports (pair, row, y) in mode ``direct``, counters (pair, row, s) otherwise. Nothing is broadcast by force: candidates
    may be a whole dictionary, and the planner knows the sizes of those that are few.
    """
    seed = p.seed if seed is None else seed
    places = _places(cands, p, seed)
    own = [c for c in places.columns if c not in ("cell", "g")]
    if mode == "transform":
        cells = fwht_groups(table.select("pair", "row", "s"), ["pair"], "row", p.m)
        return places.join(cells, ["pair", "cell"], "left").select(*own, (F.col("g") * F.coalesce("v", F.lit(0))).cast("long").alias("v"))
    value = F.col("y").cast("long") if mode == "direct" else F.col("s")
    joined = table.join(places, "pair")
    sums = joined.groupBy(*own).agg(F.sum(value * F.col("g") * had_sign(F.col("row"), F.col("cell"))).alias("sum"))
    return places.select(*own).join(sums, own, "left").select(*own, F.coalesce("sum", F.lit(0)).cast("long").alias("v"))


def combined(sums: DataFrame, cands: DataFrame, scale: float, t: int, combine: str = "median") -> DataFrame:
    """Columns of ``cands`` and ``est``: the scaled median (or mean) over the pairs."""
    over = F.median("v") if combine == "median" else F.sum("v").cast("double") / t
    return sums.groupBy(*cands.columns).agg(F.round(F.lit(scale) * over, 4).alias("est"))


def dictionary_estimates(reports: DataFrame, items: DataFrame, p: Params, mode: str = "transform", combine: str = "median", seed: int | None = None) -> DataFrame:
    """(item, est) for every row of ``items`` (item)."""
    table = reports if mode == "direct" else count(reports, ["pair", "row"])
    cands = items.select("item", F.coalesce("item", F.lit("")).alias("x"))
    sums = signed_sums(table, cands, p, mode, seed)
    return combined(sums, cands, p.t * debias(p.eps), p.t, combine).drop("x")


def dictionary_frequencies(pop: DataFrame, items: DataFrame, p: Params, **how) -> DataFrame:
    """Private frequencies of a known dictionary: the whole protocol, reports to estimates."""
    return dictionary_estimates(dictionary_reports(pop, p), items, p, **how)


def whole_row_estimates(pop: DataFrame, items: DataFrame, p: Params) -> DataFrame:
    """The variant without compression: a user sends a whole row of m signs.

    The cell of the item carries its sign, kept with the randomiser's probability; all others are fair coins,
    which is as private. The fair coins are the bits of digests, 256 cells to one, and a row is summed as what all cells throw and
    what the item's cell says instead, so a user costs m/4 hex digits rather than m digests.
    """
    Ledger.of(p).spend("row", p.eps)
    own = assign(pop, p.seed, t=p.t)
    own = own.withColumns({"h": bucket_hash(p.seed, F.col("pair"), F.col("item"), p.m), "g": sign_hash(p.seed, F.col("pair"), F.col("item"))})
    said = own.select("pair", F.col("h").alias("cell"), randomised(F.col("g"), p.eps, coin(1, F.col("user_key"), p.coins)).alias("y"), "user_key")

    def thrown(block: Column) -> Column:
        return digest("row", p.coins, F.col("user_key"), block)

    digits = max(1, min(64, p.m // 4))
    rows = said.select("pair", F.explode(F.sequence(F.lit(0), F.lit(max(1, p.m // 256) - 1))).alias("block"), "user_key")
    nibbles = rows.select("pair", "block", thrown(F.col("block")).alias("d")).select("pair", "block", "d", F.explode(F.sequence(F.lit(0), F.lit(digits - 1))).alias("at"))
    value = F.instr(F.lit("0123456789abcdef"), F.expr("substring(d, at + 1, 1)")) - 1
    sums = nibbles.select("pair", "block", "at", value.alias("x")).groupBy("pair", "block", "at").agg(*[F.sum(1 - 2 * F.shiftright("x", b).bitwiseAND(F.lit(1))).alias(f"b{b}") for b in range(4)])
    fair = sums.select("pair", F.explode(F.array(*[F.struct((F.col("block") * 256 + F.col("at") * 4 + b).cast("long").alias("cell"), F.col(f"b{b}").alias("v")) for b in range(4)])).alias("x")).select("pair", "x.*")
    own_digit = F.instr(F.lit("0123456789abcdef"), F.substring(thrown(F.floor(F.col("cell") / 256).cast("int")), (F.floor((F.col("cell") % 256) / 4) + 1).cast("int"), F.lit(1))) - 1
    own_fair = 1 - 2 * (F.floor(own_digit / F.pow(F.lit(2.0), (F.col("cell") % 4).cast("double"))).cast("int") % 2)
    instead = said.groupBy("pair", "cell").agg(F.sum((F.col("y") - own_fair).cast("long")).alias("v"))
    sums = fair.where(F.col("cell") < p.m).unionByName(instead).groupBy("pair", "cell").agg(F.sum("v").alias("v"))
    cands = items.select("item", F.col("item").alias("x"))
    found = _places(cands, p, p.seed).join(sums, ["pair", "cell"], "left").select("item", "x", "pair", (F.col("g") * F.coalesce("v", F.lit(0))).cast("long").alias("v"))
    return combined(found, cands, p.t * debias(p.eps), p.t).drop("x")


def count_sketch(pop: DataFrame, items: DataFrame, p: Params) -> DataFrame:
    """The sketch without privacy: every user counts in every pair. Its error is the sketch's own."""
    each = pop.groupBy("item").agg(F.count("*").alias("n")).select("item", "n", F.explode(F.sequence(F.lit(0), F.lit(p.t - 1))).alias("pair"))
    table = each.withColumns({"cell": bucket_hash(p.seed, F.col("pair"), F.col("item"), p.m), "g": sign_hash(p.seed, F.col("pair"), F.col("item"))})
    table = table.groupBy("pair", "cell").agg(F.sum(F.col("n") * F.col("g")).alias("v"))
    cands = items.select("item", F.col("item").alias("x"))
    found = _places(cands, p, p.seed).join(table, ["pair", "cell"], "left").select("item", "x", "pair", (F.col("g") * F.coalesce("v", F.lit(0))).cast("long").alias("v"))
    return combined(found, cands, 1.0, p.t).drop("x")
