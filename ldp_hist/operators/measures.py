"""Measures of accuracy over a truth (item, f) and a list (item, est)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ldp_hist.functions.hashing import bucket_hash, sign_hash
from ldp_hist.functions.randomizers import debias


def against(truth: DataFrame, hist: DataFrame, how: str = "full") -> DataFrame:
    """(item, f, est): an item that is missing on one side counts as zero there."""
    joined = truth.select("item", "f").join(hist.select("item", "est"), "item", how)
    return joined.select("item", F.coalesce("f", F.lit(0)).alias("f"), F.coalesce("est", F.lit(0.0)).alias("est"))


def linf_error(truth: DataFrame, hist: DataFrame) -> DataFrame:
    """The greatest error over the dictionary, unlisted items being estimated at zero."""
    return against(truth, hist).agg(F.round(F.max(F.abs(F.col("est") - F.col("f"))), 4).alias("linf"), F.count("*").alias("items"))


def list_error(truth: DataFrame, hist: DataFrame) -> DataFrame:
    """The greatest error over the listed items only."""
    return against(truth, hist, "right").agg(F.round(F.max(F.abs(F.col("est") - F.col("f"))), 4).alias("list_error"), F.count("*").alias("items"))


def precision_recall(truth: DataFrame, hist: DataFrame, threshold: Column) -> DataFrame:
    """tp, fp, fn, precision, recall of the listed items against those of at least the threshold; null if undefined."""
    both = truth.select("item", "f").join(hist.select("item", F.lit(1).alias("listed")), "item", "full")
    heavy, listed = F.coalesce(F.col("f") >= threshold, F.lit(False)), F.col("listed").isNotNull()
    sums = both.agg(*[F.coalesce(F.sum(x.cast("long")), F.lit(0)).alias(n) for n, x in (("tp", heavy & listed), ("fp", ~heavy & listed), ("fn", heavy & ~listed))])
    return sums.select("tp", "fp", "fn", F.round(F.try_divide("tp", F.col("tp") + F.col("fp")), 6).alias("precision"), F.round(F.try_divide("tp", F.col("tp") + F.col("fn")), 6).alias("recall"))


def run_stats(runs: DataFrame, truth: DataFrame, n: int | Column) -> DataFrame:
    """item, mean, sd, share, within: normalised estimates over seeds against the true share.

    ``within`` says whether the mean is within one standard deviation of the truth.
    """
    size = n if isinstance(n, Column) else F.lit(n)
    stats = runs.groupBy("item").agg(F.avg(F.col("est") / size).alias("mean"), F.stddev_samp(F.col("est") / size).alias("sd"))
    out = stats.join(truth.select("item", (F.col("f") / size).alias("share")), "item")
    return out.select("item", F.round("mean", 6).alias("mean"), F.round("sd", 6).alias("sd"), F.round("share", 6).alias("share"), (F.abs(F.col("mean") - F.col("share")) <= F.col("sd")).alias("within"))


def _ordered(truth: DataFrame) -> DataFrame:
    """Items by frequency with their place from the commonest and the number of items.

    Frequencies repeat a lot among rare items, so places come from counts of equal frequencies: the window runs over
    distinct frequencies (their number is at most sqrt(2n)), and a second one orders the items within each.
    """
    levels = truth.groupBy("f").agg(F.count("*").alias("k"))
    before = Window.orderBy(F.desc("f")).rowsBetween(Window.unboundedPreceding, -1)
    places = levels.select("f", F.coalesce(F.sum("k").over(before), F.lit(0)).alias("above"))
    return truth.join(F.broadcast(places), "f")


def ranks(truth: DataFrame) -> DataFrame:
    """(f, rank): the rank that items of a frequency share, by a window over distinct frequencies (at most sqrt(2n))."""
    levels = truth.groupBy("f").agg(F.count("*").alias("k"))
    before = Window.orderBy(F.desc("f")).rowsBetween(Window.unboundedPreceding, -1)
    return levels.select("f", (F.coalesce(F.sum("k").over(before), F.lit(0)) + 1).alias("rank"))


def rank_items(truth: DataFrame, ranks: list[int]) -> DataFrame:
    """(rank, item, f) at the given ranks of the frequency order; ties by item."""
    placed = _ordered(truth)
    near = F.lit(False)
    for r in ranks:
        near = near | (F.col("above") < r)
    inside = Window.partitionBy("f").orderBy("item")
    low = placed.where(F.col("above") < max(ranks)).withColumn("rank", (F.col("above") + F.row_number().over(inside)).cast("long"))
    return low.where(F.col("rank").isin(ranks)).select("rank", "item", "f")


def percentile_items(truth: DataFrame, percentiles: list[float]) -> DataFrame:
    """(pctle, item, f): at each percentile of the items' frequency order the least item of the last frequency within it.

    An item's percentile is the share of items that are strictly rarer.
    """
    below = Window.orderBy("f").rowsBetween(Window.unboundedPreceding, -1)
    levels = truth.groupBy("f").agg(F.count("*").alias("k"), F.min("item").alias("item"))
    total = levels.agg(F.sum("k").alias("items"))
    placed = levels.select("f", "item", F.coalesce(F.sum("k").over(below), F.lit(0)).alias("rarer")).join(F.broadcast(total))
    share = 100.0 * F.col("rarer") / F.col("items")
    asked = placed.select("f", "item", F.explode(F.array(*[F.lit(float(x)) for x in percentiles])).alias("pctle"), share.alias("share"))
    best = asked.where("share <= pctle").groupBy("pctle").agg(F.max(F.struct("f", "item")).alias("x"))
    return best.select("pctle", F.col("x.item").alias("item"), F.col("x.f").alias("f"))


def check_guarantee(truth: DataFrame, hist: DataFrame, eta: float, bound: float) -> DataFrame:
    """missing (f > 3 eta, not listed), spurious (f < eta, listed), the greatest error of the list, within the bound?"""
    both = truth.select("item", "f").join(hist.select("item", "est"), "item", "full").withColumn("f", F.coalesce("f", F.lit(0)))
    missing = (F.col("f") > 3 * eta) & F.col("est").isNull()
    spurious = (F.col("f") < eta) & F.col("est").isNotNull()
    sums = both.agg(F.coalesce(F.sum(missing.cast("long")), F.lit(0)).alias("missing"), F.coalesce(F.sum(spurious.cast("long")), F.lit(0)).alias("spurious"), F.round(F.max(F.abs(F.col("est") - F.col("f"))), 4).alias("max_error"))
    return sums.select("missing", "spurious", "max_error", (F.coalesce("max_error", F.lit(0.0)) <= bound).alias("within_bound"))


def sketch_diagnostics(own: DataFrame, n: int | Column, t: int, levels: int = 1) -> DataFrame:
    """groups, good, share: groups of users (level, pair) whose size is within a factor two of the mean."""
    size = n if isinstance(n, Column) else F.lit(n)
    mean = size / (t * levels)
    groups = own.groupBy("level", "pair").agg(F.count("*").alias("users"))
    ok = (F.col("users") >= mean / 2) & (F.col("users") <= mean * 2)
    return groups.agg(F.lit(t * levels).cast("long").alias("groups"), F.coalesce(F.sum(ok.cast("long")), F.lit(0)).alias("good")).select("groups", "good", F.round(F.col("good") / F.col("groups"), 6).alias("share"))


def good_pairs(own: DataFrame, sums: DataFrame, truth: DataFrame, p, scale: float) -> DataFrame:
    """(item, g1, g2, g3): of each asked item the number of pairs whose sampling, collisions, and estimates are within the analysis' bounds.

    ``own`` has (item, pair) of every user, ``sums`` the signed sums (item, pair, v), ``truth`` (item, f), ``scale`` the
    inverse sampling rate of a pair. g1: the pair's users are within a factor two of their mean and the item's within
    4 sqrt(n scale) of its own, scaled up; g2: so is the sketch of the pair's items without privacy, within 8 of these; g3: the
    private estimate, within 14 / eps.
    """
    per = own.groupBy("item", "pair").agg(F.count("*").alias("k"))
    users = per.groupBy("pair").agg(F.sum("k").alias("users"))
    total = truth.agg(F.sum("f").alias("n"))
    placed = per.withColumns({"cell": bucket_hash(p.seed, F.col("pair"), F.col("item"), p.m), "g": sign_hash(p.seed, F.col("pair"), F.col("item"))})
    cells = placed.groupBy("pair", "cell").agg(F.sum(F.col("g") * F.col("k")).alias("c"))
    asked = sums.select("item", "pair", "v").join(truth, "item").join(per, ["item", "pair"], "left").join(users, "pair", "left").join(F.broadcast(total))
    asked = asked.withColumns({"cell": bucket_hash(p.seed, F.col("pair"), F.col("item"), p.m), "g": sign_hash(p.seed, F.col("pair"), F.col("item"))}).join(cells, ["pair", "cell"], "left")
    unit, n = F.sqrt(F.col("n") * scale), F.col("n")
    held, sketched = scale * F.coalesce("k", F.lit(0)), scale * F.col("g") * F.coalesce("c", F.lit(0))
    g1 = (F.abs(held - F.col("f")) <= 4 * unit) & (scale * F.coalesce("users", F.lit(0))).between(n / 2, 2 * n)
    g2, g3 = F.abs(sketched - F.col("f")) <= 8 * unit, F.abs(scale * debias(p.eps) * F.col("v") - F.col("f")) <= 14 / p.eps * unit
    return asked.groupBy("item").agg(*[F.sum(x.cast("long")).alias(name) for name, x in (("g1", g1), ("g2", g2), ("g3", g3))])


def good_subsets(own: DataFrame, R: int, T: int) -> DataFrame:
    """(item, collisions, sizes, sampling): of each item the subsets where the partitioned oracle's three events hold.

    ``own`` has (item, subset) of every user and ``cell``, an array of every user's cell under each subset's hash. Collisions: other
    items' users in the cell are at most 16 n / T; sizes: the subset is within a factor two of n / R; sampling: the cell's
    users in the subset, times R, are within sqrt(8 R n) of all users in it.
    """
    per = own.groupBy("item", "subset").agg(F.count("*").alias("k"))
    items = per.groupBy("item").agg(F.sum("k").alias("f"))
    total = items.agg(F.sum("f").alias("n"))
    sizes = per.groupBy("subset").agg(F.sum("k").alias("users"))
    every = items.join(own.select("item", "cells").distinct(), "item").select("item", "f", F.posexplode("cells").alias("subset", "cell"))
    whole = every.groupBy("subset", "cell").agg(F.sum("f").alias("all"))
    drawn = per.join(every.select("item", "subset", "cell"), ["item", "subset"]).groupBy("subset", "cell").agg(F.sum("k").alias("here"))
    joined = every.join(whole, ["subset", "cell"]).join(drawn, ["subset", "cell"], "left").join(sizes, "subset", "left").join(F.broadcast(total))
    n = F.col("n")
    events = {
        "collisions": F.col("all") - F.col("f") <= 16 * n / T, "sizes": F.coalesce("users", F.lit(0)).between(n / (2 * R), 2 * n / R),
        "sampling": F.abs(R * F.coalesce("here", F.lit(0)) - F.col("all")) <= F.sqrt(8 * R * n),
    }
    return joined.groupBy("item").agg(*[F.sum(x.cast("long")).alias(name) for name, x in events.items()])


def run_quality(truth: DataFrame, runs: DataFrame, threshold: float, seeds: list[int]) -> DataFrame:
    """(runs, precision, precision_sd, recall, recall_sd): mean and standard deviation over runs (run, item, ...).

    A run that lists nothing has no precision; without an item of the threshold there is no recall.
    """
    heavy = truth.where(F.col("f") >= F.lit(threshold)).select("item", F.lit(1).alias("heavy"))
    hits = runs.select("run", "item").join(heavy, "item", "left").groupBy("run").agg(F.count("*").alias("listed"), F.count("heavy").alias("hit"))
    every = truth.sparkSession.createDataFrame([(s,) for s in seeds], "run int")
    each = every.join(hits, "run", "left").join(F.broadcast(heavy.agg(F.count("*").alias("due")))).select(
        F.try_divide("hit", "listed").alias("precision"), F.try_divide(F.coalesce("hit", F.lit(0)), F.col("due")).alias("recall"))
    return each.agg(F.count("*").alias("runs"), *[F.round(f(n), 6).alias(a) for n in ("precision", "recall") for f, a in ((F.avg, n), (F.stddev_samp, f"{n}_sd"))])


def partition_diagnostics(pop: DataFrame, p, item_cells: Column, subset: Column) -> DataFrame:
    """subset, users, collisions: of each subset its size and the users whose cell another item shares."""
    own = pop.select("item", subset.alias("subset"), item_cells.alias("cell"))
    per = own.groupBy("subset", "cell", "item").agg(F.count("*").alias("k"))
    cells = per.groupBy("subset", "cell").agg(F.sum("k").alias("k"), F.count("*").alias("items"))
    return cells.groupBy("subset").agg(F.sum("k").alias("users"), F.sum(F.when(F.col("items") > 1, F.col("k")).otherwise(0)).alias("collisions"))


def bit_error_report(bits: DataFrame, truth_bits: DataFrame) -> DataFrame:
    """item, bits, wrong, rate: of each heavy item the bits of its cell that were read wrongly."""
    joined = truth_bits.join(bits, ["rep", "cell", "bit"], "left")
    wrong = (F.coalesce("value", F.lit(0)) != F.col("true_value")).cast("long")
    return joined.groupBy("item").agg(F.count("*").alias("bits"), F.sum(wrong).alias("wrong")).select("item", "bits", "wrong", F.round(F.col("wrong") / F.col("bits"), 6).alias("rate"))
