"""Heavy hitters down a prefix tree: estimate the children of what survived, keep the heavy ones, repeat.

Reports are read once: counters of all levels and of the whole items, and the number of users, come from one scan, and one job
transforms them all. A level is then a join of the candidates with the transformed cells; the frontier stays a table, kept from
level to level so that plans don't grow. Repetitions over the same users (``runs``) walk together, a column apart.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.encoding import Encoding
from ldp_hist.functions.hadamard import fwht_groups
from ldp_hist.functions.hashing import bucket_hash, sign_hash
from ldp_hist.functions.randomizers import debias
from ldp_hist.operators.run_counters import fits, run_counters
from ldp_hist.operators.sketch_oracle import combined, count, dictionary_reports, node_name, signed_sums, tree_reports
from ldp_hist.plans.params import Params, note

#: A level may ask for this many nodes, or for so many times what the threshold lets through; more means that it is below the noise.
GUARD, SLACK = 200_000, 4


@dataclass
class Walk:
    """Transformed counters of one or more runs, and what was seen on the way down."""

    cells: DataFrame  # run, level, pair, cell, v
    final: DataFrame | None  # run, pair, cell, v; None without second reports
    encoding: Encoding
    p: Params
    n: int
    threshold: float
    runs: list[int]
    trace: list[DataFrame] = field(default_factory=list)
    frontier: DataFrame | None = None
    kept: list[DataFrame] = field(default_factory=list)

    def close(self) -> None:
        """Releases what the walk holds; its results can't be read after that."""
        for df in self.kept:
            df.unpersist()
        self.kept.clear()


def noise_threshold(n: int, factor: float = 15.0) -> float:
    """The experiment's threshold, a multiple of sqrt(n); it plays the part of twice eta."""
    return factor * math.sqrt(n)


def start(pop: DataFrame, p: Params, encoding: Encoding, factor: float = 15.0, threshold: float | None = None, runs: list[int] | None = None, second: bool = True) -> Walk:
    """Reads the reports; ``runs`` are public seeds, one for each repetition (by default the one of ``p``).

    Without ``second`` the second reports of ``runs`` are left alone: the walk lists nodes, and ``finish`` can't estimate them again.
    """
    seeds = [p.seed] if runs is None else runs
    if runs is not None and fits(p, encoding, seeds):
        both = run_counters(pop, p, encoding, seeds, second).persist()
    else:
        if runs is None:
            reports = tree_reports(pop, p, encoding).withColumn("run", F.lit(p.seed))
        else:
            reports = tree_reports(pop.withColumn("run", F.explode(F.array(*[F.lit(s) for s in seeds]))), p, encoding, run="run")
        both = reports.groupBy("run", "level", "pair", "row").agg(F.sum("y1").alias("s"), F.sum("y2").alias("s2"), F.count("*").alias("users")).persist()
    n = (both.agg(F.sum("users")).first()[0] or 0) // len(seeds)
    note("tree", n, p, encoding.width)
    cells = fwht_groups(both.select("run", "level", "pair", "row", "s"), ["run", "level", "pair"], "row", p.m).persist()
    threshold = noise_threshold(n, factor) if threshold is None else threshold
    if not second:
        return Walk(cells, None, encoding, p, n, threshold, seeds, kept=[both, cells])
    whole = both.groupBy("run", "pair", "row").agg(F.sum("s2").alias("s"))
    final = fwht_groups(whole, ["run", "pair"], "row", p.m).persist()
    return Walk(cells, final, encoding, p, n, threshold, seeds, kept=[both, cells, final])


def _estimates(walk: Walk, cells: DataFrame, asked: DataFrame, name: Column, column: str, scale: float) -> DataFrame:
    """run, ``column``, est of candidates, by look-ups in transformed cells; a cell without a user is zero."""
    p = walk.p
    seed = F.lit(p.seed) if walk.runs == [p.seed] else F.col("run")
    each = asked.select("run", column, name.alias("x"), F.explode(F.sequence(F.lit(0), F.lit(p.t - 1))).alias("pair"))
    places = each.withColumns({"cell": bucket_hash(seed, F.col("pair"), F.col("x"), p.m), "g": sign_hash(seed, F.col("pair"), F.col("x"))})
    sums = places.join(cells, ["run", "pair", "cell"], "left").select("run", column, (F.col("g") * F.coalesce("v", F.lit(0))).alias("v"))
    return sums.groupBy("run", column).agg(F.round(F.lit(scale) * F.median("v"), 4).alias("est"))


def level_estimates(walk: Walk, level: int, prefixes: DataFrame) -> DataFrame:
    """(run, prefix, est) for candidate prefixes (run, prefix) of a level."""
    cells = walk.cells.where(F.col("level") == level).drop("level")
    scale = walk.p.t * walk.encoding.levels * debias(walk.p.eps / 2)
    return _estimates(walk, cells, prefixes, node_name(F.lit(level), F.col("prefix")), "prefix", scale)


def descend(walk: Walk, beam: int | None = None) -> Walk:
    """Walks all levels. With ``beam`` the best so many of each run survive instead of those above the threshold."""
    e, spark = walk.encoding, walk.cells.sparkSession
    frontier = spark.createDataFrame([(s, 0) for s in walk.runs], "run int, prefix long")
    most = max(GUARD, math.ceil(SLACK * walk.n / walk.threshold) * e.symbols) if walk.threshold > 0 else GUARD
    symbols = F.explode(F.array(*[F.lit(i).cast("long") for i in range(e.symbols)])).alias("symbol")
    for level in range(1, e.levels + 1):
        asked = frontier.select("run", "prefix", symbols).select("run", (F.col("prefix") * (1 << e.bits) + F.col("symbol")).alias("prefix"))
        found = level_estimates(walk, level, asked)
        if beam:
            found = found.persist()
            best = found.groupBy("run").agg(F.slice(F.sort_array(F.collect_list(F.struct((-F.col("est")).alias("by"), "prefix"))), 1, beam).alias("best"))
            # A level asks for beam * symbols nodes a run and keeps ``beam`` of them: as plain rows they don't carry the plans of all levels before.
            nodes = [(r["run"], x["prefix"]) for r in best.collect() for x in r["best"]]
            walk.kept.append(found)
            best = spark.createDataFrame(nodes, "run int, prefix long")
            found = found.join(F.broadcast(best.withColumn("kept", F.lit(True))), ["run", "prefix"], "left").withColumn("kept", F.coalesce("kept", F.lit(False)))
        else:
            found = found.withColumn("kept", F.col("est") >= F.lit(walk.threshold)).persist()
            walk.kept.append(found)
        queried, survive = found.agg(F.count("*"), F.sum(F.col("kept").cast("long"))).first()
        walk.trace.append(found.select("run", F.lit(level).alias("level"), "prefix", "est", "kept"))
        frontier = best if beam else found.where("kept").select("run", "prefix")
        if (survive or 0) * e.symbols > most * len(walk.runs) and level < e.levels:
            walk.close()
            raise ValueError(f"{survive} of {queried} nodes survive level {level}: the threshold is within the noise")
        if not survive:
            break
    walk.frontier = frontier
    return walk


def listed(walk: Walk) -> DataFrame:
    """(run, code): what a walk down to the last level found."""
    reached = walk.frontier if len(walk.trace) == walk.encoding.levels else walk.frontier.limit(0)
    return reached.select("run", F.col("prefix").alias("code"))


def finish(walk: Walk) -> DataFrame:
    """(run, code, item, est): survivors estimated again from everybody's second report."""
    e, p = walk.encoding, walk.p
    if walk.final is None:
        raise ValueError("the walk was started without second reports")
    asked = listed(walk)
    hist = _estimates(walk, walk.final, asked, node_name(F.lit(e.levels), F.col("code")), "code", p.t * debias(p.eps / 2))
    return hist.select("run", "code", e.decode(F.col("code")).alias("item"), "est")


def tree_heavy_hitters(pop: DataFrame, p: Params, encoding: Encoding, factor: float = 15.0, threshold: float | None = None, beam: int | None = None) -> DataFrame:
    """(code, item, est) of the heavy items of ``pop``, discovered without knowing the dictionary.

    ``beam`` gives the heuristic without bounds: a fixed number of best prefixes and no threshold.
    """
    return finish(descend(start(pop, p, encoding, factor, threshold), beam)).drop("run")


def tree_runs(pop: DataFrame, p: Params, encoding: Encoding, seeds: list[int], factor: float = 15.0) -> DataFrame:
    """(run, code, item, est): the protocol repeated with other public draws and coins, all runs in one walk."""
    return finish(descend(start(pop, p, encoding, factor, runs=seeds)))


def tree_run_lists(pop: DataFrame, p: Params, encoding: Encoding, seeds: list[int], factor: float = 15.0) -> DataFrame:
    """(run, code, item): what ``tree_runs`` lists. Second reports only estimate what is listed, so they aren't summed."""
    found = listed(descend(start(pop, p, encoding, factor, runs=seeds, second=False)))
    return found.select("run", "code", encoding.decode(F.col("code")).alias("item"))


def tree_candidates(pop: DataFrame, p: Params, encoding: Encoding, factor: float = 15.0) -> Walk:
    """The walk without the final estimates."""
    return descend(start(pop, p, encoding, factor))


def tree_trace(walk: Walk) -> DataFrame:
    """(level, prefix, est, kept) of every node that was asked for, first run."""
    out = walk.trace[0]
    for t in walk.trace[1:]:
        out = out.unionByName(t)
    return out.where(F.col("run") == walk.runs[0]).drop("run")


def node_queries(trace: DataFrame) -> DataFrame:
    """(level, queried, kept), level null for all: how many oracle queries the walk took."""
    return trace.rollup("level").agg(F.count("*").alias("queried"), F.sum(F.col("kept").cast("long")).alias("kept"))


def brute_force(pop: DataFrame, p: Params, encoding: Encoding, factor: float = 15.0) -> DataFrame:
    """Asks the oracle for every string there is, spending the whole budget on one report; for short strings.

    Candidates are a range that the executors make, so their number is limited by patience alone.
    """
    spark, e = pop.sparkSession, encoding
    named = pop.select("user_key", node_name(F.lit(e.levels), e.encode(F.col("item"))).alias("item"))
    code, digits = F.lit(0).cast("long"), F.col("id")
    for i in range(e.levels):
        code = code + (F.floor(digits / e.symbols**i) % e.symbols).cast("long") * (1 << e.bits * i)
    cands = spark.range(e.symbols**e.levels).select(code.alias("code")).withColumn("x", node_name(F.lit(e.levels), F.col("code")))
    sums = signed_sums(count(dictionary_reports(named, p), ["pair", "row"]), cands, p)
    hist = combined(sums, cands, p.t * debias(p.eps), p.t).where(F.col("est") >= noise_threshold(pop.count(), factor))
    return hist.select("code", e.decode(F.col("code")).alias("item"), "est")
