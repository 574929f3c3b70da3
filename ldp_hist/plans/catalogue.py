"""The query catalogue: one entry a method, variant, baseline, measure or workload, with DuckDB SQL where there is one.

Unless a name says otherwise the parameters are ``params.TINY`` and the coins are public, so that both engines throw
the same ones; such runs show correctness and accuracy, not privacy.
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ldp_hist.functions import codes, hadamard, hashing
from ldp_hist.functions.encoding import SIX_LETTERS, HashEncoding, TextEncoding, integers
from ldp_hist.functions.randomizers import debias, randomised
from ldp_hist.functions.randomness import assign, coin
from ldp_hist.operators import baselines, hashed_bits, histogram, measures, prefix_tree, sign_matrix_oracle, sketch_oracle
from ldp_hist.plans import bounds, cost, dispatch, duck, privacy
from ldp_hist.plans.params import LN3, TINY, WORDS_SF001, Params, cells_for, experiment, partitioned_small, theory_tree
from ldp_hist.sources.populations import POPULATIONS, line_key, sampled, table
from ldp_hist.streaming import counters as windows

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
P = TINY
PCTLES = [50.0, 75.0, 90.0, 95.0, 99.0, 99.9]
RANKS = [1, 2, 5, 10, 20, 50, 100]
SEEDS = list(range(10))
FLAG_BITS = integers(5)
TWO_LETTERS = TextEncoding(2, 5, 27)
HOST_CODES = HashEncoding(4, 3, 8)
HOST_CODE = f"{duck.sl(duck.dig('item', 0, 'item'), 1, 12)} % 4096"
EPS_GRID, WIDTHS, SHARES = [0.5, 1.0, 2.0, 4.0], [16, 64, 256, 1024, 4096], [10, 30, 100]


def query(name: str, sql: str | None = None):
    def add(f: Callable[[SparkSession, str], DataFrame]):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return add


def population(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return POPULATIONS[name](spark, sf_dir)


def flag_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(line_key().alias("user_key"), (F.ascii("l_returnflag") - 65).cast("string").alias("item"))


def benchmark_words(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "benchmark").select(F.explode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("item")).distinct()


def with_truth(pop: DataFrame, est: DataFrame) -> DataFrame:
    return baselines.exact_frequencies(pop).join(est, "item").select("item", "f", "est")


# --- exact counts, ranks, percentiles --------------------------------------------------------------------------

for _name, _pop in (("exact_returnflag", "flag"), ("exact_hosts", "host")):
    query(_name, duck.exact(_pop))(lambda s, d, pop=_pop: baselines.exact_frequencies(population(s, d, pop)))

for _name, _pop in (("exact_words_top100", "words"), ("exact_word6_top100", "word6")):
    query(_name, f"SELECT row_number() OVER (ORDER BY f DESC, item)::INT AS rank, item, f FROM ({duck.exact(_pop)}) ORDER BY f DESC, item LIMIT 100")(
        lambda s, d, pop=_pop: histogram.top_k(baselines.exact_frequencies(population(s, d, pop)).withColumnRenamed("f", "est"), 100).select("rank", "item", F.col("est").alias("f")))

query("exact_heavy_words", f"SELECT item, f, n::BIGINT AS n FROM ({duck.exact('word6')}), (SELECT count(*) AS n FROM ({duck.POPS['word6']})) WHERE f >= 15 * sqrt(n)")(
    lambda s, d: baselines.exact_heavy_hitters(population(s, d, "word6")).select("item", "f", "n"))

query("word_percentiles", f"""WITH t AS (SELECT item, f, 100.0::DOUBLE * (rank() OVER (ORDER BY f) - 1) / count(*) OVER () AS share FROM ({duck.exact('words')})),
p AS (SELECT unnest({PCTLES})::DOUBLE AS pctle), m AS (SELECT pctle, max(f) AS f FROM t, p WHERE share <= pctle GROUP BY pctle)
SELECT pctle, min(item) AS item, m.f FROM m JOIN t ON t.f = m.f GROUP BY pctle, m.f""")(
    lambda s, d: measures.percentile_items(baselines.exact_frequencies(population(s, d, "words")), PCTLES))

query("word_ranks", f"SELECT rank, item, f FROM (SELECT row_number() OVER (ORDER BY f DESC, item)::BIGINT AS rank, item, f FROM ({duck.exact('words')})) WHERE rank IN {tuple(RANKS)}")(
    lambda s, d: measures.rank_items(baselines.exact_frequencies(population(s, d, "words")), RANKS))

query("distinct_words", f"SELECT count(DISTINCT item)::BIGINT AS words, count(DISTINCT rpad(substr(item, 1, 6), 6, '_'))::BIGINT AS word6 FROM ({duck.POPS['words']})")(
    lambda s, d: population(s, d, "words").select("item").distinct().agg(F.count("*").alias("words"), F.countDistinct(SIX_LETTERS.fit(F.col("item"))).alias("word6")))


@query("distinct_words_approx")
def _(s, d):
    return population(s, d, "words").agg(F.approx_count_distinct("item").alias("words"), F.approx_count_distinct(SIX_LETTERS.fit(F.col("item"))).alias("word6"))


# --- primitives -------------------------------------------------------------------------------------------------

_HD = duck.dig("pair", 42, "j", "n_name")
query("hash_pairs", f"SELECT n_name AS name, j::INT AS j, {duck.sl(_HD, 1, 8)} % 64 AS h, {duck.sgn(_HD, 9)}::INT AS g FROM nation, range(15) r(j)")(
    lambda s, d: table(s, d, "nation").select("n_name", F.explode(F.sequence(F.lit(0), F.lit(14))).alias("j")).select(
        F.col("n_name").alias("name"), "j", hashing.bucket_hash(42, F.col("j"), F.col("n_name"), 64).alias("h"), hashing.sign_hash(42, F.col("j"), F.col("n_name")).alias("g")))

_A, _B = hashing.coefficients(42, "affine", 2)
query("affine_hashes", f"SELECT n_nationkey AS key, ((n_nationkey::BIGINT * {_A} + {_B}) % {hashing.PRIME}) % 64 AS h FROM nation")(
    lambda s, d: table(s, d, "nation").select(F.col("n_nationkey").alias("key"), hashing.affine_hash(42, F.col("n_nationkey"), 64).alias("h")))

_HORNER = "0::BIGINT"
for _c in hashing.coefficients(42, "poly5", 5):
    _HORNER = f"(({_HORNER} * n_nationkey::BIGINT + {_c}) % {hashing.PRIME})"
query("poly_hashes", f"SELECT n_nationkey AS key, {_HORNER} % 64 AS h FROM nation")(
    lambda s, d: table(s, d, "nation").select(F.col("n_nationkey").alias("key"), hashing.poly_hash(42, F.col("n_nationkey"), 64, 5).alias("h")))

_DEGREE, _HORNER = bounds.hash_degree(25, 0.05), "0::BIGINT"
for _c in hashing.coefficients(42, f"poly{_DEGREE}", _DEGREE):
    _HORNER = f"(({_HORNER} * n_nationkey::BIGINT + {_c}) % {hashing.PRIME})"
query("poly_hashes_of_degree", f"SELECT n_nationkey AS key, {_HORNER} % 64 AS h FROM nation")(
    lambda s, d: table(s, d, "nation").select(F.col("n_nationkey").alias("key"), hashing.poly_hash(42, F.col("n_nationkey"), 64, _DEGREE).alias("h")))


def sixteenths(s: SparkSession, d: str) -> DataFrame:
    """A row and a column of the sign matrix for every order line: its order's and its part's."""
    return table(s, d, "lineitem").select((F.col("l_orderkey") % 16).alias("r"), (F.col("l_partkey") % 16).alias("c"))


_SIXTEENTHS = "SELECT l_orderkey % 16 AS r, l_partkey % 16 AS c FROM lineitem"
query("hadamard_matrix", f"SELECT r, c, {duck.had('r', 'c')}::INT AS w, count(*)::BIGINT AS users FROM ({_SIXTEENTHS}) GROUP BY ALL")(
    lambda s, d: sixteenths(s, d).groupBy("r", "c", hadamard.had_sign(F.col("r"), F.col("c")).alias("w")).agg(F.count("*").alias("users")))

query("hadamard_orthogonality", f"""WITH x AS MATERIALIZED ({_SIXTEENTHS}), c AS (SELECT DISTINCT c FROM x)
SELECT a.c AS c1, b.c AS c2, sum({duck.had('r', 'a.c')} * {duck.had('r', 'b.c')})::BIGINT AS inner_product FROM (SELECT DISTINCT r FROM x), c a, c b GROUP BY 1, 2""")(
    lambda s, d: (lambda x: x.select("r").distinct().crossJoin(x.select(F.col("c").alias("c1")).distinct()).crossJoin(x.select(F.col("c").alias("c2")).distinct()))(sixteenths(s, d))
    .groupBy("c1", "c2").agg(F.sum(hadamard.had_sign(F.col("r"), F.col("c1")) * hadamard.had_sign(F.col("r"), F.col("c2"))).alias("inner_product")))

query("user_assignment", f"WITH pop AS ({duck.POPS['priority']}) SELECT user_key::BIGINT AS o_orderkey, level, pair, row_ AS \"row\", subset FROM ({duck.own(P, L=6)})")(
    lambda s, d: assign(population(s, d, "priority"), 42, levels=6, t=P.t, m=P.m, subsets=P.R).select(F.col("user_key").cast("long").alias("o_orderkey"), "level", "pair", "row", "subset"))

query("assignment_balance", f"""WITH pop AS ({duck.POPS['priority']}), n AS (SELECT count(*) / 90.0::DOUBLE AS mean FROM pop)
SELECT level, pair, count(*)::BIGINT AS users, count(*) BETWEEN any_value(mean) / 2 AND any_value(mean) * 2 AS in_band FROM ({duck.own(P, L=6)}), n GROUP BY level, pair""")(
    lambda s, d: (lambda pop: assign(pop, 42, levels=6, t=P.t).groupBy("level", "pair").agg(F.count("*").alias("users")).join(F.broadcast(pop.agg((F.count("*") / 90).alias("mean"))))
                  .select("level", "pair", "users", F.col("users").between(F.col("mean") / 2, F.col("mean") * 2).alias("in_band")))(population(s, d, "priority")))

query("encode_words", f"SELECT DISTINCT item, ({duck.text_code('item', 6)})::BIGINT AS code FROM ({duck.POPS['word6']})")(
    lambda s, d: population(s, d, "word6").select("item").distinct().select("item", SIX_LETTERS.encode(F.col("item")).alias("code")))

query("prefixes_words", f"""SELECT level::INT AS level, (code >> (5 * (6 - level))::INT) AS prefix, count(*)::BIGINT AS f
FROM (SELECT ({duck.text_code('item', 6)})::BIGINT AS code FROM ({duck.POPS['word6']})), range(1, 7) r(level) GROUP BY ALL""")(
    lambda s, d: baselines.exact_frequencies(population(s, d, "word6")).select("f", SIX_LETTERS.encode(F.col("item")).alias("code"), F.explode(F.sequence(F.lit(1), F.lit(6))).alias("level"))
    .groupBy("level", SIX_LETTERS.prefix(F.col("code"), F.col("level")).alias("prefix")).agg(F.sum("f").alias("f")))

query("child_set", "SELECT n_nationkey::BIGINT AS prefix, n_nationkey::BIGINT * 32 + i AS child FROM nation, range(27) r(i)")(
    lambda s, d: SIX_LETTERS.children(table(s, d, "nation").select(F.col("n_nationkey").cast("long").alias("prefix"))).select(F.floor(F.col("prefix") / 32).cast("long").alias("prefix"), F.col("prefix").alias("child")))


def flags(eps: float, kind: str = "binary") -> tuple[str, Callable]:
    x = "(2 * item::INT - 1)"
    sql = f"SELECT user_key::BIGINT AS doc_id, {x} AS x, {duck.flip(x, eps, 1, kind=kind)}::INT AS z FROM ({duck.POPS['toxic']})"

    def run(s, d):
        pop = population(s, d, "toxic").select(F.col("user_key").cast("long").alias("doc_id"), (2 * F.col("item").cast("int") - 1).alias("x"), "user_key")
        return pop.select("doc_id", "x", randomised(F.col("x"), eps, coin(1, F.col("user_key"), P.coins), kind).alias("z"))

    return sql, run


for _name, _how in (("binary_rr_flags", (2.0,)), ("half_budget_rr", (1.0,)), ("linear_rr_flags", (0.5, "linear"))):
    _sql, _run = flags(*_how)
    query(_name, _sql)(_run)

_LAP = f"(({duck.sl(duck.dig('lap', 42, 'item'), 1, 13)} + 0.5::DOUBLE) / 4503599627370496.0::DOUBLE - 0.5::DOUBLE)"
_LAPLACE = f"SELECT item, f, round(f + (-(2 / {{eps}}) * sign({_LAP}) * ln(1 - 2 * abs({_LAP}))), 4) AS est FROM ({{exact}})"


def _survey(s: SparkSession, d: str) -> DataFrame:
    z = QUERIES["binary_rr_flags"](s, d).agg(F.round(F.avg((F.col("x") + 1) / 2), 6).alias("true_mean"), F.round((F.lit(debias(2.0)) * F.avg("z") + 1) / 2, 6).alias("local_estimate"))
    noisy = baselines.curator_laplace(population(s, d, "toxic"), 2.0)
    curator = noisy.agg(F.round(F.sum(F.when(F.col("item") == "1", F.col("est"))) / F.sum("f"), 6).alias("curator_estimate"))
    return z.join(curator)


query("survey_mean_toxic", f"""WITH z AS ({ORACLES['binary_rr_flags']}), c AS ({_LAPLACE.format(eps='2.0::DOUBLE', exact=duck.exact('toxic'))})
SELECT round(avg((x + 1) / 2), 6) AS true_mean, round(({duck.num(debias(2.0))} * avg(z) + 1) / 2, 6) AS local_estimate,
  (SELECT round(sum(est) FILTER (item = '1') / sum(f), 6) FROM c) AS curator_estimate FROM z""")(_survey)

query("curator_laplace_segment", _LAPLACE.format(eps="2.0::DOUBLE", exact=duck.exact("segment")))(lambda s, d: baselines.curator_laplace(population(s, d, "segment"), 2.0))

# --- the sketch oracle -------------------------------------------------------------------------------------------


def count_sketch_sql(pop: str) -> str:
    hd = duck.dig("pair", 42, "pair", "item")
    return f"""WITH t AS MATERIALIZED ({duck.exact(pop)}),
x AS MATERIALIZED (SELECT item, f, pair, {duck.sl('hd', 1, 8)} % {P.m} AS h, {duck.sgn('hd', 9)} AS g FROM (SELECT *, {hd} AS hd FROM (SELECT item, f, i AS pair FROM t, range({P.t}) r(i)))),
c AS (SELECT pair, h, sum(f * g)::BIGINT AS v FROM x GROUP BY ALL)
SELECT item, any_value(f) AS f, round(median(g * v), 4) AS est FROM x JOIN c USING (pair, h) GROUP BY item"""


for _name, _pop in (("count_sketch_returnflag", "flag"), ("count_sketch_words", "words")):
    query(_name, count_sketch_sql(_pop))(lambda s, d, pop=_pop: (lambda x: with_truth(x, sketch_oracle.count_sketch(x, x.select("item").distinct(), P)))(population(s, d, pop)))



_PRIORITY = integers(3)
_PCODE = "substr(item, 1, 1)::BIGINT"


def priority_codes(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").select(F.col("o_orderkey").cast("string").alias("user_key"), F.substring("o_orderpriority", 1, 1).alias("item"))


_H1 = duck.dig("pair", 42, "pair", "concat_ws('.', level, (code >> (3 - level)::INT))")
_H2 = duck.dig("pair", 42, "pair", "concat_ws('.', 3, code)")
_Y1 = duck.flip(f"{duck.sgn('h1', 9)} * {duck.had('row_', f'{duck.sl(chr(104) + chr(49), 1, 8)} % {P.m}')}", 1.0, 1)
_Y2 = duck.flip(f"{duck.sgn('h2', 9)} * {duck.had('row_', f'{duck.sl(chr(104) + chr(50), 1, 8)} % {P.m}')}", 1.0, 2)
query("sketch_reports", f"""WITH pop AS ({duck.POPS['priority']}) SELECT user_key::BIGINT AS user, level, pair, row_ AS "row", {_Y1}::INT AS y1, {_Y2}::INT AS y2
FROM (SELECT *, {_H1} AS h1, {_H2} AS h2 FROM (SELECT *, {_PCODE} AS code FROM ({duck.own(P, L=3)})))""")(
    lambda s, d: sketch_oracle.tree_reports(priority_codes(s, d), P, _PRIORITY, keep_user=True).select(F.col("user_key").cast("long").alias("user"), "level", "pair", "row", "y1", "y2"))

query("sketch_counters", f"""WITH r AS ({ORACLES['sketch_reports']}) SELECT level, pair, "row", sum(y1)::BIGINT AS s FROM r GROUP BY ALL""")(
    lambda s, d: sketch_oracle.count(sketch_oracle.tree_reports(priority_codes(s, d), P, _PRIORITY), ["level", "pair", "row"], "y1"))


def known(name: str, pop: str, p: Params = P, mode: str = "transform", **how):
    def run(s, d):
        x = population(s, d, pop)
        return with_truth(x, sketch_oracle.dictionary_frequencies(x, x.select("item").distinct(), p, mode=mode, **how))

    return query(name, duck.dictionary(pop, p))(run)


known("sketch_direct_priority", "priority", mode="direct")
known("sketch_presummed_priority", "priority", mode="counters")
known("sketch_freq_priority", "priority")
for _n in ("returnflag:flag", "quantity:quantity", "brand:brand", "words_known:words"):
    known(f"sketch_freq_{_n.split(':')[0]}", _n.split(":")[1])
known("sketch_freq_prop", "prop")
query("json_prop_freq", f"SELECT item AS k, f, est FROM ({ORACLES.pop('sketch_freq_prop')})")(lambda s, d, run=QUERIES.pop("sketch_freq_prop"): run(s, d).withColumnRenamed("item", "k"))

query("sketch_transform_cells", f"""WITH {duck.dictionary_ctes('priority', P)}
SELECT pair, cell, sum(s * {duck.had('row_', 'cell')})::BIGINT AS v FROM cnt, range({P.m}) r(cell) GROUP BY ALL""")(
    lambda s, d: hadamard.fwht_groups(sketch_oracle.count(sketch_oracle.dictionary_reports(population(s, d, "priority"), P), ["pair", "row"]), ["pair"], "row", P.m))

query("sketch_mean_combine", f"WITH {duck.dictionary_ctes('flag', P)} SELECT item, round({duck.num(P.t * debias(P.eps))} * (sum(v)::DOUBLE / {P.t}), 4) AS est FROM sums GROUP BY item")(
    lambda s, d: (lambda x: sketch_oracle.dictionary_frequencies(x, x.select("item").distinct(), P, combine="mean"))(population(s, d, "flag")))

_W16, _STATUS = P.but(m=16), "SELECT o_orderkey::VARCHAR AS user_key, o_orderstatus AS item FROM orders"


def whole_row_sql(source: str, p: Params) -> str:
    hd, blocks = duck.dig("pair", 42, "pair", "item"), f"range({max(1, p.m // 256)}) k(block), range({min(256, p.m)}) r(spot)"
    return f"""(WITH pop AS MATERIALIZED ({source}),
x AS MATERIALIZED (SELECT user_key, pair, {duck.sl('hd', 1, 8)} % {p.m} AS h, {duck.flip(duck.sgn('hd', 9), p.eps, 1)} AS said FROM (SELECT *, {hd} AS hd FROM ({duck.own(p)}))),
y AS (SELECT pair, block * 256 + spot AS cell, CASE WHEN block * 256 + spot = h THEN said ELSE 1 - 2 * (({duck.sl('row_d', '(spot // 4 + 1)::INT', 1)} >> (spot % 4)::INT) & 1) END AS y
  FROM (SELECT *, {duck.dig('row', 42, 'user_key', 'block')} AS row_d FROM x, {blocks})),
v AS (SELECT pair, cell, sum(y)::BIGINT AS v FROM y GROUP BY ALL),
q AS (SELECT item, pair, {duck.sl('hd', 1, 8)} % {p.m} AS cell, {duck.sgn('hd', 9)} AS g FROM (SELECT *, {hd} AS hd FROM (SELECT DISTINCT item, i AS pair FROM pop, range({p.t}) r(i))))
SELECT item, round({duck.num(p.t * debias(p.eps))} * median(g * coalesce(v, 0)), 4) AS est FROM q LEFT JOIN v USING (pair, cell) GROUP BY item)"""


def statuses(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "orders").select(F.col("o_orderkey").cast("string").alias("user_key"), F.col("o_orderstatus").alias("item"))


query("sketch_uncompressed_status", f"SELECT * FROM {whole_row_sql(_STATUS, _W16)}")(lambda s, d: (lambda x: sketch_oracle.whole_row_estimates(x, x.select("item").distinct(), _W16))(statuses(s, d)))

duck.POPS["status_orders"] = _STATUS
_WIDE = P.but(t=285, m=128)
query("compression_compare", f"""SELECT c.item, c.f, c.est AS compressed, w.est AS uncompressed FROM ({duck.dictionary('status_orders', _WIDE)}) c JOIN {whole_row_sql(_STATUS, _WIDE)} w USING (item)""")(
    lambda s, d: (lambda x: with_truth(x, sketch_oracle.dictionary_frequencies(x, x.select("item").distinct(), _WIDE)).withColumnRenamed("est", "compressed")
                  .join(sketch_oracle.whole_row_estimates(x, x.select("item").distinct(), _WIDE).withColumnRenamed("est", "uncompressed"), "item"))(statuses(s, d)))

# --- sign-matrix and partitioned oracles ----------------------------------------------------------------------------


def matrix_sql(pop: str, family: str = "sha", eps: float = 2.0, kind: str = "binary") -> str:
    def z(x: str) -> str:
        if family == "sha":
            return duck.sgn(duck.dig("z", 42, x, "user_key"), 1)
        if family == "linear":
            d = duck.dig("lin", 42, "user_key")
            return f"({duck.had(f'{duck.sl(duck.dig("key", 42, x), 1, 8)} + 1', duck.sl(d, 1, 8))} * {duck.sgn(d, 9)})"
        u, value = f"({duck.sl(duck.dig('usr', 42, 'user_key'), 1, 8)} % {hashing.PRIME})", "0::BIGINT"
        for i in range(2 if family == "affine" else sign_matrix_oracle.DEGREE):
            value = f"(({value} * {u} + {duck.sl(duck.dig(family, 42, x), 1 + 8 * i, 8)} % {hashing.PRIME}) % {hashing.PRIME})"
        return f"(1 - 2 * ({value} % 2))"

    return f"""WITH pop AS MATERIALIZED ({duck.POPS[pop]}), t AS (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item),
rep AS MATERIALIZED (SELECT user_key, {duck.flip(z('item'), eps, 1, kind=kind)} AS y FROM pop),
e AS (SELECT t.item AS it, any_value(f) AS f, sum(y * {z('t.item')})::BIGINT AS v FROM rep, t GROUP BY t.item)
SELECT it AS item, f, round({duck.num(debias(eps, kind))} * v, 4) AS est FROM e"""


def matrix_run(pop: str, family: str = "sha", eps: float = 2.0, kind: str = "binary"):
    return lambda s, d: (lambda x: with_truth(x, sign_matrix_oracle.plain_estimates(x, x.select("item").distinct(), P.but(eps=eps), family, kind)))(population(s, d, pop))


query("signmatrix_freq_priority", matrix_sql("priority"))(matrix_run("priority"))
query("signmatrix_linear_rr", matrix_sql("priority", "sha", 0.5, "linear"))(matrix_run("priority", "sha", 0.5, "linear"))
_FAMILIES = ("sha", "affine", "poly", "linear")
query("signmatrix_families", " UNION ALL ".join(f"SELECT item, '{k}' AS family, est FROM ({matrix_sql('segment', k)})" for k in _FAMILIES))(
    lambda s, d: _union([matrix_run("segment", k)(s, d).select("item", F.lit(k).alias("family"), "est") for k in _FAMILIES]))
query("predecessor_priority", matrix_sql("priority"))(lambda s, d: (lambda x: with_truth(x, baselines.predecessor(x, x.select("item").distinct(), P)))(population(s, d, "priority")))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


query("partitioned_counters", f"WITH pop AS MATERIALIZED ({duck.POPS['segment']}), {duck.partitioned_ctes('SELECT * FROM pop', P, P.eps)} SELECT subset, col, s FROM pcnt")(
    lambda s, d: sign_matrix_oracle.partitioned_counters(sign_matrix_oracle.partitioned_reports(population(s, d, "segment"), P)))


def partitioned(name: str, pop: str, mode: str = "transform", f: bool = True):
    truth = "t.f, " if f else ""
    sql = f"""WITH pop AS MATERIALIZED ({duck.POPS[pop]}), {duck.partitioned_ctes('SELECT * FROM pop', P, P.eps)}
SELECT t.item, {truth}e.est FROM (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item) t JOIN pest e USING (item)"""
    return query(name, sql)(lambda s, d: (lambda x: with_truth(x, sign_matrix_oracle.partitioned_estimates(x, x.select("item").distinct(), P, mode)))(population(s, d, pop)))


partitioned("partitioned_freq_segment", "segment")
partitioned("partitioned_direct_segment", "segment", "direct")
partitioned("partitioned_presummed_segment", "segment", "counters")
partitioned("partitioned_freq_quantity", "quantity")
query("full_histogram_nation", f"""WITH pop AS MATERIALIZED ({duck.POPS['nation']}), {duck.partitioned_ctes('SELECT * FROM pop', P, P.eps, items='SELECT n_name AS item FROM nation')}
SELECT item AS n_name, est FROM pest""")(
    lambda s, d: sign_matrix_oracle.full_histogram(population(s, d, "nation"), table(s, d, "nation").select(F.col("n_name").alias("item")), P).select(F.col("item").alias("n_name"), "est"))

# --- the prefix tree ---------------------------------------------------------------------------------------------------


def tree(name: str, pop: str, p: Params, encoding, code: str, decode: str, factor: float = 15.0, run_pop: Callable | None = None, item: Callable[[Column], Column] | None = None, truth: bool = False, beam: int | None = None):
    ctes = duck.tree_ctes(pop, p, code, encoding.levels, encoding.bits, encoding.symbols, factor, beam)
    sql = f"WITH {ctes} SELECT {decode} AS item, est FROM hist"
    if truth:
        sql = f"WITH {ctes}, t AS (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item) SELECT h.item, h.est, coalesce(t.f, 0)::BIGINT AS f FROM (SELECT {decode} AS item, est FROM hist) h LEFT JOIN t USING (item)"

    def run(s, d):
        x = run_pop(s, d) if run_pop else population(s, d, pop)
        out = prefix_tree.tree_heavy_hitters(x, p, encoding, factor, beam=beam)
        out = out.select((item(F.col("code")) if item else F.col("item")).alias("item"), "est")
        return measures.against(baselines.exact_frequencies(x), out, "right").select("item", "est", "f") if truth else out

    return query(name, sql)(run)


def letter(code: Column) -> Column:
    return F.char(code + 65)


tree("tree_hh_returnflag", "flagcode", P, FLAG_BITS, "item::BIGINT", "chr((code + 65)::INT)", run_pop=flag_codes, item=letter)
tree("tree_hh_lang", "lang", P, TWO_LETTERS, duck.text_code("item", 2), duck.text_decode("code", 2))
tree("tree_binary_quantity", "quantity", P, integers(6), "item::BIGINT", "code::VARCHAR")
tree("tree_hh_powerlaw", "powerlaw6", WORDS_SF001, SIX_LETTERS, duck.text_code("item", 6), duck.text_decode("code", 6), truth=True)
tree("tree_hh_words", "word6", WORDS_SF001, SIX_LETTERS, duck.text_code("item", 6), duck.text_decode("code", 6), truth=True)
tree("beam_hh_words", "word6", WORDS_SF001, SIX_LETTERS, duck.text_code("item", 6), duck.text_decode("code", 6), beam=8)

query("tree_hh_host", f"WITH {duck.tree_ctes('host', P, HOST_CODE, 4, 3, 8, 8.0)} SELECT i.item, h.est FROM hist h JOIN (SELECT DISTINCT item, {HOST_CODE} AS code FROM pop) i USING (code)")(
    lambda s, d: (lambda x: HOST_CODES.name_codes(prefix_tree.tree_heavy_hitters(x, P, HOST_CODES, 8.0).select("code", "est"), x).select("item", "est"))(population(s, d, "host")))

_EVENT = duck.tree_ctes("event", P, duck.text_code("item", 6), 6, 5, 27, 15.0)
query("tree_candidates_event", f"WITH {_EVENT} {duck.trace(6)}")(
    lambda s, d: prefix_tree.tree_trace(prefix_tree.tree_candidates(population(s, d, "event"), P, SIX_LETTERS)))
_LANG = duck.tree_ctes("lang", P, duck.text_code("item", 2), 2, 5, 27, 15.0)
query("tree_trace_lang", f"WITH {_LANG} {duck.trace(2)}")(
    lambda s, d: prefix_tree.tree_trace(prefix_tree.tree_candidates(population(s, d, "lang"), P, TWO_LETTERS)))
query("tree_node_queries", f"WITH {_EVENT} SELECT level, count(*)::BIGINT AS queried, sum(kept::INT)::BIGINT AS kept FROM ({duck.trace(6)}) GROUP BY ROLLUP (level)")(
    lambda s, d: prefix_tree.node_queries(QUERIES["tree_candidates_event"](s, d)))

_BRUTE = WORDS_SF001


def _first_two(s: SparkSession, d: str) -> DataFrame:
    return population(s, d, "words").select("user_key", TWO_LETTERS.fit(F.col("item")).alias("item"))


duck.POPS["word2"] = f"SELECT user_key, concat_ws('.', 2, {duck.text_code('item', 2)}) AS item FROM ({duck.POPS['words']})"
_LETTER2 = "SELECT concat_ws('.', 2, a * 32 + b) AS item FROM range(27) x(a), range(27) y(b)"
query("brute_force_letters2", f"""WITH {duck.dictionary_ctes('word2', _BRUTE).replace('items AS (SELECT DISTINCT  item FROM pop)', f'items AS ({_LETTER2})')}
SELECT {duck.text_decode('substr(item, 3)::BIGINT', 2)} AS item, est FROM est WHERE est >= 15 * sqrt((SELECT count(*) FROM pop))""")(
    lambda s, d: prefix_tree.brute_force(_first_two(s, d), _BRUTE, TWO_LETTERS).select("item", "est"))

# --- bit by bit -----------------------------------------------------------------------------------------------------------

_FLAGBIT = "(code >> (4 - bit)) & 1"
_CELLS = duck.bit_ctes("flagcode", P, "item::BIGINT", _FLAGBIT, 5)
query("hashed_bits_cells", f"WITH {_CELLS} SELECT cell, bit, value FROM best")(
    lambda s, d: hashed_bits.warm_up_cells(flag_codes(s, d), P, FLAG_BITS).select("cell", "bit", "value"))


def found_sql(ctes: str, word: str, decode: str, floor: bool = False, p: Params = P) -> str:
    final = duck.partitioned_ctes("SELECT user_key, code::VARCHAR AS item FROM pop", p, p.eps / 2, 2, items="SELECT DISTINCT code::VARCHAR AS item FROM words")
    where = " WHERE est > sqrt((SELECT count(*) FROM pop))" if floor else ""
    return f"WITH {ctes}, words AS ({word}), {final} SELECT item::BIGINT AS code, {decode} AS item, est FROM (SELECT item, item::BIGINT AS code, est FROM pest){where}"


_ASSEMBLE = "SELECT rep, cell, sum(value::BIGINT << (4 - bit))::BIGINT AS code FROM best GROUP BY ALL"
query("hashed_bits_returnflag", found_sql(_CELLS, _ASSEMBLE, "chr((code + 65)::INT)"))(
    lambda s, d: hashed_bits.warm_up(flag_codes(s, d), P, FLAG_BITS).select("code", letter(F.col("code")).alias("item"), "est"))
query("hashed_bits_repeat", found_sql(duck.bit_ctes("flagcode", P, "item::BIGINT", _FLAGBIT, 5, 3), _ASSEMBLE, "chr((code + 65)::INT)"))(
    lambda s, d: hashed_bits.warm_up(flag_codes(s, d), P, FLAG_BITS, repeats=3).select("code", letter(F.col("code")).alias("item"), "est"))


def votes(width: int, repeats: int = 1, T: int = P.T) -> str:
    """Messages by majority of the copies of each bit that were read; a word of which no bit was read has none."""
    return f"""SELECT rep, cell, sum((vote > 0)::BIGINT << ({width - 1} - b)::INT)::BIGINT AS code FROM (
  SELECT g.rep, g.cell, b, coalesce(sum(2 * value - 1), 0) AS vote, count(value) AS known FROM (SELECT rep, cell, b FROM range({repeats}) r(rep), range({T}) c(cell), range({width}) w(b)) g
  LEFT JOIN best ON best.rep = g.rep AND best.cell = g.cell AND best.bit % {width} = g.b GROUP BY ALL) GROUP BY rep, cell HAVING sum(known) > 0"""


_P4 = P.but(eps=4.0)
query("coded_bits_returnflag_repeat3", found_sql(duck.bit_ctes("flagcode", P, "item::BIGINT", "(code >> (4 - bit % 5)::INT) & 1", 15, 3, 3), votes(5, 3), "chr((code + 65)::INT)", True))(
    lambda s, d: hashed_bits.coded(flag_codes(s, d), P, FLAG_BITS, "repeat3").select("code", letter(F.col("code")).alias("item"), "est"))
query("coded_bits_lang_repeat3", found_sql(duck.bit_ctes("lang", _P4, duck.text_code("item", 2), "(code >> (9 - bit % 10)::INT) & 1", 30, 1, 1), votes(10), duck.text_decode("code", 2), True, _P4))(
    lambda s, d: hashed_bits.coded(population(s, d, "lang"), _P4, TWO_LETTERS, "repeat3", 1, 1).select("code", "item", "est"))
query("coded_bits_uncoded", found_sql(_CELLS, votes(5), "chr((code + 65)::INT)"))(
    lambda s, d: hashed_bits.coded(flag_codes(s, d), P, FLAG_BITS, "none", 1, 1, floor="none").select("code", letter(F.col("code")).alias("item"), "est"))
query("assisted_bits_returnflag", found_sql(duck.bit_ctes("flagcode", P, "item::BIGINT", "(code >> (4 - bit % 5)::INT) & 1", 15), votes(5), "chr((code + 65)::INT)"))(
    lambda s, d: hashed_bits.assisted_warm_up(flag_codes(s, d), P, FLAG_BITS).select("code", letter(F.col("code")).alias("item"), "est"))


def words_read(name: str, pop: str, p: Params, encoding, code: str, kind: str, repeats: int, inner: int) -> None:
    """The words read off all cells under a code, -1 for bits that nobody was dealt to."""
    c = codes.Code(kind, encoding.width)
    bit = f"bit_count(code & list_extract({c.masks()}, (bit + 1)::INT)) % 2"
    sql = f"""WITH {duck.bit_ctes(pop, p, code, bit, c.length, repeats, inner)}
SELECT g.rep::INT AS rep, g.cell, string_agg(coalesce(value, -1)::VARCHAR, ' ' ORDER BY g.bit) AS word FROM (SELECT rep, cell, bit FROM range({repeats}) r(rep), range({p.T}) c(cell), range({c.length}) b(bit)) g
LEFT JOIN best ON best.rep = g.rep AND best.cell = g.cell AND best.bit = g.bit GROUP BY ALL"""
    query(name, sql)(lambda s, d: hashed_bits.coded_words(population(s, d, pop), p, encoding, c, repeats, inner).select("rep", "cell", F.array_join(F.transform("word", lambda x: x.cast("string")), " ").alias("word")))


_T16 = _P4.but(T=16)
words_read("coded_words_lang", "lang", _T16, TWO_LETTERS, duck.text_code("item", 2), "concat", 3, 3)
words_read("coded_words_six_letters", "word6", _T16, SIX_LETTERS, duck.text_code("item", 6), "concat", 3, 3)


@query("coded_bits_returnflag")
def _(s, d):
    return hashed_bits.coded(flag_codes(s, d), _P4, FLAG_BITS, "concat", 1, 1).select("code", letter(F.col("code")).alias("item"), "est")


@query("coded_bits_lang")
def _(s, d):
    return hashed_bits.coded(population(s, d, "lang"), _T16.but(eps=8.0), TWO_LETTERS, "concat", 3, 3).select("code", "item", "est")


@query("coded_bits_six_letters")
def _(s, d):
    return hashed_bits.coded(population(s, d, "word6"), _T16.but(eps=8.0), SIX_LETTERS, "concat", 3, 3).select("code", "item", "est")


_SIMPLE, _FULL = ORACLES["hashed_bits_returnflag"], ORACLES["coded_bits_returnflag_repeat3"]
query("simple_against_full", f"SELECT coalesce(s.item, f.item) AS item, s.est AS simple, f.est AS full_form FROM ({_SIMPLE}) s FULL JOIN ({_FULL}) f ON s.item = f.item")(
    lambda s, d: QUERIES["hashed_bits_returnflag"](s, d).select("item", F.col("est").alias("simple")).join(QUERIES["coded_bits_returnflag_repeat3"](s, d).select("item", F.col("est").alias("full_form")), "item", "full"))

# The 25 nations as users and their region as the item: few enough for a cell of their own for every pair of users.
_NATIONS, _REGION = 25, integers(3)
duck.POPS["region"] = "SELECT n_nationkey::VARCHAR AS user_key, n_regionkey::VARCHAR AS item FROM nation"
_REGIMES = [(kind, cells_for(_NATIONS, kind), 3 if kind == "sqrt" else 1) for kind in ("sqrt", "n", "n2")]


def regions(s: SparkSession, d: str) -> DataFrame:
    return table(s, d, "nation").select(F.col("n_nationkey").cast("string").alias("user_key"), F.col("n_regionkey").cast("string").alias("item"))


def region_sql(T: int, repeats: int, final_T: int) -> str:
    word = "SELECT rep, cell, sum(value::BIGINT << (2 - bit))::BIGINT AS code FROM best GROUP BY ALL"
    return found_sql(duck.bit_ctes("region", _P4.but(T=T), "item::BIGINT", "(code >> (2 - bit)) & 1", 3, repeats), word, "code::VARCHAR", p=_P4.but(T=final_T))


query("collision_regimes", " UNION ALL ".join(f"SELECT '{kind}' AS regime, {T}::INT AS cells, code, est FROM ({region_sql(T, repeats, T)})" for kind, T, repeats in _REGIMES))(
    lambda s, d: _union([hashed_bits.regime(regions(s, d), _P4, _REGION, kind, _NATIONS, repeats).select(F.lit(kind).alias("regime"), F.lit(T).alias("cells"), "code", "est") for kind, T, repeats in _REGIMES]))
query("predecessor_discovery", f"SELECT code, est FROM ({region_sql(cells_for(_NATIONS, 'n2'), 1, P.T)})")(
    lambda s, d: hashed_bits.discover_predecessor(regions(s, d), _P4, _REGION, _NATIONS).select("code", "est"))


_CODE30 = codes.Code("concat", 30)


def roundtrips(s: SparkSession, d: str) -> DataFrame:
    """Each nation's message encoded, hit in as many places as the code always corrects (or none), and decoded."""
    message = (F.col("n_nationkey").cast("long") * 2654435761 + 12345) % (1 << 30)
    rows = table(s, d, "nation").select("n_name", "n_nationkey", message.alias("message"), F.explode(F.array(F.lit(0), F.lit(_CODE30.corrects))).alias("flips"))
    word = hashed_bits.encoded(F.col("message"), _CODE30)
    # 193 is a prime above the length, so the places that are hit are as many as asked for, or one fewer.
    noisy = F.transform(word, lambda bit, i: F.when((i * 7919 + F.col("n_nationkey") * 104729) % 193 < F.col("flips"), 1 - bit).otherwise(bit))
    return rows.select(F.col("n_name").alias("item"), "flips", (hashed_bits.decoder(_CODE30)(noisy) == F.col("message")).alias("equal"))


query("code_roundtrip", f"SELECT n_name AS item, flips::INT AS flips, TRUE AS equal FROM nation, (SELECT unnest([0, {_CODE30.corrects}]) AS flips)")(roundtrips)


# --- other baselines ------------------------------------------------------------------------------------------------------

_BEL, _BLOCKS = math.floor(baselines.bloom_flip(LN3.eps) * (1 << 16)), -(-baselines.BITS // 16)
_BSET = [f"{duck.sl(duck.dig('bloom', 42, 'cohort', str(i), 'item'), 1, 8)} % {baselines.BITS}" for i in range(baselines.HASHES)]


def bloom_sql(pop: str) -> str:
    flips = ", ".join(f"{duck.dig('flip', 42, str(k), 'user_key')} AS d{k}" for k in range(_BLOCKS))
    digit = "CASE " + " ".join(f"WHEN bit < {16 * k + 16} THEN d{k}" for k in range(_BLOCKS)) + " END"
    flipped = f"({duck.sl('(' + digit + ')', '(1 + 4 * (bit % 16))::INT', 4)} < {_BEL})"
    return f"""WITH x AS MATERIALIZED (SELECT cohort, {', '.join(f'd{k}' for k in range(_BLOCKS))}, {', '.join(f'{b} AS p{i}' for i, b in enumerate(_BSET))} FROM
  (SELECT item, ({duck.sl(duck.dig('coh', 42, 'user_key'), 1, 8)} % {baselines.COHORTS})::INT AS cohort, {flips} FROM ({duck.POPS[pop]})))
SELECT cohort, bit::INT AS bit, sum(((p0 = bit OR p1 = bit) <> {flipped})::INT)::BIGINT AS s, count(*)::BIGINT AS n FROM x, range({baselines.BITS}) r(bit) GROUP BY cohort, bit"""


def bloom_decode_sql(pop: str) -> str:
    k = baselines.bloom_constants(LN3.eps)
    places = ", ".join(f"({b})::INT" for b in _BSET)
    return f"""WITH b AS MATERIALIZED ({bloom_sql(pop)}),
a AS (SELECT item, cohort, unnest(list_distinct([{places}])) AS bit FROM (SELECT DISTINCT item FROM ({duck.POPS[pop]})), range({baselines.COHORTS}) r(cohort)),
c AS (SELECT a.item, a.cohort, avg((((s - {duck.num(k['q'])} * n) / {duck.num(1 - 2 * k['q'])}) - {duck.num(k['q0'])} * n) / {duck.num(1 - k['q0'])}) AS users, any_value(n) * {duck.num(k['spread'])} / count(*) AS variance
  FROM a JOIN b ON a.cohort = b.cohort AND a.bit = b.bit GROUP BY a.item, a.cohort)
SELECT item, CASE WHEN sum(users) >= 3 * sqrt(sum(variance)) THEN round(sum(users), 4) ELSE 0 END::DOUBLE AS est FROM c GROUP BY item"""


query("bloom_report_counts", bloom_sql("word6"))(lambda s, d: baselines.bloom_reports(population(s, d, "word6"), LN3))
query("bloom_decode", bloom_decode_sql("word6"))(lambda s, d: (lambda x: baselines.bloom_decode(baselines.bloom_reports(x, LN3), x.select("item").distinct(), LN3))(population(s, d, "word6")))


@query("bloom_refined")
def _(s, d):
    x = population(s, d, "powerlaw")
    reports = baselines.bloom_reports(x, LN3).persist()
    return baselines.bloom_refine(reports, baselines.bloom_decode(reports, x.select("item").distinct(), LN3), LN3)


def ln3(s: SparkSession, d: str, pop: str) -> DataFrame:
    """The whole dictionary, rare items included: f, the sketch's estimate (0 for less), the Bloom reports' and the rank.

    Every item of the truth has both estimates, so ranks come from the truth, which is kept, and the estimates are made once.
    """
    x = population(s, d, pop)
    truth = baselines.exact_frequencies(x).persist()
    ours = sketch_oracle.dictionary_frequencies(x, truth, LN3).withColumnRenamed("est", "sketch")
    bloom = baselines.bloom_decode(baselines.bloom_reports(x, LN3), truth, LN3).withColumnRenamed("est", "bloom")
    return truth.join(F.broadcast(measures.ranks(truth)), "f").join(ours, "item").join(bloom, "item").select("item", "f", "sketch", "bloom", "rank")


def ln3_sql(pop: str) -> str:
    return f"SELECT d.item, d.f, d.est AS sketch, b.est AS bloom FROM ({duck.dictionary(pop, LN3)}) d JOIN ({bloom_decode_sql(pop)}) b USING (item)"


query("baseline_ln3", f"SELECT *, (rank() OVER (ORDER BY f DESC))::BIGINT AS rank FROM ({ln3_sql('powerlaw')})")(
    lambda s, d: ln3(s, d, "powerlaw"))
query("baseline_ln3_by_rank", f"""WITH x AS (SELECT *, floor(log2(rank() OVER (ORDER BY f DESC)))::INT AS band FROM ({ln3_sql('word6')}))
SELECT band, count(*)::BIGINT AS items, round(avg(f), 4) AS f, round(avg(abs(sketch - f)), 4) AS sketch_error, round(avg(abs(bloom - f)), 4) AS bloom_error, round(avg((bloom = 0)::INT), 6) AS bloom_zero FROM x GROUP BY band""")(
    lambda s, d: ln3(s, d, "word6").groupBy(F.floor(F.log2("rank")).cast("int").alias("band")).agg(
        F.count("*").alias("items"), F.round(F.avg("f"), 4).alias("f"), F.round(F.avg(F.abs(F.col("sketch") - F.col("f"))), 4).alias("sketch_error"), F.round(F.avg(F.abs(F.col("bloom") - F.col("f"))), 4).alias("bloom_error"),
        F.round(F.avg((F.col("bloom") == 0).cast("int")), 6).alias("bloom_zero")))


def line_users(s: SparkSession, d: str) -> DataFrame:
    """(line, n): the populations that costs are asked for, order lines by their number in the order."""
    return table(s, d, "lineitem").groupBy(F.col("l_linenumber").alias("line")).agg(F.count("*").alias("n"))


_USERS = "SELECT l_linenumber AS line, count(*)::BIGINT AS n FROM lineitem GROUP BY l_linenumber"
_COST = f"""WITH x AS (SELECT method, line, n::DOUBLE AS n, log2(n) AS l, 30.0::DOUBLE AS d FROM (SELECT unnest(['tree', 'hashed_bits', 'predecessor']) AS method), ({_USERS})),
y AS (SELECT *, pow(greatest(l, d), 2) AS u FROM x)
SELECT method, line, n::BIGINT AS n, round(CASE method WHEN 'tree' THEN n * sqrt(d) WHEN 'hashed_bits' THEN n ELSE n * n * sqrt(n) END, 0) AS server_time,
round(CASE method WHEN 'predecessor' THEN n ELSE u END, 3) AS user_time,
round(CASE method WHEN 'tree' THEN sqrt(n) * pow(l, 1.5) * d WHEN 'hashed_bits' THEN sqrt(n) ELSE n * n END, 0) AS server_memory,
round(CASE method WHEN 'predecessor' THEN NULL ELSE greatest(l, d) END, 3) AS user_memory, round(CASE method WHEN 'predecessor' THEN 1.0::DOUBLE ELSE 2.0::DOUBLE END, 3) AS communication_bits,
round(CASE method WHEN 'tree' THEN sqrt(n * l * d) / 2.0::DOUBLE ELSE sqrt(n * d) / 2.0::DOUBLE END, 3) AS error FROM y"""
query("cost_table", _COST)(lambda s, d: cost.cost_table(line_users(s, d), 30, 2.0))
query("predecessor_cost", f"SELECT line, n, server_time AS predecessor_time, tree_time, round(server_time / tree_time, 3) AS ratio FROM (SELECT line, n, server_time FROM ({_COST}) WHERE method = 'predecessor') JOIN (SELECT line, server_time AS tree_time FROM ({_COST}) WHERE method = 'tree') USING (line)")(
    lambda s, d: (lambda c: c.where("method = 'predecessor'").select("line", "n", F.col("server_time").alias("predecessor_time")).join(c.where("method = 'tree'").select("line", F.col("server_time").alias("tree_time")), "line")
                  .select("line", "n", "predecessor_time", "tree_time", F.round(F.col("predecessor_time") / F.col("tree_time"), 3).alias("ratio")))(cost.cost_table(line_users(s, d), 30, 2.0)))

_MECHANISMS = {"single_report": "e", "half_report": "e / 2", "two_reports": "e", "linear_report": "ln((1 + e) / (1 - e))", "doubled_report": "2 * e"}
query("privacy_ratio", " UNION ALL ".join(f"SELECT '{k}' AS mechanism, e AS eps, round({v}, 9) AS loss FROM (SELECT unnest([0.25, 0.5, 0.75])::DOUBLE AS e)" for k, v in _MECHANISMS.items()))(
    lambda s, d: s.createDataFrame([(k, e, round(privacy.mechanism_loss(k, e), 12)) for k in _MECHANISMS for e in (0.25, 0.5, 0.75)], "mechanism string, eps double, loss double").withColumn("loss", F.round("loss", 9)))


_OPERATIONS = {"direct": ("n * 1000 // 6", "2 * n"), "counters": (f"2 * n + {1000 * P.t * P.m}", "2 * n"), "transform": (f"2 * n + {7 * P.t * P.m * (P.m.bit_length() - 1)}", "2 * n"), "partitioned": (f"n + {P.R * 2 * P.T * P.T.bit_length()}", "n")}
_HELD = {"direct": (P.t, 0, 0), "counters": (P.t, 0, 7), "transform": (P.t, P.t, 7), "partitioned": (P.R, P.R, 0)}


@query("operation_counts", " UNION ALL ".join(f"""SELECT '{m}' AS method, line, n, {1000 * h}::BIGINT AS hashes, ({additions})::BIGINT AS additions, {1000 * looked}::BIGINT AS look_ups, ({bits})::BIGINT AS bits,
{2 * P.R * P.T if m == 'partitioned' else levels * P.t * P.m}::BIGINT AS cells FROM ({_USERS})""" for m, (additions, bits) in _OPERATIONS.items() for h, looked, levels in [_HELD[m]]))
def _(s, d):
    def counts(m: str) -> DataFrame:
        return line_users(s, d).select(F.lit(m).alias("method"), "line", "n", *[(v if isinstance(v, Column) else F.lit(v)).cast("long").alias(k) for k, v in cost.operations(m, F.col("n"), P, 6, 1000).items()])

    return _union([counts(m) for m in _OPERATIONS])


# --- measures ---------------------------------------------------------------------------------------------------------------

query("linf_error_quantity", f"SELECT round(max(abs(est - f)), 4) AS linf, count(*)::BIGINT AS items FROM ({ORACLES['sketch_freq_quantity']})")(
    lambda s, d: (lambda r: measures.linf_error(r.select("item", "f"), r.select("item", "est")))(QUERIES["sketch_freq_quantity"](s, d)))
query("list_error_words", f"SELECT round(max(abs(est - f)), 4) AS list_error, count(*)::BIGINT AS items FROM ({ORACLES['tree_hh_words']})")(
    lambda s, d: (lambda r: measures.list_error(r.select("item", "f"), r.select("item", "est")))(QUERIES["tree_hh_words"](s, d)))
query("precision_recall_words", f"""WITH h AS MATERIALIZED ({ORACLES['tree_hh_words']}), t AS MATERIALIZED ({duck.exact('word6')}), n AS (SELECT 15 * sqrt(sum(f)) AS thr FROM t),
c AS (SELECT count(*) FILTER (t.f >= thr AND h.item IS NOT NULL) AS tp, count(*) FILTER (coalesce(t.f, 0) < thr AND h.item IS NOT NULL) AS fp, count(*) FILTER (t.f >= thr AND h.item IS NULL) AS fn, any_value(thr) AS thr FROM t FULL JOIN h ON t.item = h.item, n)
SELECT round(thr, 4) AS thr, tp::BIGINT AS tp, fp::BIGINT AS fp, fn::BIGINT AS fn, round(CASE WHEN tp + fp > 0 THEN tp::DOUBLE / (tp + fp) END, 6) AS precision, round(CASE WHEN tp + fn > 0 THEN tp::DOUBLE / (tp + fn) END, 6) AS recall FROM c""")(
    lambda s, d: words_quality(s, d))


def words_quality(s: SparkSession, d: str) -> DataFrame:
    """The population is read twice: for the reports, and for the truth, which has the number of users too."""
    x = population(s, d, "word6")
    truth = baselines.exact_frequencies(x).persist()
    thr = prefix_tree.noise_threshold(truth.agg(F.sum("f")).first()[0] or 0)
    found = prefix_tree.tree_heavy_hitters(x, WORDS_SF001, SIX_LETTERS, threshold=thr)
    return measures.precision_recall(truth, found, F.lit(thr)).select(F.round(F.lit(thr), 4).alias("thr"), "tp", "fp", "fn", "precision", "recall")


_ETA, _BOUND = 2500.0, 20000.0
query("guarantee_check", f"""WITH h AS MATERIALIZED ({ORACLES['tree_hh_returnflag']}), t AS ({duck.exact('flag')}), b AS (SELECT coalesce(f, 0) AS f, h.item AS hit, est FROM t FULL JOIN h ON t.item = h.item)
SELECT count(*) FILTER (f > {3 * _ETA} AND hit IS NULL)::BIGINT AS missing, count(*) FILTER (f < {_ETA} AND hit IS NOT NULL)::BIGINT AS spurious, round(max(abs(est - f)), 4) AS max_error, coalesce(round(max(abs(est - f)), 4), 0) <= {_BOUND} AS within_bound FROM b""")(
    lambda s, d: measures.check_guarantee(baselines.exact_frequencies(population(s, d, "flag")), QUERIES["tree_hh_returnflag"](s, d), _ETA, _BOUND))


def seeded_at(pop: DataFrame, items: DataFrame, p: Params, budgets: list[float], seeds: list[int]) -> DataFrame:
    """(eps, seed, item, est): one job for all budgets and seeds, the seed being a column."""
    runs = pop.withColumn("seed", F.explode(F.array(*[F.lit(i) for i in seeds])))
    reports = sketch_oracle.budget_reports(runs.select("*", F.col("seed").alias("run")), p, budgets, F.col("seed"), F.col("run"))
    sums = reports.groupBy("seed", "pair", "row").agg(*[F.sum(F.col(f"y{i}").cast("long")).alias(f"s{i}") for i in range(len(budgets))])
    each = F.explode(F.array(*[F.struct(F.lit(float(eps)).alias("eps"), F.col(f"s{i}").alias("s")) for i, eps in enumerate(budgets)]))
    sums = sums.select("seed", "pair", "row", each.alias("x")).select("x.eps", "seed", "pair", "row", "x.s")
    cells = hadamard.fwht_groups(sums, ["eps", "seed", "pair"], "row", p.m)
    asked = items.select("item", F.explode(F.array(*[F.lit(i) for i in seeds])).alias("seed")).select("*", F.explode(F.sequence(F.lit(0), F.lit(p.t - 1))).alias("pair"))
    h, g = hashing.bucket_hash(F.col("seed"), F.col("pair"), F.col("item"), p.m), hashing.sign_hash(F.col("seed"), F.col("pair"), F.col("item"))
    places = asked.withColumns({"cell": h, "g": g}).select("*", F.explode(F.array(*[F.lit(float(eps)) for eps in budgets])).alias("eps"))
    v = places.join(cells, ["eps", "seed", "pair", "cell"], "left").select("eps", "seed", "item", (F.col("g") * F.coalesce("v", F.lit(0))).alias("v"))
    scale = F.element_at(F.array(*[F.lit(p.t * debias(eps)) for eps in budgets]), F.array_position(F.array(*[F.lit(float(eps)) for eps in budgets]), F.col("eps")).cast("int"))
    return v.groupBy("eps", "seed", "item").agg(F.median("v").alias("v")).select("eps", "seed", "item", F.round(scale * F.col("v"), 4).alias("est"))


def seeded(pop: DataFrame, items: DataFrame, p: Params, seeds: list[int]) -> DataFrame:
    """(seed, item, est) at the budget of ``p``."""
    return seeded_at(pop, items, p, [p.eps], seeds).drop("eps")


query("run_stats_ten_seeds", f"""WITH {duck.dictionary_ctes('flag', P, seeds=str(SEEDS))}, n AS (SELECT count(*)::DOUBLE / {len(SEEDS)} AS n FROM pop), t AS ({duck.exact('flag')}),
r AS (SELECT item, avg(est / n) AS mean, stddev_samp(est / n) AS sd FROM est, n GROUP BY item)
SELECT item, round(mean, 6) AS mean, round(sd, 6) AS sd, round(f / n, 6) AS share, abs(mean - f / n) <= sd AS within FROM r JOIN t USING (item), n""")(
    lambda s, d: (lambda x: measures.run_stats(seeded(x, x.select("item").distinct(), P, SEEDS), baselines.exact_frequencies(x), float(x.count())))(population(s, d, "flag")))

query("bucket_diagnostics", f"""WITH pop AS ({duck.POPS['flag']}), n AS (SELECT count(*) / 75.0::DOUBLE AS mean FROM pop), g AS (SELECT level, pair, count(*) AS users FROM ({duck.own(P, L=5)}) GROUP BY ALL)
SELECT 75::BIGINT AS groups, count(*) FILTER (users >= mean / 2 AND users <= mean * 2)::BIGINT AS good, round(count(*) FILTER (users >= mean / 2 AND users <= mean * 2) / 75.0::DOUBLE, 6) AS share FROM g, n""")(
    lambda s, d: (lambda x: measures.sketch_diagnostics(assign(x, 42, levels=5, t=P.t), float(x.count()), P.t, 5))(population(s, d, "flag")))

_PCELL = f"{duck.sl(duck.dig('cell', 42, 'subset', 'item'), 1, 8)} % {P.T}"
query("partition_diagnostics", f"""WITH pop AS ({duck.POPS['nation']}), x AS (SELECT item, subset, {_PCELL} AS cell FROM ({duck.own(P)})), c AS (SELECT subset, cell, count(*) AS k, count(DISTINCT item) AS items FROM x GROUP BY ALL)
SELECT subset, sum(k)::BIGINT AS users, sum(CASE WHEN items > 1 THEN k ELSE 0 END)::BIGINT AS collisions FROM c GROUP BY subset""")(
    lambda s, d: (lambda x: measures.partition_diagnostics(x, P, sign_matrix_oracle.cell_of(42, F.col("subset"), F.col("item"), P.T), F.col("subset")))(assign(population(s, d, "nation"), 42, subsets=P.R)))

query("bit_error_report", f"""WITH {_CELLS}, i AS (SELECT DISTINCT code FROM pop), b AS (SELECT code, bit::INT AS bit, (code >> (4 - bit)::INT) & 1 AS true_value, {duck.sl(duck.dig('hcell', 42, '0', 'code'), 1, 8)} % {P.T} AS cell FROM i, range(5) r(bit))
SELECT chr((code + 65)::INT) AS item, count(*)::BIGINT AS bits, sum((coalesce(value, 0) <> true_value)::INT)::BIGINT AS wrong, round(sum((coalesce(value, 0) <> true_value)::INT) / count(*)::DOUBLE, 6) AS rate FROM b LEFT JOIN best ON best.rep = 0 AND best.cell = b.cell AND best.bit = b.bit GROUP BY code""")(
    lambda s, d: (lambda x: measures.bit_error_report(
        hashed_bits.warm_up_cells(x, P, FLAG_BITS),
        x.select(F.col("item").cast("long").alias("code")).distinct().select("code", F.explode(F.sequence(F.lit(0), F.lit(4))).alias("bit")).select(
            letter(F.col("code")).alias("item"), F.lit(0).alias("rep"), "bit", hashed_bits.cell_of(P, F.lit(0), F.col("code")).alias("cell"),
            F.when(F.col("code").bitwiseAND(F.element_at(F.array(*[F.lit(1 << 4 - i).cast("long") for i in range(5)]), F.col("bit") + 1)) != 0, 1).otherwise(0).alias("true_value"))))(flag_codes(s, d)))

# --- workloads: what moves with n, with the budget, with the width -----------------------------------------------------------


def at_percentiles(pop: DataFrame, est: DataFrame) -> DataFrame:
    truth = baselines.exact_frequencies(pop)
    n = pop.agg(F.count("*").alias("n"))
    picked = measures.percentile_items(truth, PCTLES).join(est, "item").join(F.broadcast(n))
    return picked.select("pctle", "item", F.round(F.col("f") / F.col("n"), 6).alias("share"), F.round(F.col("est") / F.col("n"), 6).alias("est_share"))


def at_percentiles_sql(p: Params, where: str = "TRUE") -> str:
    return f"""(WITH {duck.dictionary_ctes('powerlaw', p, where)}, n AS (SELECT count(*)::DOUBLE AS n FROM pop), f AS (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item),
t AS (SELECT item, f, 100.0::DOUBLE * (rank() OVER (ORDER BY f) - 1) / count(*) OVER () AS share FROM f), q AS (SELECT unnest({PCTLES})::DOUBLE AS pctle),
m AS (SELECT pctle, max(f) AS f FROM t, q WHERE share <= pctle GROUP BY pctle), k AS (SELECT pctle, min(item) AS item, m.f FROM m JOIN t ON t.f = m.f GROUP BY pctle, m.f)
SELECT pctle, item, round(f / n, 6) AS share, round(est / n, 6) AS est_share FROM k JOIN est USING (item), n)"""


def vary(s: SparkSession, d: str, p: Params, keep: Callable[[DataFrame], DataFrame] = lambda x: x) -> DataFrame:
    x = keep(population(s, d, "powerlaw"))
    return at_percentiles(x, sketch_oracle.dictionary_frequencies(x, x.select("item").distinct(), p))


_SUB = f"{duck.sl(duck.dig('sub', 0, 'user_key'), 1, 8)} % 100 < "
query("vary_n", " UNION ALL ".join(f"SELECT {c} AS percent_of_users, * FROM {at_percentiles_sql(P, _SUB + str(c))}" for c in SHARES))(
    lambda s, d: _union([vary(s, d, P, lambda x, c=c: x.where(hashing.hex_slice(hashing.digest("sub", 0, F.col("user_key")), 1, 8) % 100 < c)).select(F.lit(c).alias("percent_of_users"), "*") for c in SHARES]))
query("vary_eps", " UNION ALL ".join(f"SELECT {e}::DOUBLE AS eps, * FROM {at_percentiles_sql(P.but(eps=e))}" for e in EPS_GRID))(
    lambda s, d: _union([vary(s, d, P.but(eps=e)).select(F.lit(e).alias("eps"), "*") for e in EPS_GRID]))
query("vary_width", " UNION ALL ".join(f"SELECT {m}::INT AS width, * FROM {at_percentiles_sql(P.but(m=m))}" for m in WIDTHS))(
    lambda s, d: _union([vary(s, d, P.but(m=m)).select(F.lit(m).alias("width"), "*") for m in WIDTHS]))

# --- the published experiments: 285 pairs, sqrt(n) cells, ten runs ---------------------------------------------------------------


def repeated(pop: DataFrame, truth: DataFrame, picks: DataFrame, budgets: list[float], m: int | None = None) -> DataFrame:
    """eps, columns of ``picks`` (item, f and a key), share, mean and sd of the estimated share over ``SEEDS``; one job for all runs and budgets."""
    n = truth.agg(F.sum("f")).first()[0] or 0
    p = experiment(n, budgets[0], public_coins=True)
    runs = seeded_at(pop, picks.select("item").distinct(), p if m is None else p.but(m=m), budgets, SEEDS)
    size = float(max(n, 1))
    stats = runs.groupBy("eps", "item").agg(F.round(F.avg(F.col("est") / size), 6).alias("mean"), F.round(F.stddev_samp(F.col("est") / size), 6).alias("sd"))
    return picks.join(stats, "item").select("eps", *[c for c in picks.columns if c != "f"], F.round(F.col("f") / size, 6).alias("share"), "mean", "sd")


def share_of_users(pop: DataFrame, percent: int) -> DataFrame:
    return pop.where(hashing.hex_slice(hashing.digest("sub", 0, F.col("user_key")), 1, 8) % 100 < percent)


def figure(s: SparkSession, d: str, name: str, grid: list, how: Callable) -> DataFrame:
    """``repeated`` at the percentiles of the power law for every value of ``grid``; ``how`` gives a value's population and cells."""
    out = []
    for value in grid:
        pop, m = how(population(s, d, "powerlaw"), value)
        truth = baselines.exact_frequencies(pop).persist()
        out.append(repeated(pop, truth, measures.percentile_items(truth, PCTLES), [2.0], m).drop("eps").select(F.lit(value).alias(name), "*"))
    return _union(out)


def figure_budgets(s: SparkSession, d: str) -> DataFrame:
    """The same for every budget; the users are read once for all of them."""
    pop = population(s, d, "powerlaw")
    truth = baselines.exact_frequencies(pop).persist()
    return repeated(pop, truth, measures.percentile_items(truth, PCTLES).persist(), EPS_GRID)


_PICKS = f"""WITH t AS (SELECT item, f, 100.0::DOUBLE * (rank() OVER (ORDER BY f) - 1) / count(*) OVER () AS share FROM f), q AS (SELECT unnest({PCTLES})::DOUBLE AS pctle),
k AS (SELECT pctle, max(f) AS f FROM t, q WHERE share <= pctle GROUP BY pctle) SELECT pctle, min(item) AS item FROM k JOIN t ON t.f = k.f GROUP BY pctle"""
_LAW = duck.POPS["powerlaw"]
query("figure_n", " UNION ALL ".join(f"SELECT {c} AS percent_of_users, * FROM {duck.repeated(f'SELECT * FROM ({_LAW}) WHERE {_SUB}{c}', 2.0, SEEDS, _PICKS, 'pctle')}" for c in SHARES))(
    lambda s, d: figure(s, d, "percent_of_users", SHARES, lambda x, c: (share_of_users(x, c), None)))
query("figure_eps", " UNION ALL ".join(f"SELECT {e}::DOUBLE AS eps, * FROM {duck.repeated(_LAW, e, SEEDS, _PICKS, 'pctle')}" for e in EPS_GRID))(figure_budgets)
query("figure_width", " UNION ALL ".join(f"SELECT {m}::INT AS width, * FROM {duck.repeated(_LAW, 2.0, SEEDS, _PICKS, 'pctle', m=m)}" for m in WIDTHS[:4]))(
    lambda s, d: figure(s, d, "width", WIDTHS[:4], lambda x, m: (x, m)))

#: Draws with replacement from the corpus (the published run makes ten million).
DRAWS = 100_000
_DRAWN = f"""SELECT x.user_key, l.item FROM (SELECT id::VARCHAR AS user_key, {duck.sl(duck.dig('draw', 0, 'id'), 1, 13)} % (SELECT count(*) FROM ({duck.POPS['words']})) AS at FROM range({DRAWS}) r(id)) x
ASOF JOIN (SELECT item, sum(f) OVER (ORDER BY item) - f AS low FROM ({duck.exact('words')})) l ON x.at >= l.low"""
_RANKED = f"SELECT rank, item FROM (SELECT row_number() OVER (ORDER BY f DESC, item)::BIGINT AS rank, item FROM f) WHERE rank IN {tuple(RANKS)}"


def corpus_figure(s: SparkSession, d: str) -> DataFrame:
    drawn = sampled(population(s, d, "words"), DRAWS).persist()
    truth = baselines.exact_frequencies(drawn).persist()
    picks = measures.rank_items(truth, RANKS).persist()
    return repeated(drawn, truth, picks, EPS_GRID)


query("figure_corpus_eps", " UNION ALL ".join(f"SELECT {e}::DOUBLE AS eps, * FROM {duck.repeated(_DRAWN, e, SEEDS, _RANKED, 'rank')}" for e in EPS_GRID))(corpus_figure)
query("corpus_draws", f"SELECT item, count(*)::BIGINT AS f FROM ({_DRAWN}) GROUP BY item")(lambda s, d: baselines.exact_frequencies(sampled(population(s, d, "words"), DRAWS)))

_T31 = P.but(t=31, m=256)


def runs_quality(s: SparkSession, d: str, pop: str) -> DataFrame:
    """Mean and deviation of precision and recall over ten walks at the published budget and threshold; they ask for lists, not for estimates."""
    x = population(s, d, pop)
    truth = baselines.exact_frequencies(x).persist()
    runs = prefix_tree.tree_run_lists(x, _T31, SIX_LETTERS, SEEDS)
    return measures.run_quality(truth, runs, prefix_tree.noise_threshold(truth.agg(F.sum("f")).first()[0] or 0), SEEDS)


for _name, _pop in (("heavy_hitter_runs_words", "word6"), ("heavy_hitter_runs_powerlaw", "powerlaw6")):
    query(_name, duck.run_quality(duck.tree_runs(_pop, _T31, duck.text_code("item", 6), 6, 5, 27, 15.0, SEEDS), duck.text_decode("code", 6), 15.0))(lambda s, d, pop=_pop: runs_quality(s, d, pop))

query("true_powerlaw_bins", f"SELECT item, f, round(f / sum(f) OVER ()::DOUBLE, 6) AS share FROM ({duck.exact('powerlaw')})")(
    lambda s, d: (lambda t: t.join(F.broadcast(t.agg(F.sum("f").alias("n")))).select("item", "f", F.round(F.col("f") / F.col("n"), 6).alias("share")))(baselines.exact_frequencies(population(s, d, "powerlaw"))))
query("brute_force_against_tree", f"WITH t AS ({ORACLES['tree_node_queries']}) SELECT queried AS tree_queries, {27**6}::BIGINT AS all_strings, {26**6}::BIGINT AS all_words FROM t WHERE level IS NULL")(
    lambda s, d: QUERIES["tree_node_queries"](s, d).where("level IS NULL").select(F.col("queried").alias("tree_queries"), F.lit(27**6).alias("all_strings"), F.lit(26**6).alias("all_words")))

# --- guarantees and good events, measured ------------------------------------------------------------------------------------------

_ENUM = "SELECT i::VARCHAR AS item FROM range(32) r(i)"
query("enumerate_without_dictionary", f"WITH pop AS MATERIALIZED ({duck.POPS['flagcode']}), {duck.partitioned_ctes('SELECT * FROM pop', P, P.eps, items=_ENUM)} SELECT item, est FROM pest")(
    lambda s, d: sign_matrix_oracle.full_histogram(flag_codes(s, d), dispatch.all_items(s, FLAG_BITS), P))

# The analysis' parameters for 50 queries to 60,000 users, whatever the table has.
_SMALL = partitioned_small(60_000, 50, 0.05, 1.0)
_PA = P.but(eps=1.0, R=int(_SMALL["R"]), T=int(_SMALL["T"]))
query("partitioned_theory_quantity", f"""WITH pop AS MATERIALIZED ({duck.POPS['quantity']}), {duck.partitioned_ctes('SELECT * FROM pop', _PA, _PA.eps)},
e AS (SELECT abs(f - est) AS error FROM (SELECT item, count(*) AS f FROM pop GROUP BY item) JOIN pest USING (item))
SELECT round(max(error), 4) AS max_error, {round(_SMALL['error'], 4)}::DOUBLE AS bound, max(error) <= {round(_SMALL['error'], 4)} AS within FROM e""")(
    lambda s, d: (lambda x: with_truth(x, sign_matrix_oracle.partitioned_estimates(x, x.select("item").distinct(), _PA)))(population(s, d, "quantity")).agg(
        F.round(F.max(F.abs(F.col("f") - F.col("est"))), 4).alias("max_error"), F.lit(round(_SMALL["error"], 4)).alias("bound"), (F.max(F.abs(F.col("f") - F.col("est"))) <= round(_SMALL["error"], 4)).alias("within")))


def theory_check(s: SparkSession, d: str) -> DataFrame:
    """The tree's guarantee with the analysis' own threshold and bound: both are above n here, which is what makes it vacuous."""
    truth = baselines.exact_frequencies(population(s, d, "flag")).persist()
    n = truth.agg(F.sum("f")).first()[0] or 0
    theory = theory_tree(n, 5, 2.0)
    found = measures.check_guarantee(truth, QUERIES["tree_hh_returnflag"](s, d), theory["eta"], theory["list_error"])
    return found.select(F.lit(n).cast("long").alias("n"), F.round(F.lit(theory["eta"]), 2).alias("eta"), F.round(F.lit(theory["list_error"]), 2).alias("bound"), "missing", "within_bound", F.lit(3 * theory["eta"] > n).alias("vacuous"))


query("guarantee_theory", f"""WITH h AS MATERIALIZED ({ORACLES['tree_hh_returnflag']}), t AS ({duck.exact('flag')}), n AS (SELECT sum(f)::BIGINT AS n FROM t),
c AS (SELECT n, 147 * sqrt(n * ln(n / 0.05::DOUBLE) * 5) / 2 AS eta, 147 * sqrt(n * ln(n / 0.05::DOUBLE)) / 2 AS bound FROM n),
b AS (SELECT coalesce(f, 0) AS f, h.item AS hit, est FROM t FULL JOIN h ON t.item = h.item)
SELECT any_value(n) AS n, round(any_value(eta), 2) AS eta, round(any_value(bound), 2) AS bound, count(*) FILTER (f > 3 * eta AND hit IS NULL)::BIGINT AS missing, coalesce(round(max(abs(est - f)), 4), 0) <= any_value(bound) AS within_bound, any_value(3 * eta > n) AS vacuous FROM b, c""")(theory_check)


_ALPHAS = [0.1, 0.25, 0.5, 1.0]


def load_tails(s: SparkSession, d: str) -> DataFrame:
    """How many of the subsets that users are dealt to are off their mean by a share alpha, against the Poisson tails, carried over to balls in bins."""
    own = assign(population(s, d, "priority"), P.seed, subsets=P.R)
    loads = own.groupBy("subset").agg(F.count("*").alias("users")).join(F.broadcast(own.agg((F.count("*") / P.R).alias("mu"))))
    each = loads.select("users", "mu", F.explode(F.array(*[F.lit(a) for a in _ALPHAS])).alias("alpha"))
    off = (F.col("users") <= F.col("mu") * (1 - F.col("alpha"))) | (F.col("users") >= F.col("mu") * (1 + F.col("alpha")))
    out = each.groupBy("alpha").agg(F.sum(off.cast("long")).alias("off"), F.first("mu").alias("mu"))
    tail = (F.exp(-F.col("alpha") * F.col("alpha") * F.col("mu") / 2) + F.exp(-F.col("alpha") * F.col("alpha") * F.col("mu") / 3)) * math.e * F.sqrt(F.col("mu") * P.R)
    return out.select("alpha", "off", F.round(F.least(F.lit(1.0), tail), 6).alias("bound"))


query("load_tails", f"""WITH pop AS ({duck.POPS['priority']}), l AS (SELECT subset, count(*) AS users FROM ({duck.own(P)}) GROUP BY subset), m AS (SELECT count(*) / {P.R}.0::DOUBLE AS mu FROM pop),
a AS (SELECT unnest({_ALPHAS})::DOUBLE AS alpha)
SELECT alpha, count(*) FILTER (users <= mu * (1 - alpha) OR users >= mu * (1 + alpha))::BIGINT AS off, round(least(1.0::DOUBLE, (exp(-alpha * alpha * any_value(mu) / 2) + exp(-alpha * alpha * any_value(mu) / 3)) * {duck.num(math.e)} * sqrt(any_value(mu) * {P.R})), 6) AS bound
FROM l, m, a GROUP BY alpha""")(load_tails)


def pair_events(s: SparkSession, d: str) -> DataFrame:
    x = population(s, d, "quantity")
    truth = baselines.exact_frequencies(x).persist()
    own = assign(x, P.seed, t=P.t).select("item", "pair")
    cands = truth.select("item", F.col("item").alias("x"))
    sums = sketch_oracle.signed_sums(sketch_oracle.count(sketch_oracle.dictionary_reports(x, P), ["pair", "row"]), cands, P)
    return measures.good_pairs(own, sums, truth, P, float(P.t))


_UNIT = f"sqrt(n * {float(P.t)}::DOUBLE)"
query("good_pairs_quantity", f"""WITH {duck.dictionary_ctes('quantity', P)}, t AS (SELECT item, count(*)::BIGINT AS f FROM pop GROUP BY item), n AS (SELECT count(*) AS n FROM pop),
mine AS MATERIALIZED (SELECT item, pair, count(*) AS k FROM ({duck.own(P)}) GROUP BY ALL), users AS (SELECT pair, sum(k) AS users FROM mine GROUP BY pair),
cells AS (SELECT pair, h, sum(k * g) AS c FROM mine JOIN places USING (item, pair) GROUP BY ALL),
x AS (SELECT p.item, f, n, {P.t} * coalesce(k, 0) AS held, {P.t} * coalesce(users, 0) AS scaled, {P.t} * p.g * coalesce(c, 0) AS sketched, {duck.num(P.t * debias(P.eps))} * v AS est
  FROM places p JOIN sums USING (item, pair) JOIN t USING (item) LEFT JOIN mine USING (item, pair) LEFT JOIN users USING (pair) LEFT JOIN cells ON cells.pair = p.pair AND cells.h = p.h, n)
SELECT item, count(*) FILTER (abs(held - f) <= 4 * {_UNIT} AND scaled BETWEEN n / 2.0 AND 2 * n)::BIGINT AS g1, count(*) FILTER (abs(sketched - f) <= 8 * {_UNIT})::BIGINT AS g2, count(*) FILTER (abs(est - f) <= 14 / 2.0::DOUBLE * {_UNIT})::BIGINT AS g3 FROM x GROUP BY item""")(pair_events)


def subset_events(s: SparkSession, d: str) -> DataFrame:
    own = assign(population(s, d, "nation"), P.seed, subsets=P.R)
    return measures.good_subsets(own.select("item", "subset", F.array(*[sign_matrix_oracle.cell_of(P.seed, F.lit(r), F.col("item"), P.T) for r in range(P.R)]).alias("cells")), P.R, P.T)


query("good_subsets_nation", f"""WITH pop AS MATERIALIZED ({duck.POPS['nation']}), n AS (SELECT count(*) AS n FROM pop), mine AS MATERIALIZED (SELECT item, subset, count(*) AS k FROM ({duck.own(P)}) GROUP BY ALL),
t AS (SELECT item, count(*) AS f FROM pop GROUP BY item), e AS MATERIALIZED (SELECT item, f, subset, {_PCELL} AS cell FROM t, range({P.R}) r(subset)),
w AS (SELECT subset, cell, sum(f) AS total FROM e GROUP BY ALL), h AS (SELECT e.subset, e.cell, sum(k) AS here FROM e JOIN mine USING (item, subset) GROUP BY ALL), z AS (SELECT subset, sum(k) AS users FROM mine GROUP BY subset)
SELECT item, count(*) FILTER (total - f <= 16 * n / {P.T}::DOUBLE)::BIGINT AS collisions, count(*) FILTER (coalesce(users, 0) BETWEEN n / {2 * P.R}::DOUBLE AND 2 * n / {P.R}::DOUBLE)::BIGINT AS sizes,
count(*) FILTER (abs({P.R} * coalesce(here, 0) - total) <= sqrt(8 * {P.R} * n))::BIGINT AS sampling FROM e JOIN w USING (subset, cell) LEFT JOIN h USING (subset, cell) LEFT JOIN z USING (subset), n GROUP BY item""")(subset_events)


def held_cells(s: SparkSession, d: str) -> DataFrame:
    """Counters that the server holds, next to the model's number of them."""
    x = population(s, d, "quantity")
    tables = {
        "tree": (sketch_oracle.count(sketch_oracle.tree_reports(x, P, integers(6)), ["level", "pair", "row"], "y1"), P.t * P.m * 6),
        "sketch": (sketch_oracle.count(sketch_oracle.dictionary_reports(x, P), ["pair", "row"]), P.t * P.m),
        "partitioned": (sign_matrix_oracle.partitioned_counters(sign_matrix_oracle.partitioned_reports(x, P)), 2 * P.R * P.T),
    }
    return _union([t.agg(F.count("*").alias("held")).select(F.lit(k).alias("method"), "held", F.lit(model).cast("long").alias("model")) for k, (t, model) in tables.items()])


query("server_memory_counted", f"""WITH pop AS MATERIALIZED ({duck.POPS['quantity']}) SELECT 'tree' AS method, count(DISTINCT (level, pair, row_))::BIGINT AS held, {P.t * P.m * 6}::BIGINT AS model FROM ({duck.own(P, L=6)})
UNION ALL SELECT 'sketch', count(DISTINCT (pair, row_))::BIGINT, {P.t * P.m}::BIGINT FROM ({duck.own(P)}) UNION ALL SELECT 'partitioned', count(DISTINCT (subset, col))::BIGINT, {2 * P.R * P.T}::BIGINT FROM ({duck.own(P)})""")(held_cells)

# --- surrounding operators ------------------------------------------------------------------------------------------------------

query("bounded_events_per_user", "SELECT user_id, arg_max(event_type, (ts, event_id)) AS event_type FROM events GROUP BY user_id")(
    lambda s, d: population(s, d, "event_user").select(F.col("user_key").cast("long").alias("user_id"), F.col("item").alias("event_type")))


def listed(s: SparkSession, d: str) -> DataFrame:
    """Words that the known-dictionary oracle puts above the threshold, the list that filters act on."""
    return QUERIES["sketch_freq_words_known"](s, d).where(F.col("est") >= F.lit(4000.0))


_LISTED = f"SELECT item, est FROM ({ORACLES['sketch_freq_words_known']}) WHERE est >= 4000"
query("new_words_antijoin", f"SELECT item, est FROM ({_LISTED}) WHERE item NOT IN (SELECT item FROM ({duck.POPS['bench']}))")(
    lambda s, d: histogram.new_items(listed(s, d), benchmark_words(s, d)).select("item", "est"))
query("known_filter_semijoin", f"SELECT item, est FROM ({_LISTED}) WHERE item IN (SELECT item FROM ({duck.POPS['bench']}))")(
    lambda s, d: histogram.filter_known(listed(s, d), benchmark_words(s, d)).select("item", "est"))


def seed_list(s: SparkSession, d: str, seed: int) -> DataFrame:
    x = population(s, d, "words")
    return sketch_oracle.dictionary_frequencies(x, x.select("item").distinct(), P.but(seed=seed)).where("est >= 4000")


def seed_sql(seed: int) -> str:
    return f"SELECT item, est FROM ({duck.dictionary('words', P.but(seed=seed))}) WHERE est >= 4000"


query("stable_hitters_intersect", f"SELECT item FROM ({seed_sql(1)}) INTERSECT SELECT item FROM ({seed_sql(2)})")(lambda s, d: histogram.stable(seed_list(s, d, 1), seed_list(s, d, 2)))
query("false_positives_except", f"SELECT item FROM ({seed_sql(1)}) EXCEPT SELECT item FROM ({duck.exact('words')}) WHERE f >= 4000")(
    lambda s, d: histogram.false_positives(seed_list(s, d, 1), baselines.exact_frequencies(population(s, d, "words")).where("f >= 4000")))
query("union_of_runs", f"SELECT item, max(est) AS est FROM ({seed_sql(1)} UNION ALL {seed_sql(2)}) GROUP BY item")(lambda s, d: histogram.union_of_runs([seed_list(s, d, 1), seed_list(s, d, 2)]))


def lang_reports(s: SparkSession, d: str) -> DataFrame:
    """One report a document about its source, with its language as a public attribute."""
    docs = table(s, d, "documents").select(F.col("doc_id").cast("string").alias("user_key"), F.col("source").alias("item"), "lang")
    return sketch_oracle.dictionary_reports(docs, P)


_LREP = f"""WITH pop AS MATERIALIZED (SELECT doc_id::VARCHAR AS user_key, source AS item, lang FROM documents)
SELECT lang, pair, {duck.flip(f"{duck.sgn('hd', 9)} * {duck.had('row_', f'{duck.sl(chr(104) + chr(100), 1, 8)} % {P.m}')}", P.eps, 1)} AS y FROM (SELECT *, {duck.dig('pair', 42, 'pair', 'item')} AS hd FROM ({duck.own(P)}))"""
query("lang_rollup", f"SELECT lang, pair, sum(y)::BIGINT AS s FROM ({_LREP}) GROUP BY ROLLUP (lang, pair)")(lambda s, d: lang_reports(s, d).rollup("lang", "pair").agg(F.sum(F.col("y").cast("long")).alias("s")))
query("cube_params", f"""SELECT seed, eps, round(avg(est), 4) AS mean_est FROM ({' UNION ALL '.join(f"SELECT {k} AS seed, {e}::DOUBLE AS eps, est FROM ({duck.dictionary('flag', P.but(seed=k, eps=e))})" for k in (1, 2) for e in (1.0, 2.0))}) GROUP BY CUBE (seed, eps)""")(
    lambda s, d: _union([(lambda x: sketch_oracle.dictionary_frequencies(x, x.select("item").distinct(), P.but(seed=k, eps=e)).select(F.lit(k).alias("seed"), F.lit(e).alias("eps"), "est"))(population(s, d, "flag")) for k in (1, 2) for e in (1.0, 2.0)])
    .cube("seed", "eps").agg(F.round(F.avg("est"), 4).alias("mean_est")))

# --- windows of an event stream ----------------------------------------------------------------------------------------------------

_EREP = f"""WITH pop AS MATERIALIZED (SELECT event_id::VARCHAR AS user_key, event_type AS item, ts FROM events)
SELECT ts, pair, row_, {duck.flip(f"{duck.sgn('hd', 9)} * {duck.had('row_', f'{duck.sl(chr(104) + chr(100), 1, 8)} % {P.m}')}", P.eps, 1)} AS y FROM (SELECT *, {duck.dig('pair', 42, 'pair', 'item')} AS hd FROM ({duck.own(P)}))"""
query("windowed_counters", f"SELECT date_trunc('hour', ts) AS start, pair, row_ AS \"row\", sum(y)::BIGINT AS s FROM ({_EREP}) GROUP BY ALL")(lambda s, d: windows.windowed_counters(table(s, d, "events"), P))
query("sliding_counters", f"""SELECT start - k * INTERVAL 30 MINUTE AS start, pair, row_ AS "row", sum(y)::BIGINT AS s
FROM (SELECT *, time_bucket(INTERVAL 30 MINUTE, ts) AS start FROM ({_EREP})), range(2) r(k) GROUP BY ALL""")(lambda s, d: windows.windowed_counters(table(s, d, "events"), P, "sliding"))
query("session_counters", f"""WITH x AS ({_EREP}), y AS (SELECT *, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 10 MINUTE OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS fresh FROM x WINDOW w AS (PARTITION BY pair, row_ ORDER BY ts)),
z AS (SELECT *, sum(fresh) OVER (PARTITION BY pair, row_ ORDER BY ts ROWS UNBOUNDED PRECEDING) AS nth FROM y) SELECT min(ts) AS start, pair, row_ AS "row", sum(y)::BIGINT AS s FROM z GROUP BY pair, row_, nth""")(
    lambda s, d: windows.windowed_counters(table(s, d, "events"), P, "session"))


def hourly(s: SparkSession, d: str) -> DataFrame:
    """An hourly publication: running true counts by event type stand in for a published histogram."""
    per = table(s, d, "events").groupBy(F.date_trunc("hour", "ts").alias("h"), F.col("event_type").alias("item")).agg(F.count("*").alias("n"))
    return per.select((F.col("h") + F.expr("INTERVAL 1 HOUR")).alias("ts"), "item", F.col("n").cast("double").alias("est"))


query("asof_histogram", """WITH p AS (SELECT date_trunc('hour', ts) + INTERVAL 1 HOUR AS pts, event_type AS item, count(*)::DOUBLE AS est FROM events GROUP BY ALL)
SELECT e.event_id, e.event_type AS item, p.est FROM events e ASOF LEFT JOIN p ON e.event_type = p.item AND e.ts >= p.pts""")(
    lambda s, d: histogram.as_of(table(s, d, "events").select("event_id", "ts", F.col("event_type").alias("item")), hourly(s, d)))


_HOURLY = "SELECT date_trunc('hour', ts) + INTERVAL 1 HOUR AS ts, event_type AS item, count(*)::DOUBLE AS est FROM events GROUP BY ALL"
query("estimate_drift", f"SELECT item, ts, est, est - lag(est) OVER (PARTITION BY item ORDER BY ts) AS change FROM ({_HOURLY})")(lambda s, d: histogram.drift(hourly(s, d)))
query("moving_day", f"SELECT item, ts, est, sum(est) OVER (PARTITION BY item ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 86399 PRECEDING AND CURRENT ROW) AS recent FROM ({_HOURLY})")(lambda s, d: histogram.moving_counts(hourly(s, d), 24))
query("cumulative_share_quantity", f"""SELECT row_number() OVER (ORDER BY est DESC, item)::INT AS rank, item, est, round(sum(est) OVER (ORDER BY est DESC, item ROWS UNBOUNDED PRECEDING) / sum(est) OVER (), 6) AS share FROM ({ORACLES['sketch_freq_quantity']})""")(
    lambda s, d: histogram.cumulative_share(QUERIES["sketch_freq_quantity"](s, d).select("item", "est")))
query("merged_truth_words", f"SELECT t.item, t.f, coalesce(h.est, 0)::DOUBLE AS est FROM ({duck.exact('word6')}) t LEFT JOIN (SELECT item, est FROM ({ORACLES['tree_hh_words']})) h USING (item)")(
    lambda s, d: (lambda x: histogram.merged_truth(baselines.exact_frequencies(x), prefix_tree.tree_heavy_hitters(x, WORDS_SF001, SIX_LETTERS).select("item", "est")).where("f > 0"))(population(s, d, "word6")))


def price_bands(s: SparkSession, d: str) -> DataFrame:
    """Orders by a public dictionary of price bands of growing width, then the frequencies of the bands."""
    bands = s.createDataFrame([(float(a), float(b), f"{a}-{b}") for a, b in _BANDS], "low double, high double, name string")
    priced = table(s, d, "orders").select(F.col("o_orderkey").cast("string").alias("user_key"), F.col("o_totalprice").alias("value"))
    pop = histogram.range_join(priced, bands, 10_000.0).select("user_key", F.col("name").alias("item"))
    return with_truth(pop, sketch_oracle.dictionary_frequencies(pop, bands.select(F.col("name").alias("item")), P))


_BANDS = [(0, 10_000), (10_000, 25_000), (25_000, 60_000), (60_000, 150_000), (150_000, 400_000), (400_000, 1_000_000)]
duck.POPS["bands"] = "SELECT o_orderkey::VARCHAR AS user_key, CASE " + " ".join(f"WHEN o_totalprice >= {a} AND o_totalprice < {b} THEN '{a}-{b}'" for a, b in _BANDS) + " END AS item FROM orders"
query("price_band_range_join", duck.dictionary("bands", P))(price_bands)
