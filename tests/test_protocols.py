"""Protocols: parity with DuckDB, equal forms, accuracy over seeds, edge cases, streams."""

import math

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from ldp_hist.functions.encoding import SIX_LETTERS, integers
from ldp_hist.operators import baselines, hashed_bits, histogram, measures, prefix_tree, sign_matrix_oracle, sketch_oracle
from ldp_hist.plans import catalogue, dispatch, sql_surface
from ldp_hist.functions import codes
from ldp_hist.plans.params import LN3, Params
from ldp_hist.sources import populations, sinks
from ldp_hist.streaming import counters

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
PARITY = ["exact_words_top100", "word_percentiles", "word_ranks", "hash_pairs", "hadamard_matrix", "user_assignment", "prefixes_words", "sketch_reports", "sketch_freq_returnflag", "sketch_uncompressed_status",
          "signmatrix_families", "partitioned_freq_segment", "tree_candidates_event", "hashed_bits_cells", "coded_bits_returnflag_repeat3", "bloom_report_counts", "privacy_ratio", "cost_table", "session_counters", "asof_histogram", "vary_width",
          "coded_words_lang", "coded_bits_uncoded", "assisted_bits_returnflag", "collision_regimes", "predecessor_discovery", "bloom_decode", "figure_n", "corpus_draws", "heavy_hitter_runs_powerlaw", "good_pairs_quantity",
          "good_subsets_nation", "enumerate_without_dictionary", "guarantee_theory", "estimate_drift", "moving_day", "price_band_range_join", "compression_compare", "tree_trace_lang", "baseline_ln3_by_rank"]


def open_params(**how):
    """Parameters of a run whose coins are public."""
    return Params(public_coins=True, **how)


def rows(df):
    names = sorted(df.columns)
    return sorted(str(tuple(r)) for r in df.select(*[f"`{c}`" for c in names]).collect())


@pytest.mark.parametrize("name", PARITY)
def test_parity(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.sql(catalogue.ORACLES[name])
    names = sorted(want.columns)
    assert rows(catalogue.QUERIES[name](spark, SF)) == sorted(str(tuple(r)) for r in want.select(*[f'"{c}"' for c in names]).fetchall())


def people(spark, counts):
    data = [(f"{item}{i}", item) for item, k in counts.items() for i in range(k)]
    return spark.createDataFrame(data, "user_key string, item string").repartition(4)


def test_equal_forms(spark):
    pop, p = people(spark, {"a": 300, "b": 50, "c": 5}), open_params(t=4, m=16, R=6, T=16)
    items = pop.select("item").distinct()
    forms = [rows(sketch_oracle.dictionary_frequencies(pop, items, p, mode=m)) for m in ("direct", "counters", "transform")]
    assert forms[0] == forms[1] == forms[2]
    forms = [rows(sign_matrix_oracle.partitioned_estimates(pop, items, p, m)) for m in ("direct", "counters", "transform")]
    assert forms[0] == forms[1] == forms[2]


def test_unbiased_with_the_predicted_spread(spark):
    n, heavy = 6000, 2400
    pop = people(spark, {"h": heavy, **{f"x{i}": 400 for i in range(9)}})
    p = open_params(eps=2.0, t=15, m=64)
    got = {(r["seed"], r["item"]): r["est"] for r in catalogue.seeded(pop, pop.select("item").distinct(), p, list(range(10))).collect()}
    sd = 1.25 * (math.exp(2) + 1) / (math.exp(2) - 1) * math.sqrt(n)
    values = np.array([got[s, "h"] for s in range(10)])
    assert abs(values.mean() - heavy) <= 4 * sd / math.sqrt(10)
    spread = np.sqrt(np.mean([(got[s, i] - (heavy if i == "h" else 400)) ** 2 for s, i in got]))
    assert 0.7 * sd < spread < 1.4 * sd


def test_bound_of_the_plain_oracle(spark):
    pop = people(spark, {"a": 700, "b": 300})
    est = {r["item"]: r["est"] for r in sign_matrix_oracle.plain_estimates(pop, pop.select("item").distinct(), open_params(eps=1.0)).collect()}
    assert abs(est["a"] - 700) <= 3 * math.sqrt(1000 * math.log(8 / 0.05)) and abs(est["b"] - 300) <= 3 * math.sqrt(1000 * math.log(8 / 0.05))


def test_methods_find_the_same_heavy_items(spark):
    pop, p, e = people(spark, {"9": 9000, "20": 7000, "3": 100}), open_params(eps=4.0, t=15, m=64, T=64), integers(5)
    tree = {r["item"] for r in prefix_tree.tree_heavy_hitters(pop, p, e).collect()}
    brute = {r["item"] for r in prefix_tree.brute_force(pop, p, integers(5, 5)).collect()}
    warm = {r["item"] for r in histogram.top_k(hashed_bits.warm_up(pop, p, e).select("item", "est"), 2).collect()}
    full = {r["item"] for r in histogram.top_k(hashed_bits.coded(pop, p, e, "concat", 1, 1).select("item", "est"), 2).collect()}
    assert tree == brute == warm == full == {"9", "20"}
    auto = {r["item"] for r in dispatch.histogram(pop, 4.0, e, for_tests=True).collect()}
    assert {"9", "20"} <= auto


def test_nothing_heavy_and_edges(spark):
    p = open_params(eps=2.0, t=5, m=16, R=5, T=16)
    flat = spark.range(3000).selectExpr("cast(id as string) AS user_key", "cast(id % 1000 as string) AS item")
    assert prefix_tree.tree_heavy_hitters(flat, p, integers(10)).count() == 0
    empty = people(spark, {"a": 1}).limit(0)
    one = spark.createDataFrame([("u", "a")], "user_key string, item string")
    for pop in (empty, one):
        assert sketch_oracle.dictionary_frequencies(pop, spark.createDataFrame([("a",)], "item string"), p).count() == 1
        assert prefix_tree.tree_heavy_hitters(pop, p, SIX_LETTERS, threshold=1e9).count() == 0
        assert hashed_bits.warm_up(pop, p, integers(3)).count() <= p.T
    missing = spark.createDataFrame([(str(i), None) for i in range(50)], "user_key string, item string")
    assert sketch_oracle.tree_reports(missing, p, SIX_LETTERS).count() == 50
    with pytest.raises(ValueError):
        prefix_tree.tree_heavy_hitters(flat, p, SIX_LETTERS, threshold=-1e9)


def test_reports_carry_no_item(spark, tmp_path):
    pop = people(spark, {"abc": 20})
    reports = sketch_oracle.tree_reports(pop, open_params(), SIX_LETTERS)
    assert reports.columns == ["level", "pair", "row", "y1", "y2"]
    sinks.write_reports(reports, str(tmp_path / "r"))
    assert rows(sinks.read_reports(spark, str(tmp_path / "r"))) == rows(reports)
    sinks.write_counters(sketch_oracle.count(reports, ["level", "pair", "row"], "y1"), str(tmp_path / "c"))
    plan = spark.read.parquet(str(tmp_path / "c")).where("level = 2")._jdf.queryExecution().toString()
    assert "PartitionFilters: [isnotnull(level" in plan
    with pytest.raises(ValueError):
        sinks.write_reports(pop, str(tmp_path / "no"))


def test_measures(spark):
    truth = spark.createDataFrame([("a", 100), ("b", 50), ("c", 1)], "item string, f long")
    hist = spark.createDataFrame([("a", 90.0), ("z", 30.0)], "item string, est double")
    assert measures.linf_error(truth, hist).first()["linf"] == 50
    assert measures.list_error(truth, hist).first()["list_error"] == 30
    assert tuple(measures.precision_recall(truth, hist, F.lit(40)).first()) == (1, 1, 1, 0.5, 0.5)
    assert tuple(measures.check_guarantee(truth, hist, 10.0, 20.0).first()) == (1, 1, 30.0, False)
    assert [r["item"] for r in histogram.frequency_of(hist, truth).where("est > 0").collect()] == ["a"]
    assert baselines.exact_heavy_hitters(people(spark, {"a": 90, "b": 2}), 5.0).count() == 1


def test_populations(spark):
    sizes = {"word6": 81_331, "flag": 6_000, "lang": 200, "host": 50, "toxic": 87, "role": 87, "signbits": 500, "powerlaw6": 6_000}
    for name, n in sizes.items():
        assert populations.POPULATIONS[name](spark, SF).count() == n
    pop = populations.POPULATIONS["lang"](spark, SF)
    drawn = populations.sampled(pop, 3000)
    assert drawn.count() == 3000 and abs(drawn.where("item = 'en'").count() / 3000 - 127 / 200) < 0.05
    assert populations.powerlaw_rows(spark, 5000).where("item = '99'").count() > 500


def test_rare_items_vanish_from_bloom_reports(spark):
    pop = people(spark, {"common": 6000, "rare": 30})
    reports = baselines.bloom_reports(pop, LN3)
    found = baselines.bloom_decode(reports, pop.select("item").distinct(), LN3)
    est = {r["item"]: r["est"] for r in found.collect()}
    assert est["rare"] == 0 and est["common"] > 3000
    refined = {r["item"]: r["est"] for r in baselines.bloom_refine(reports, found, LN3).collect()}
    assert set(refined) == {"common"} and abs(refined["common"] - 6000) < 2500
    with pytest.raises(ValueError):
        baselines.bloom_refine(reports, found, LN3, limit=0)


def test_sql_surface(spark):
    sql_surface.register(spark)
    assert spark.sql("SELECT had_sign(3, 1), binary_rr(1, 2.0, 0)").first()[:] == (-1, 1)
    assert [r[0] for r in spark.sql("SELECT prefix FROM children(1, 5, 3)").collect()] == [32, 33, 34]
    pop, p = people(spark, {"a": 300, "b": 50}), open_params(t=5, m=16)
    items = pop.select("item").distinct()
    from ldp_hist.functions.hadamard import fwht_groups
    from ldp_hist.functions.randomizers import debias

    cells = fwht_groups(sketch_oracle.count(sketch_oracle.dictionary_reports(pop, p), ["pair", "row"]), ["pair"], "row", p.m)
    assert rows(sql_surface.sketch_query(spark, cells, items, 42, p.t, p.m, p.t * debias(p.eps))) == rows(sketch_oracle.dictionary_frequencies(pop, items, p))


def test_stream_equals_batch(spark, tmp_path):
    events = spark.read.parquet(f"{SF}/events.parquet").select(*[c.split()[0] for c in counters.EVENTS.split(", ")])
    for i in range(3):
        events.where(F.col("event_id") % 3 == i).coalesce(1).write.parquet(str(tmp_path / "in" / f"part{i}"))
    stream = spark.readStream.schema(counters.EVENTS).option("recursiveFileLookup", "true").option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    counters.stream_counters(stream, open_params(), str(tmp_path / "out"), str(tmp_path / "ck"), late="30 days").awaitTermination()
    got = counters.merged(spark.read.parquet(str(tmp_path / "out")), ["start", "pair", "row"])
    assert rows(got) == rows(counters.windowed_counters(events, open_params()).select("start", "pair", "row", "s"))


def test_stream_budget_and_duplicates(spark, tmp_path):
    data = spark.createDataFrame([(i, f"2024-01-01 00:0{i}:00", 1 + i % 2, "click", 0.0, "{}") for i in range(8)], "event_id long, t string, user_id long, event_type string, value double, props string")
    data.selectExpr("event_id", "cast(t as timestamp) AS ts", "user_id", "event_type", "value", "props").coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(counters.EVENTS).parquet(str(tmp_path / "in"))
    for name, df, n in (("spent", counters.budgeted(stream, 0.5, 1.0), 4), ("once", counters.once_per_horizon(stream), 2)):
        q = df.writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        assert spark.table(name).count() == n


def test_coins_come_from_the_key_alone(spark):
    pop = people(spark, {"a": 300, "b": 100})
    secret, public = Params(seed=1000, coin_key="secret"), open_params(seed=1000)
    ys = lambda p, **how: [tuple(r) for r in sketch_oracle.dictionary_reports(pop.coalesce(1).orderBy("user_key"), p, **how).collect()]
    assert ys(secret) == ys(secret, seed=1000) == ys(secret, seed=F.lit(1000)) != ys(public)
    assert [r[:2] for r in ys(secret)] == [r[:2] for r in ys(public)]  # the public draws are the same
    other = ys(secret.but(coin_key="other"))
    assert 100 < sum(a[2] == b[2] for a, b in zip(ys(secret), other)) < 390
    for seed in (1000, F.lit(1000)):
        assert ys(secret, seed=seed) != ys(open_params(seed=1000), seed=seed)
    assert ys(secret, run=F.lit(1)) != ys(secret, run=F.lit(2))
    keyed = Params(seed=1000, coin_key="secret")
    for make in (lambda p: sketch_oracle.tree_reports(pop, p, SIX_LETTERS), lambda p: sign_matrix_oracle.plain_reports(pop, p), lambda p: sign_matrix_oracle.partitioned_reports(pop, p),
                 lambda p: hashed_bits.warm_up(pop.withColumn("item", F.lit("1")), p, integers(3)), lambda p: baselines.bloom_reports(pop, p), lambda p: dispatch.histogram(pop, 1.0, SIX_LETTERS, coin_key=p.coin_key)):
        make(keyed)
        with pytest.raises(ValueError, match="secret"):
            make(Params())
    for bad in ({"coin_key": 42}, {"coin_key": "42"}, {"coin_key": "x", "public_coins": True}):
        with pytest.raises(ValueError):
            Params(**bad)


def test_budgets_and_preconditions_are_checked(spark):
    pop = people(spark, {"1": 300})
    with pytest.raises(ValueError, match="budget"):
        sketch_oracle.dictionary_reports(pop, open_params(eps=1.0), eps=1.5)
    with pytest.raises(ValueError, match="budget"):
        sign_matrix_oracle.partitioned_reports(pop, open_params(eps=1.0), eps=1.1)
    with pytest.raises(ValueError, match="R >= 48"):
        hashed_bits.coded(pop, open_params(strict=True), integers(5), "repeat3", 1, 1)
    with pytest.raises(ValueError, match="eps <= 1"):
        hashed_bits.warm_up(pop, open_params(strict=True), integers(5), n=300)


def test_no_word_is_lost(spark):
    """Three users: nearly all (repetition, bit) groups are empty, and all words come back all the same."""
    pop = spark.createDataFrame([(f"u{i}", "en") for i in range(3)], "user_key string, item string")
    code = codes.Code("concat", 10)
    words = hashed_bits.coded_words(pop, open_params(T=16), catalogue.TWO_LETTERS, code, 3, 3).collect()
    assert len(words) == 48 and {len(r["word"]) for r in words} == {64}
    known = {r["rep"]: sum(b >= 0 for b in r["word"]) for r in words}
    assert 1 <= sum(known.values()) <= 3
    lang = catalogue.QUERIES["coded_words_lang"](spark, SF).collect()
    assert len(lang) == 48 and any("-1" in r["word"] for r in lang)


def test_a_code_finds_what_single_bits_miss(spark):
    pop = people(spark, {"21": 4000, "9": 3000})
    got = {r["item"] for r in hashed_bits.coded(pop, open_params(eps=8.0, T=16), integers(5, 5), "concat", 2, 1).collect()}
    assert {"21", "9"} <= got


def test_regimes_and_their_limit(spark):
    pop = people(spark, {"1": 12, "4": 13})
    assert hashed_bits.regime(pop, open_params(eps=4.0), integers(3), "n", 25).count() <= 32
    with pytest.raises(ValueError, match="regime"):
        hashed_bits.regime(pop, open_params(eps=4.0), integers(3), "n2", 1000)
    direct = rows(hashed_bits.discover_predecessor(pop, open_params(eps=4.0), integers(3), 25))
    assert direct == rows(hashed_bits._final(pop.withColumn("code", F.col("item").cast("long")), hashed_bits.warm_up(pop, open_params(eps=4.0, T=1024), integers(3)).select("code"), open_params(eps=4.0), hashed_bits.Ledger(4.0)).select("code", F.col("code").cast("string").alias("item"), "est"))


def test_runs_walk_together(spark):
    pop = people(spark, {"9": 3000, "20": 2500, "3": 100})
    runs = prefix_tree.tree_runs(pop, open_params(eps=8.0, t=9, m=64), integers(5, 5), [1, 2, 3], factor=15.0).collect()
    assert {(r["run"], r["item"]) for r in runs} >= {(s, i) for s in (1, 2, 3) for i in ("9", "20")}
    assert len({r["est"] for r in runs if r["item"] == "9"}) > 1
    quality = measures.run_quality(baselines.exact_frequencies(pop), spark.createDataFrame([(1, "9"), (1, "3"), (2, "9"), (2, "20")], "run int, item string"), 1000.0, [1, 2, 3]).first()
    assert tuple(quality) == (3, 0.75, pytest.approx(0.353553), 0.5, 0.5)


@pytest.mark.parametrize(("kept", "p"), [(1 << 27, {}), (1 << 27, {"t": 31, "m": 256, "eps": 8.0}), (400, {})])
def test_runs_are_summed_as_their_reports(spark, monkeypatch, kept, p):
    """Cell by cell what the reports of every run sum to: null items and keys, several batches, nodes that a worker doesn't keep."""
    from ldp_hist.operators import run_counters as rc

    p, seeds, e = open_params(**{"eps": 2.0, "t": 9, "m": 64, **p}), [0, 3, 12], SIX_LETTERS
    words = ["the", "of", "and", "banana", "bandana", "x", "Zoë", "", None]
    data = [(None if i == 5 else "" if i == 6 else f"{i}:k", words[i * i % 9]) for i in range(2500)]
    pop = spark.createDataFrame(data, "user_key string, item string").repartition(2).persist()
    monkeypatch.setattr(rc, "KEPT", kept)
    monkeypatch.setattr(rc, "_kept", {})
    each = sketch_oracle.tree_reports(pop.withColumn("run", F.explode(F.array(*[F.lit(s) for s in seeds]))), p, e, run="run")
    want = each.groupBy("run", "level", "pair", "row").agg(F.sum("y1").alias("s"), F.sum("y2").alias("s2"), F.count("*").alias("users"))
    assert rows(rc.run_counters(pop, p, e, seeds)) == rows(want)
    assert rows(rc.run_counters(pop, p, e, seeds, second=False).drop("s2")) == rows(want.drop("s2"))
    # The same within this process, where few nodes are kept and batches are small.
    users = pop.select(e.encode(F.col("item")).alias("code"), F.coalesce(F.concat(F.lit(":"), F.col("user_key")), F.lit("")).alias("key"))
    heads = [h for s in seeds for h in (f"pub:{s}", f"coin1:{p.coins}:{s}", f"coin2:{p.coins}:{s}")]
    table = users.select("code", F.concat(*[F.sha2(F.concat(F.lit(h), F.col("key")), 256) for h in heads]).alias("thrown")).toArrow()
    work = rc._summed(tuple(seeds), p.t, p.m, e.levels, e.bits, rc.limit(rc.keep_probability(p.eps / 2)), 2)
    got = [b for b in work(iter(table.combine_chunks().to_batches(max_chunksize=300)))]
    assert sorted(str(tuple(r.values())) for b in got for r in b.to_pylist()) == sorted(str(tuple(r)) for r in want.select("run", "level", "pair", "row", "s", "s2", "users").collect())


def test_lists_of_runs_need_no_second_reports(spark):
    pop = people(spark, {"9": 3000, "20": 2500, "3": 100})
    how = (pop, open_params(eps=8.0, t=9, m=64), integers(5, 5), [1, 2, 3])
    assert rows(prefix_tree.tree_run_lists(*how)) == rows(prefix_tree.tree_runs(*how).drop("est"))
    walk = prefix_tree.descend(prefix_tree.start(*how[:3], runs=how[3], second=False))
    with pytest.raises(ValueError, match="second"):
        prefix_tree.finish(walk)
    nobody = (pop.limit(0), *how[1:])
    assert rows(prefix_tree.tree_run_lists(*nobody)) == rows(prefix_tree.tree_runs(*nobody).drop("est"))


def test_runs_take_a_row_a_user(spark):
    """The ten runs of a word share its row: nothing makes a row of every report."""
    lists = prefix_tree.start(populations.word6(spark, SF), catalogue._T31, SIX_LETTERS, runs=catalogue.SEEDS, second=False)
    plan = lists.cells._jdf.queryExecution().optimizedPlan().toString() + lists.kept[0]._jdf.queryExecution().executedPlan().toString()
    lists.close()
    assert "MapInArrow" in plan and "explode(array(0" not in plan and "explode([0" not in plan


READING = {"hadamard_matrix": 256, "hadamard_orthogonality": 256, "cost_table": 21, "predecessor_cost": 7, "operation_counts": 28}


@pytest.mark.parametrize("name", READING)
def test_closed_forms_read_a_table(spark, name):
    df, con = catalogue.QUERIES[name](spark, SF), duckdb.connect()
    assert any(f.endswith("lineitem.parquet") for f in df.inputFiles())
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{SF}/lineitem.parquet'")
    want = con.sql(catalogue.ORACLES[name])
    got = rows(df)
    assert len(got) == READING[name] and got == sorted(str(tuple(r)) for r in want.select(*[f'"{c}"' for c in sorted(want.columns)]).fetchall())
    if name == "hadamard_orthogonality":
        assert all(r["inner_product"] == 16 * (r["c1"] == r["c2"]) for r in df.collect())


def test_both_estimates_are_made_once(spark):
    plan = catalogue.QUERIES["baseline_ln3_by_rank"](spark, SF)._jdf.queryExecution().sparkPlan().toString()
    assert plan.count("FlatMapGroupsInPandas") == 1


def test_plans_of_a_beam_stay_small(spark):
    """A level's plan doesn't hold those of the levels before it twice; the beam keeps the best nodes."""
    pop = people(spark, {"9": 900, "20": 700, "3": 100})
    walk = prefix_tree.descend(prefix_tree.start(pop, open_params(eps=8.0, t=9, m=64), integers(8)), beam=3)
    sizes = [len(t._jdf.queryExecution().toString()) for t in walk.trace]
    assert max(sizes) < 2 * sizes[1]
    for level, t in enumerate(walk.trace, 1):
        nodes = sorted(((-r["est"], r["prefix"], r["kept"]) for r in t.collect()))
        assert [kept for *_, kept in nodes] == [i < 3 for i in range(len(nodes))] and len(nodes) == min(2**level, 6)
    assert {"9", "20"} <= {r["item"] for r in prefix_tree.finish(walk).collect()}


def test_draws_follow_the_corpus(spark):
    pop = people(spark, {"a": 900, "b": 90, "c": 10})
    got = {r["item"]: r["f"] for r in baselines.exact_frequencies(populations.sampled(pop, 20_000)).collect()}
    assert sum(got.values()) == 20_000 and abs(got["a"] - 18_000) < 300 and abs(got["b"] - 1_800) < 250 and 100 < got["c"] < 320
    before = populations.LOT
    try:
        populations.LOT = 1
        again = {r["item"]: r["f"] for r in baselines.exact_frequencies(populations.sampled(pop, 20_000)).collect()}
    finally:
        populations.LOT = before
    assert abs(again["a"] - 18_000) < 300 and sum(again.values()) == 20_000
    assert populations.sampled(pop.limit(0), 5).count() == 0


@pytest.mark.parametrize("lot", [150, 1000])
def test_draws_are_laid_out_in_the_order_of_items(spark, monkeypatch, lot):
    """Over several lots too: as the SQL has them, by item."""
    monkeypatch.setattr(populations, "LOT", lot)
    con = duckdb.connect()
    con.sql(f"CREATE VIEW documents AS SELECT * FROM '{SF}/documents.parquet' WHERE doc_id < 20")
    pop = populations.words(spark, SF).where(F.col("user_key").cast("long") < 20 << 20)
    assert baselines.exact_frequencies(pop).count() > 1000
    got = sorted(tuple(r) for r in baselines.exact_frequencies(populations.sampled(pop, catalogue.DRAWS)).collect())
    assert got == sorted(con.sql(catalogue.ORACLES["corpus_draws"]).fetchall())


@pytest.mark.parametrize("name", ["figure_eps", "figure_corpus_eps"])
def test_all_budgets_are_one_job(spark, monkeypatch, name):
    """Users are hashed once for all budgets, and ranks are those of draws in the order of items."""
    monkeypatch.setattr(populations, "LOT", 1000)
    con = duckdb.connect()
    for t in ("lineitem", "documents"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df, want = catalogue.QUERIES[name](spark, SF), con.sql(catalogue.ORACLES[name])
    assert df._jdf.queryExecution().sparkPlan().toString().count("FlatMapGroupsInPandas") == 1
    assert rows(df) == sorted(str(tuple(r)) for r in want.select(*[f'"{c}"' for c in sorted(want.columns)]).fetchall())


def test_as_of_across_hours(spark):
    events = spark.createDataFrame([(i, f"2024-01-01 {h:02d}:30:00", k) for i, (h, k) in enumerate([(0, "a"), (1, "a"), (5, "a"), (5, "b"), (9, "a")])], "event_id long, t string, item string").selectExpr("event_id", "cast(t as timestamp) AS ts", "item")
    published = spark.createDataFrame([("2024-01-01 01:00:00", "a", 1.0), ("2024-01-01 01:45:00", "a", 2.0), ("2024-01-01 09:30:00", "a", 3.0)], "t string, item string, est double").selectExpr("cast(t as timestamp) AS ts", "item", "est")
    assert {r["event_id"]: r["est"] for r in histogram.as_of(events, published).collect()} == {0: None, 1: 1.0, 2: 2.0, 3: None, 4: 3.0}


def test_range_join_and_merge_join(spark):
    values = spark.createDataFrame([(str(i), float(i)) for i in range(100)], "user_key string, value double")
    bands = spark.createDataFrame([(0.0, 10.0, "low"), (10.0, 95.0, "mid")], "low double, high double, name string")
    got = histogram.range_join(values, bands, 7.0).groupBy("name").count().collect()
    assert {r["name"]: r["count"] for r in got} == {"low": 10, "mid": 85}
    truth = baselines.exact_frequencies(people(spark, {"a": 9, "b": 2}))
    merged = histogram.merged_truth(truth, spark.createDataFrame([("a", 8.0), ("z", 1.0)], "item string, est double"))
    assert {tuple(r) for r in merged.collect()} == {("a", 9, 8.0), ("b", 2, 0.0), ("z", 0, 1.0)} and "SortMergeJoin" in merged._jdf.queryExecution().toString()


def test_approximate_counts(spark):
    exact, near = (catalogue.QUERIES[n](spark, SF).first() for n in ("distinct_words", "distinct_words_approx"))
    assert all(abs(near[c] - exact[c]) <= 0.1 * exact[c] for c in ("words", "word6"))
