"""Populations: (user_key, item), one row a user, from the given tables or from row keys."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ldp_hist.functions.encoding import SIX_LETTERS
from ldp_hist.functions.hashing import digest, hex_slice

LETTERS = "abcdefghijklmnopqrstuvwxyz"
#: The power law: density proportional to x**(POWER-1) on the unit interval, in BINS equal bins.
POWER, BINS = 15, 100


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def line_key():
    return F.concat_ws(":", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")


def column(name: str, key: str, item: str) -> Callable[[SparkSession, str], DataFrame]:
    def read(spark: SparkSession, sf_dir: str) -> DataFrame:
        return table(spark, sf_dir, name).select(F.col(key).cast("string").alias("user_key"), F.col(item).cast("string").alias("item"))

    return read


def lines(item: str) -> Callable[[SparkSession, str], DataFrame]:
    """Order lines; the four-column key is their public index."""
    return lambda spark, d: table(spark, d, "lineitem").select(line_key().alias("user_key"), F.expr(item).cast("string").alias("item"))


def words(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Word occurrences of documents: privacy is per occurrence, not per author (see ``bounded``)."""
    found = table(spark, sf_dir, "documents").select("doc_id", F.posexplode(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0))).alias("pos", "item"))
    return found.select((F.col("doc_id") * (1 << 20) + F.col("pos")).cast("string").alias("user_key"), "item")


def word6(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same, cut or padded to six letters."""
    return words(spark, sf_dir).select("user_key", SIX_LETTERS.fit(F.col("item")).alias("item"))


def hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select(F.col("page_id").cast("string").alias("user_key"), F.regexp_extract("url", "^[a-z]+://([^/:?#]+)", 1).alias("item"))


def nations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Customers with their nation's name: a broadcast join, nations being 25."""
    names = F.broadcast(table(spark, sf_dir, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name"))
    return table(spark, sf_dir, "customer").join(names, "c_nationkey").select(F.col("c_custkey").cast("string").alias("user_key"), F.col("n_name").alias("item"))


def brands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order lines with the brand of their part."""
    parts = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    return table(spark, sf_dir, "lineitem").join(parts, "l_partkey").select(line_key().alias("user_key"), F.col("p_brand").alias("item"))


def props(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.col("event_id").cast("string").alias("user_key"), F.get_json_object("props", "$.k").alias("item"))


def bounded_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One event a user, the latest (then the one of the greatest id): contribution bounding."""
    return bounded(table(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "event_type")


def bounded(df: DataFrame, user: str, order: list[str], item: str) -> DataFrame:
    """A user's last item, as an aggregation with map-side combination: a hot user is no hot task."""
    return df.groupBy(F.col(user).cast("string").alias("user_key")).agg(F.max_by(F.col(item), F.struct(*order)).cast("string").alias("item"))


def power_bin(key) -> F.Column:
    u = hex_slice(digest("pow", 0, key), 1, 13) / float(1 << 52)
    return F.least(F.floor(BINS * F.pow(u, F.lit(1 / POWER))).cast("int"), F.lit(BINS - 1))


def powerlaw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Synthetic power law: each order-line key is a uniform draw through the inverse distribution function."""
    return table(spark, sf_dir, "lineitem").select(line_key().alias("user_key")).select("user_key", power_bin(F.col("user_key")).cast("string").alias("item"))


def powerlaw_rows(spark: SparkSession, n: int, partitions: int | None = None) -> DataFrame:
    """The same for any number of users."""
    return spark.range(0, n, 1, partitions).select(F.col("id").cast("string").alias("user_key")).select("user_key", power_bin(F.col("user_key")).cast("string").alias("item"))


def bin_words(spark: SparkSession) -> DataFrame:
    """(item, word): a letter string for each of the ``BINS`` bins, eight letters drawn and cut to six."""
    d = digest("word", 0, F.col("item"))
    eight = F.concat(*[F.substring(F.lit(LETTERS), (hex_slice(d, 1 + 2 * i, 2) % 26 + 1).cast("int"), F.lit(1)) for i in range(8)])
    return spark.range(BINS).select(F.col("id").cast("string").alias("item")).select("item", SIX_LETTERS.fit(eight).alias("word"))


def powerlaw6(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bins as letter strings; the table of bins, a hundred rows, is what is sent around."""
    return powerlaw(spark, sf_dir).join(F.broadcast(bin_words(spark)), "item").select("user_key", F.col("word").alias("item"))


#: Items of a dictionary that are put in order by one task, when draws are laid out.
LOT = 100_000


def _lot(item: F.Column, bounds: list[str], first: int = 0) -> F.Column:
    """How many of the sorted ``bounds`` are at most ``item``, by halves; null counts as the greatest."""
    if not bounds:
        return F.lit(first)
    at = len(bounds) // 2
    return F.when(item < F.lit(bounds[at]), _lot(item, bounds[:at], first)).otherwise(_lot(item, bounds[at + 1:], first + at + 1))


def sampled(pop: DataFrame, n: int, seed: int = 0) -> DataFrame:
    """``n`` draws of an item with replacement, each by the hash of its number.

    Items are laid out along a line in their order, each as long as it is frequent, and a draw is a point on it. Lots are ranges of
    items; their bounds come from a hashed share of the items, which decides how even lots are and nothing else. The line is cut into
    cells that points and items are dealt to, so a frequent item lies in many cells and no task has it all.
    """
    spark = pop.sparkSession
    freq = pop.groupBy("item").agg(F.count("*").alias("f")).persist()
    items, total = freq.agg(F.count("*"), F.sum("f")).first()
    lots, length = 1 + (items or 0) // LOT, total or 0
    some = sorted(r["item"] for r in freq.where(F.pmod(F.xxhash64("item"), F.lit(max(1, items // (64 * lots)))) == 0).where("item IS NOT NULL").select("item").collect()) if lots > 1 else []
    bounds = sorted({some[i * len(some) // lots] for i in range(1, lots)}) if some else []
    dealt = freq.withColumn("lot", _lot(F.col("item"), bounds))
    sizes = dealt.groupBy("lot").agg(F.sum("f").alias("k"))
    starts = sizes.select("lot", F.coalesce(F.sum("k").over(Window.orderBy("lot").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("start"))
    end = F.sum("f").over(Window.partitionBy("lot").orderBy(F.asc_nulls_last("item")).rowsBetween(Window.unboundedPreceding, 0))
    line = dealt.withColumn("end", end).join(starts, "lot").select("item", (F.col("start") + F.col("end") - F.col("f")).alias("low"), (F.col("start") + F.col("end")).alias("high"))
    width = max(1, length // 4096)
    cells = line.select("item", "low", "high", F.explode(F.sequence(F.floor(F.col("low") / width), F.floor((F.col("high") - 1) / width))).alias("cell"))
    picks = spark.range(n).select(F.col("id").cast("string").alias("user_key"), (hex_slice(digest("draw", seed, F.col("id")), 1, 13) % max(length, 1)).alias("at"))
    return picks.withColumn("cell", F.floor(F.col("at") / width)).join(cells, "cell").where("at >= low AND at < high").select("user_key", "item")


def signbits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Signs of an embedding's first eight coordinates as a number of eight bits."""
    bits = F.aggregate(F.slice("embedding", 1, 8), F.lit(0), lambda a, x: a * 2 + F.when(x > 0, 1).otherwise(0))
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("user_key"), bits.cast("string").alias("item"))


def roles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "conversations").select(F.concat_ws(":", "conv_id", "turn").alias("user_key"), F.col("role").alias("item"))


POPULATIONS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "flag": lines("l_returnflag"), "status": lines("l_linestatus"), "line": lines("l_linenumber"), "discount": lines("cast(round(l_discount * 100) as bigint)"),
    "quantity": lines("cast(l_quantity as bigint)"), "shipdate": lines("datediff(l_shipdate, date '1992-01-01')"), "supp": lines("l_suppkey"), "part": lines("l_partkey"),
    "priority": column("orders", "o_orderkey", "o_orderpriority"), "segment": column("customer", "c_custkey", "c_mktsegment"), "lang": column("documents", "doc_id", "lang"),
    "event": column("events", "event_id", "event_type"), "toxic": column("labels", "doc_id", "toxic"), "quality": column("labels", "doc_id", "quality"),
    "nation": nations, "brand": brands, "words": words, "word6": word6, "host": hosts, "prop": props, "event_user": bounded_events,
    "powerlaw": powerlaw, "powerlaw6": powerlaw6, "signbits": signbits, "role": roles,
}
