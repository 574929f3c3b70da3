"""SQL functions over the engine: signs, randomised bits and hashes; tree children and sketch look-ups."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

FUNCTIONS = {
    "had_sign": ("r BIGINT, c BIGINT", "INT", "cast(1 - 2 * (bit_count(r & c) % 2) AS INT)"),
    "bucket_hash": ("seed INT, j INT, x STRING, m BIGINT", "BIGINT", "cast(conv(substring(sha2(concat_ws(':', 'pair', seed, j, x), 256), 1, 8), 16, 10) AS BIGINT) % m"),
    "sign_hash": ("seed INT, j INT, x STRING", "INT", "cast(1 - 2 * (cast(conv(substring(sha2(concat_ws(':', 'pair', seed, j, x), 256), 9, 1), 16, 10) AS BIGINT) % 2) AS INT)"),
    "binary_rr": ("x INT, eps DOUBLE, coin BIGINT", "INT", "CASE WHEN coin < cast(floor(exp(eps) / (exp(eps) + 1) * 4503599627370496) AS BIGINT) THEN x ELSE -x END"),
}


@udtf(returnType="prefix: bigint")
class Children:
    """A prefix's children: TABLE children(prefix, bits, symbols)."""

    def eval(self, prefix: int, bits: int, symbols: int):
        for s in range(symbols):
            yield (prefix << bits) + s,


def register(spark: SparkSession) -> None:
    for name, (args, kind, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({args}) RETURNS {kind} RETURN {body}")
    spark.udtf.register("children", Children)


def sketch_query(spark: SparkSession, cells: DataFrame, items: DataFrame, seed: int, t: int, m: int, scale: float) -> DataFrame:
    """Look-ups in transformed cells (pair, cell, v) with SQL only; ``register`` first."""
    return spark.sql(
        """SELECT item, round(:scale * median(g * coalesce(v, 0)), 4) AS est FROM (
             SELECT item, p.pair, sign_hash(:seed, p.pair, item) AS g, bucket_hash(:seed, p.pair, item, :m) AS cell
             FROM {items}, LATERAL (SELECT explode(sequence(0, :t - 1)) AS pair) p) x
           LEFT JOIN {cells} c ON c.pair = x.pair AND c.cell = x.cell GROUP BY item""",
        args={"scale": scale, "seed": seed, "t": t, "m": m}, items=items, cells=cells,
    )
