"""Entries of the sign matrix on demand, and the fast transform of counter vectors."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def had_sign(r: Column, c: Column) -> Column:
    """Entry (r, c) of the Hadamard matrix, +1 or -1: the parity of the bits that r and c share."""
    return (1 - 2 * (F.bit_count(r.cast("long").bitwiseAND(c.cast("long"))) % 2)).cast("int")


def fwht(vector: np.ndarray) -> np.ndarray:
    """The Hadamard transform of a vector of 2**k integers, in k passes; twice gives 2**k times the vector."""
    out = vector.astype(np.int64)
    step = 1
    while step < len(out):
        pairs = out.reshape(-1, 2, step)
        out = np.stack((pairs[:, 0] + pairs[:, 1], pairs[:, 0] - pairs[:, 1]), axis=1).reshape(-1)
        step *= 2
    return out


def fwht_groups(counters: DataFrame, keys: list[str], index: str, m: int) -> DataFrame:
    """``keys``, cell, v: the transform of each group's vector (``index``, s) of length ``m``.

    One group is at most m cells, whatever the number of users; groups are as many as pairs times levels.
    """
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        vector = np.zeros(m, np.int64)
        np.add.at(vector, pdf[index].to_numpy(), pdf["s"].to_numpy())
        head = {k: pdf[k].iloc[0] for k in keys}
        return pd.DataFrame({**{k: np.full(m, v) for k, v in head.items()}, "cell": np.arange(m), "v": fwht(vector)})

    kinds = {f.name: f.dataType for f in counters.schema.fields}
    schema = T.StructType([T.StructField(k, kinds[k]) for k in keys] + [T.StructField("cell", T.LongType()), T.StructField("v", T.LongType())])
    return counters.groupBy(*keys).applyInPandas(run, schema)
