"""Closed forms of the cost and error table, and counts of the operations that a run needs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.plans.params import Params

#: Asymptotic rows with all constants one: server time, user time, server memory, communication, error.
METHODS = ("tree", "hashed_bits", "predecessor")


def cost_table(sizes: DataFrame, log_d: int, eps: float) -> DataFrame:
    """method, columns of ``sizes``, server_time, user_time, server_memory, user_memory, communication_bits, error; rounded.

    ``sizes`` has the number of users, n, of each population. The earlier protocol's row is the one with public randomness for its
    users' time; their memory isn't published.
    """
    rows = sizes.select(F.explode(F.array(*[F.lit(m) for m in METHODS])).alias("method"), "*")
    log_n, d = F.log2("n"), F.lit(float(log_d))
    longest = F.pow(F.greatest(log_n, d), F.lit(2.0))
    tree, hashed = F.col("method") == "tree", F.col("method") == "hashed_bits"

    def pick(a, b, c, name, places=3):
        return F.round(F.when(tree, a).when(hashed, b).otherwise(c), places).alias(name)

    n, root = F.col("n").cast("double"), F.sqrt("n")
    return rows.select(
        "method", *sizes.columns,
        pick(n * F.sqrt(d), n, n * n * root, "server_time", 0),
        pick(longest, longest, n, "user_time"),
        pick(root * F.pow(log_n, F.lit(1.5)) * d, root, n * n, "server_memory", 0),
        pick(F.greatest(log_n, d), F.greatest(log_n, d), F.lit(None).cast("double"), "user_memory"),
        pick(F.lit(2.0), F.lit(2.0), F.lit(1.0), "communication_bits"),
        pick(F.sqrt(n * log_n * d) / eps, F.sqrt(n * d) / eps, F.sqrt(n * d) / eps, "error"),
    )


def lower_bound(n: int, log_d: int, eps: float) -> float:
    """The error no local protocol avoids, constants aside; a curator's error does not depend on n."""
    return (n * log_d) ** 0.5 / eps


def operations(method: str, n: int | Column, p: Params, levels: int, nodes: int) -> dict[str, int | Column]:
    """Hashes, additions and look-ups on the server, report bits, and counters held, of a number of users or a column of such."""
    log_m, log_T = p.m.bit_length() - 1, p.T.bit_length()
    if method == "direct":
        asked, share = n * nodes, max(levels, 1)
        return {"hashes": nodes * p.t, "additions": ((asked - asked % share) / share).cast("long") if isinstance(n, Column) else asked // share, "look_ups": 0, "bits": 2 * n, "cells": 0}
    if method == "counters":
        return {"hashes": nodes * p.t, "additions": 2 * n + nodes * p.t * p.m, "look_ups": 0, "bits": 2 * n, "cells": p.m * p.t * (levels + 1)}
    if method == "transform":
        return {"hashes": nodes * p.t, "additions": 2 * n + (levels + 1) * p.t * p.m * log_m, "look_ups": nodes * p.t, "bits": 2 * n, "cells": p.m * p.t * (levels + 1)}
    if method == "partitioned":
        return {"hashes": nodes * p.R, "additions": n + p.R * 2 * p.T * log_T, "look_ups": nodes * p.R, "bits": n, "cells": 2 * p.R * p.T}
    raise ValueError(method)
