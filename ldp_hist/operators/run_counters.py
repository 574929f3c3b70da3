"""Counters of many runs over the same users, a row a user rather than a report.

A run has a public draw and coins of its own for every user: one digest for the draw and one for each report's coin, which nothing
shares. They are one string in the user's row. What a report says before its coin is thrown depends on the node, the pair and the run
and not on the user, so a worker hashes that once and keeps it; with the digests it is summed in Python, cell by cell.
"""

from __future__ import annotations

import hashlib
from binascii import unhexlify
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.encoding import Encoding
from ldp_hist.functions.randomizers import keep_probability
from ldp_hist.functions.randomness import limit
from ldp_hist.plans.params import Params
from ldp_hist.plans.privacy import Ledger

#: Cells that a task sums in arrays of its own (24 bytes each at most), and bytes that a worker keeps of hashed nodes; nodes beyond are hashed each time.
CELLS, KEPT = 1 << 22, 128 << 20
#: More partitions than there are: merging down to so many merges none, and digests are compiled apart from what reads the users (in one method they are too long for the JIT).
APART = 1 << 20
SCHEMA = "run int, level int, pair int, row long, s long, s2 long, users long"
_kept: dict[tuple, Nodes] = {}


def fits(p: Params, encoding: Encoding, seeds: list[int]) -> bool:
    """Whether the cells of all runs can be summed in a task's arrays."""
    return len(seeds) * encoding.levels * p.t * p.m <= CELLS


class Nodes:
    """What nodes hash to in every run and pair, twice the cell and one for a sign of -1: known after the first look-up."""

    def __init__(self, seeds: tuple[int, ...], t: int, m: int, levels: int, bits: int):
        self.seeds, self.t, self.m, self.levels, self.bits = seeds, t, m, levels, bits
        kind = np.min_scalar_type(-2 * m - 1)
        self.most = max(1, KEPT // (len(seeds) * t * kind.itemsize))
        self.said = np.zeros(self.most * len(seeds) * t, kind)  # 0: not known, else one more than the value; pages are taken as they are written
        self.slots: list[dict[int, int]] = [{} for _ in range(levels)]
        self.used = 0
        self.codes, self.rows = np.empty(0, np.int64), np.empty((0, levels), np.int64)  # codes met before, in order, and their nodes' slots

    def _slot(self, level: int, prefix: int) -> int:
        slot = self.slots[level - 1].get(prefix, -1)
        if slot < 0 and self.used < self.most:
            slot = self.slots[level - 1][prefix] = self.used
            self.used += 1
        return slot

    def paths(self, codes: np.ndarray) -> np.ndarray:
        """The slots of every code's nodes, a column a level; -1 for a node that is not kept."""
        if len(self.codes) > self.most:
            self.codes, self.rows = self.codes[:0], self.rows[:0]
        new = codes
        if len(self.codes):
            new = codes[self.codes[np.searchsorted(self.codes, codes).clip(max=len(self.codes) - 1)] != codes]
        if len(new):
            more = np.unique(new)
            rows = np.empty((len(more), self.levels), np.int64)
            for level in range(1, self.levels + 1):
                prefixes = more >> self.bits * (self.levels - level)
                first = np.flatnonzero(np.r_[True, prefixes[1:] != prefixes[:-1]])
                slots = [self._slot(level, x) for x in prefixes[first].tolist()]
                rows[:, level - 1] = np.repeat(slots, np.diff(np.r_[first, len(prefixes)]))
            where = np.searchsorted(self.codes, more)
            self.codes, self.rows = np.insert(self.codes, where, more), np.insert(self.rows, where, rows, axis=0)
        return self.rows[np.searchsorted(self.codes, codes)]

    def look_up(self, run: int, slots: np.ndarray, codes: np.ndarray, level: np.ndarray, pair: np.ndarray) -> np.ndarray:
        """The values of the nodes on ``codes`` at ``level``, in the run and each one's pair."""
        at = (slots * len(self.seeds) + run) * self.t + pair
        found = self.said[np.maximum(at, 0)].astype(np.int64)
        found[slots < 0] = 0
        new = np.flatnonzero(found == 0)
        if len(new):
            prefixes = codes[new] >> self.bits * (self.levels - level[new])
            seed = self.seeds[run]
            raw = np.array([int.from_bytes(hashlib.sha256(b"pair:%d:%d:%d.%d" % (seed, j, k, x)).digest()[:5], "big")
                            for j, k, x in zip(pair[new].tolist(), level[new].tolist(), prefixes.tolist(), strict=True)], np.int64)
            found[new] = (raw >> 8) % self.m * 2 + (raw >> 4 & 1) + 1
            keep = new[slots[new] >= 0]
            self.said[at[keep]] = found[keep]
        return found - 1


def _nodes(*key) -> Nodes:
    """The worker's own, kept from task to task; one at a time."""
    if key not in _kept:
        _kept.clear()
        _kept[key] = Nodes(*key)
    return _kept[key]


def _hex(column: pa.Array, digests: int) -> np.ndarray:
    """A column of strings of so many digests, by user, digest and hex digit."""
    column = column.cast(pa.large_string())
    first = int(np.frombuffer(column.buffers()[1], np.int64, 1, column.offset * 8)[0])
    return np.frombuffer(column.buffers()[2], np.uint8, len(column) * digests * 64, first).reshape(-1, digests, 64)


def _below(digits: np.ndarray, bound: int) -> np.ndarray:
    """Whether the first 13 hex digits are below ``bound``; eight decide, but for ties."""
    if bound >= 1 << 52:
        return np.ones(len(digits), bool)
    text = f"{bound:013x}".encode()
    head = np.ascontiguousarray(digits[:, :8]).view(">u8").ravel().astype(np.uint64)
    edge = np.uint64(int.from_bytes(text[:8], "big"))
    out = head < edge
    for i in np.flatnonzero(head == edge).tolist():
        out[i] = digits[i, 8:13].tobytes() < text[8:]
    return out


def _summed(seeds: tuple[int, ...], t: int, m: int, levels: int, bits: int, bound: int, reports: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes, size = _nodes(seeds, t, m, levels, bits), levels * t * m
        sums = np.zeros((len(seeds), reports, size), np.int64)
        users = np.zeros((len(seeds), size), np.int64)
        for batch in batches:
            if not batch.num_rows:
                continue
            codes = batch.column(0).to_numpy()
            paths, one = nodes.paths(codes), np.ones(len(codes), np.int64)
            last, each = np.full(len(codes), levels), np.arange(len(codes))
            digests = _hex(batch.column(1), len(seeds) * (1 + reports))
            for i in range(len(seeds)):
                draw, *coins = (digests[:, i * (1 + reports) + k] for k in range(1 + reports))
                own = np.frombuffer(unhexlify(np.ascontiguousarray(draw[:, :24])), ">u4").reshape(-1, 3).astype(np.uint32)
                level, pair, row = (own[:, k] % np.uint32(n) for k, n in enumerate((levels, t, m)))
                level, pair, row = level.astype(np.int64) + 1, pair.astype(np.int64), row.astype(np.int64)
                cell = ((level - 1) * t + pair) * m + row
                np.add.at(users[i], cell, one)
                for k, at in enumerate((level, last)[:reports]):
                    said = nodes.look_up(i, paths[each, at - 1], codes, at, pair)
                    turned = (np.bitwise_count(row & said >> 1) + said + ~_below(coins[k], bound)) & 1
                    np.add.at(sums[i, k], cell, 1 - 2 * turned)
        for i, seed in enumerate(seeds):
            at = np.flatnonzero(users[i])
            two = [sums[i, k][at] for k in range(reports)] + [None] * (2 - reports)
            columns = [np.full(len(at), seed, np.int32), (at // (t * m) + 1).astype(np.int32), (at // m % t).astype(np.int32), at % m, *two, users[i][at]]
            kinds = [pa.int32()] * 3 + [pa.int64()] * 4
            names = ["run", "level", "pair", "row", "s", "s2", "users"]
            yield pa.RecordBatch.from_arrays([pa.nulls(len(at), k) if c is None else pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names)

    return run


def run_counters(pop: DataFrame, p: Params, encoding: Encoding, seeds: list[int], second: bool = True) -> DataFrame:
    """(run, level, pair, row, s, s2, users): the sums of ``tree_reports`` of every run, and how many reports are in them.

    Without ``second`` the reports on whole items are not summed and s2 is null. Users send them all the same: their budget is spent.
    """
    if not fits(p, encoding, seeds):
        raise ValueError("too many cells for a task's arrays")
    ledger = Ledger.of(p)
    ledger.spend("prefix", p.eps / 2)
    ledger.spend("item", p.eps / 2)
    phases = range(1, 3 if second else 2)
    # As ``digest`` joins them, with what is the same for all users joined beforehand.
    users = pop.select(encoding.encode(F.col("item")).alias("code"), F.coalesce(F.concat(F.lit(":"), F.col("user_key")), F.lit("")).alias("key")).coalesce(APART)
    thrown = [F.sha2(F.concat(F.lit(head), F.col("key")), 256) for s in seeds for head in (f"pub:{s}", *(f"coin{phase}:{p.coins}:{s}" for phase in phases))]
    work = _summed(tuple(seeds), p.t, p.m, encoding.levels, encoding.bits, limit(keep_probability(p.eps / 2)), len(phases))
    parts = users.select("code", F.concat(*thrown).alias("thrown")).mapInArrow(work, SCHEMA)
    return parts.groupBy("run", "level", "pair", "row").agg(*[F.sum(c).alias(c) for c in ("s", "s2", "users")])
