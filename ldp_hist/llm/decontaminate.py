"""Benchmark decontamination: SimHash of item-sized windows, multi-index candidates, exact verification."""

from __future__ import annotations

import functools
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ldp_hist.llm.shared import packed
from ldp_hist.llm.words import ALPHANUMERIC, mix, shingle_hashes, word_hashes

#: Benchmark text is sent to the executors in parts of about this many bytes, each with a pass of its own.
PART_BYTES = 16 << 20
#: Fingerprints have 256 bits in 16 blocks. Two of a weighted similarity of 0.8 differ by 39 bits on average, with a
#: standard deviation of under 7 for items of 20 shingles or more; RADIUS is over three and a half of these above.
WORDS, BLOCKS, RADIUS = 4, 16, 63
WIDTH = 64 * WORDS // BLOCKS
#: RADIUS // BLOCKS flips are shared out: items are filed under values one flip away, windows ask for two flips more.
FILED, ASKED = 1, RADIUS // BLOCKS - 1
_SALT = mix(np.arange(1, WORDS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))


def _flips(most: int) -> np.ndarray:
    return np.array([sum(1 << b for b in c) for n in range(most + 1) for c in combinations(range(WIDTH), n)], np.uint32)


def _words(text: str | None) -> np.ndarray:
    return word_hashes((text or "").lower().encode("utf-8", "surrogatepass"), ALPHANUMERIC)[2]


def weighted_similarity(a: np.ndarray, b: np.ndarray) -> float:
    """The sum of the lesser over the sum of the greater multiplicities of shingles (weighted Jaccard)."""
    (x, n), (y, m) = np.unique(a, return_counts=True), np.unique(b, return_counts=True)
    at = np.minimum(np.searchsorted(y, x), max(len(y) - 1, 0))
    both = int(np.minimum(n, m[at])[y[at] == x].sum()) if len(y) else 0
    total = len(a) + len(b) - both
    return both / total if total else 0.0


def window_prints(shingles: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """(windows, BLOCKS): the 256-bit SimHash of every window shingles[start:end], as blocks of 16 bits.

    Running sums of the bits give a window's votes as one difference, however much the windows overlap.
    """
    hashes = mix(shingles[:, None] + _SALT[None, :])
    bits = np.unpackbits(np.ascontiguousarray(hashes, "<u8").view(np.uint8), axis=1, bitorder="little")
    sums = np.zeros((len(bits) + 1, 64 * WORDS), np.int32)
    np.cumsum(bits, axis=0, out=sums[1:])
    ones = sums[ends] - sums[starts]
    majority = 2 * ones > (ends - starts)[:, None]
    return np.packbits(majority, axis=1, bitorder="little").view("<u2").astype(np.uint32)


class Index:
    """Fingerprints of benchmark items under a multi-index, as sorted arrays.

    Fingerprints within ``RADIUS`` differ by RADIUS // BLOCKS = 3 bits or fewer in some block (pigeonhole). An item is filed
    under the 17 values that are up to one flip from each of its blocks; a window asks for the 137 values up to
    two flips from its own, so the two meet in that block and no item within the radius is missed.
    """

    def __init__(self, items: list[tuple[int, str]], shingle: int):
        self.shingle, ids, shingles, sizes = shingle, [], [], []
        for item_id, text in items:
            words = _words(text)
            if len(words):
                ids.append(item_id)
                shingles.append(shingle_hashes(words, shingle))
                sizes.append(len(words))
        self.ids, self.sizes = np.array(ids, np.int64), np.array(sizes, np.int64)
        self.starts = np.concatenate(([0], np.cumsum([len(s) for s in shingles]))).astype(np.int64)
        self.shingles = np.concatenate(shingles) if shingles else np.zeros(0, np.uint64)
        self.widths = np.minimum(self.sizes, shingle)
        self.prints = np.concatenate([window_prints(s, np.array([0]), np.array([len(s)])) for s in shingles]) if shingles else np.zeros((0, BLOCKS), np.uint32)
        number = np.repeat(np.arange(len(ids)), self.starts[1:] - self.starts[:-1])
        order = np.argsort(self.shingles, kind="stable")
        self.known, self.holder = self.shingles[order], number[order]
        flips = _flips(FILED)
        keys = (np.arange(BLOCKS, dtype=np.uint32)[None, :, None] << np.uint32(WIDTH)) | (self.prints[:, :, None] ^ flips[None, None, :])
        owner = np.broadcast_to(np.arange(len(ids))[:, None, None], keys.shape).reshape(-1)
        order = np.argsort(keys.reshape(-1), kind="stable")
        self.filed, self.owner = keys.reshape(-1)[order], owner[order]

    @functools.cached_property
    def probes(self) -> np.ndarray:
        return _flips(ASKED)

    def near(self, fingerprint: np.ndarray) -> np.ndarray:
        """Numbers of all items whose fingerprint is within the radius."""
        keys = ((np.arange(BLOCKS, dtype=np.uint32)[:, None] << np.uint32(WIDTH)) | (fingerprint[:, None] ^ self.probes[None, :])).reshape(-1)
        low, high = np.searchsorted(self.filed, keys), np.searchsorted(self.filed, keys, "right")
        hit = np.flatnonzero(high > low)
        if not len(hit):
            return np.zeros(0, np.int64)
        found = np.unique(np.concatenate([self.owner[a:b] for a, b in zip(low[hit].tolist(), high[hit].tolist(), strict=True)]))
        return found[np.bitwise_count(self.prints[found] ^ fingerprint[None, :]).sum(axis=1) <= RADIUS]

    def matches(self, text: str | None, similarity: float) -> dict[int, float]:
        """The best similarity of each item that some window of the text reaches ``similarity`` with.

        A window slides over every word. Two multisets of n and m shingles that are s alike share at least s(n+m)/(1+s) of
        them, so windows with fewer shingles of the benchmark are passed over; running counts say how many each has.
        """
        words, best = _words(text), {}
        if not len(words) or not len(self.known):
            return best
        for k in np.unique(self.widths).tolist():
            if len(words) < k:
                continue
            shingles = shingle_hashes(words, k)
            low = np.searchsorted(self.known, shingles)
            hits = self.known[np.minimum(low, len(self.known) - 1)] == shingles
            if not hits.any():
                continue
            high = np.searchsorted(self.known, shingles[hits], "right")
            holders = np.unique(np.concatenate([self.holder[a:b] for a, b in zip(low[hits].tolist(), high.tolist(), strict=True)]))
            count = np.concatenate(([0], np.cumsum(hits)))
            first = np.arange(len(shingles))
            for size in np.unique(self.sizes[holders[self.widths[holders] == k]]).tolist():
                m = size - k + 1
                last = np.minimum(first + m, len(shingles))
                shared = count[last] - count[first]
                able = np.flatnonzero(shared * (1 + similarity) >= similarity * (last - first + m) - 1e-9)
                for at in range(0, len(able), 4096):
                    self._verify(shingles, able[at : at + 4096], last, m, k, similarity, best)
        return best

    def _verify(self, shingles: np.ndarray, starts: np.ndarray, last: np.ndarray, m: int, k: int, similarity: float, best: dict[int, float]) -> None:
        a, b = int(starts[0]), int(last[starts[-1]])
        prints = window_prints(shingles[a:b], starts - a, last[starts] - a)
        for start, fingerprint in zip(starts.tolist(), prints, strict=True):
            window = None
            for item in self.near(fingerprint).tolist():
                if self.widths[item] == k and best.get(item, 0) < 1:
                    window = shingles[start : start + m] if window is None else window
                    s = weighted_similarity(window, self.shingles[self.starts[item] : self.starts[item + 1]])
                    if s >= similarity and s > best.get(item, 0):
                        best[item] = s


def _find(index, similarity: float):
    def run(batches):
        held = index.value
        for batch in batches:
            found = [held.matches(t.as_py(), similarity) for t in batch.column("row").field("text")]
            items = [sorted({int(held.ids[i]) for i in m}) for m in found]
            top = [max(m.values(), default=0.0) for m in found]
            yield pa.record_batch([*batch.columns, pa.array(items, pa.list_(pa.int64())), pa.array(top, pa.float64())],
                                  names=[*batch.schema.names, "item_ids", "similarity"])

    return run


def contamination(docs: DataFrame, benchmark: DataFrame, shingle: int = 5, similarity: float = 0.8, part_bytes: int = PART_BYTES) -> DataFrame:
    """``row`` (all columns of ``docs``) with item_ids (sorted array) and similarity (the best, or 0).

    Words are maximal runs of letters and digits in lower case. A window as many words long as an item begins at every word
    (those at the end of the text are shorter); its SimHash asks the multi-index for items within the radius, and
    the weighted similarity of the shingles themselves decides. Order within an item does not matter beyond
    its shingles. Items of fewer words than a shingle match as a whole. Items without a word, null items and null texts
    match nothing; repeated rows and items get equal answers; with an empty benchmark nothing matches; other columns, whatever
    their names, are carried.

    The benchmark is dealt into parts of about ``part_bytes`` bytes by hash. The driver holds one part at a time to build its index, a
    worker one part's arrays (about ten times its text); each part is one more pass over ``docs``.
    """
    spark, rows = docs.sparkSession, packed(docs)
    clean = benchmark.where(F.col("item_id").isNotNull() & F.col("text").isNotNull()).select(F.col("item_id").cast("long"), "text").distinct()
    size = clean.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    parts = 1 + size // part_bytes
    out, schema = rows, T.StructType(list(rows.schema.fields))
    for n in range(parts):
        own = clean.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == n)
        index = spark.sparkContext.broadcast(Index(sorted((r[0], r[1]) for r in own.collect()), shingle))
        schema = T.StructType(list(schema.fields)).add("item_ids", T.ArrayType(T.LongType())).add("similarity", "double")
        out = out.mapInArrow(_find(index, similarity), schema)
        out = out.withColumnsRenamed({"item_ids": f"items{n}", "similarity": f"similarity{n}"})
        schema = out.schema
    every = range(parts)
    return out.select(
        "row",
        F.array_sort(F.array_distinct(F.flatten(F.array(*[f"items{n}" for n in every])))).alias("item_ids"),
        F.greatest(F.lit(0.0), *[f"similarity{n}" for n in every]).alias("similarity"),
    )
