"""Items as fixed-width codes, most significant symbol first, and their prefixes."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.hashing import digest, hex_slice

LETTERS = "abcdefghijklmnopqrstuvwxyz_"


@dataclass(frozen=True)
class Encoding:
    """``levels`` symbols of ``bits`` bits; ``symbols`` of the 2**bits values occur. At most 62 bits in all.

    A null item gets the code of all last symbols: every user reports, so that reporting leaks nothing.
    """

    levels: int
    bits: int
    symbols: int

    @property
    def width(self) -> int:
        return self.levels * self.bits

    def encode(self, item: Column) -> Column:
        raise NotImplementedError

    def decode(self, code: Column) -> Column:
        return code.cast("string")

    def missing(self) -> int:
        return sum((self.symbols - 1) << self.bits * i for i in range(self.levels))

    def prefix(self, code: Column, level: Column) -> Column:
        """The first ``level`` symbols, as a number."""
        steps = F.lit(0).cast("long")
        for k in range(1, self.levels + 1):
            steps = F.when(level == k, F.shiftright(code, self.bits * (self.levels - k))).otherwise(steps)
        return steps

    def children(self, prefixes: DataFrame) -> DataFrame:
        """(prefix): every prefix extended by every symbol."""
        more = F.explode(F.array(*[F.lit(i).cast("long") for i in range(self.symbols)]))
        return prefixes.select(more.alias("symbol"), "prefix").select((F.col("prefix") * (1 << self.bits) + F.col("symbol")).alias("prefix"))


@dataclass(frozen=True)
class IntEncoding(Encoding):
    """Non-negative integers of ``levels * bits`` bits."""

    def encode(self, item: Column) -> Column:
        return F.coalesce(item.try_cast("long"), F.lit(self.missing()))


def integers(width: int, bits: int = 1) -> IntEncoding:
    """Whole symbols; a narrower code is padded on the left (with zeros)."""
    return IntEncoding(-(-width // bits), bits, 1 << bits)


@dataclass(frozen=True)
class TextEncoding(Encoding):
    """Lower-case words cut or padded to ``levels`` letters; 27 of 32 symbols occur."""

    def fit(self, word: Column) -> Column:
        return F.rpad(F.substring(word, 1, self.levels), self.levels, "_")

    def encode(self, item: Column) -> Column:
        fitted = F.coalesce(self.fit(item), F.lit("_" * self.levels))
        terms = [(F.greatest(F.instr(F.lit(LETTERS), F.substring(fitted, i + 1, 1)), F.lit(1)) - 1).cast("long") * (1 << self.bits * (self.levels - 1 - i)) for i in range(self.levels)]
        return sum(terms[1:], terms[0])

    def decode(self, code: Column) -> Column:
        return F.concat(*[F.substring(F.lit(LETTERS), (F.shiftright(code, self.bits * (self.levels - 1 - i)).bitwiseAND(F.lit((1 << self.bits) - 1)) + 1).cast("int"), F.lit(1)) for i in range(self.levels)])


SIX_LETTERS = TextEncoding(6, 5, 27)


@dataclass(frozen=True)
class DictEncoding(Encoding):
    """Codes are places in a sorted list of values that is public and short (64K at most)."""

    values: tuple[str, ...] = ()

    @classmethod
    def of(cls, values, bits: int = 1) -> DictEncoding:
        ordered = tuple(sorted(set(values)))
        if len(ordered) > 1 << 16:
            raise ValueError("a dictionary of over 65,536 values needs a hash encoding")
        width = max(1, math.ceil(math.log2(max(2, len(ordered) + 1))))
        return cls(-(-width // bits), bits, 1 << bits, ordered)

    def encode(self, item: Column) -> Column:
        table = F.create_map(*[F.lit(x) for i, v in enumerate(self.values) for x in (v, i)])
        return F.coalesce(F.try_element_at(table, item).cast("long"), F.lit(self.missing()))

    def decode(self, code: Column) -> Column:
        return F.get(F.array(*[F.lit(v) for v in self.values]), code.cast("int"))


@dataclass(frozen=True)
class HashEncoding(Encoding):
    """Hashed items; a code is named again by whoever knows the item (``name_codes``)."""

    def encode(self, item: Column) -> Column:
        return F.coalesce(hex_slice(digest("item", 0, item), 1, 12) % (1 << self.width), F.lit(self.missing()))

    def name_codes(self, hist: DataFrame, known: DataFrame) -> DataFrame:
        """``hist`` (code, ...) joined to the items of ``known`` that have its codes."""
        return hist.join(known.select("item").distinct().withColumn("code", self.encode(F.col("item"))), "code")


def bucket(value: Column, low: float, step: float) -> Column:
    """Numbers and dates (as numbers) in steps, for use with ``integers``."""
    return F.floor((value - low) / step).cast("long")
