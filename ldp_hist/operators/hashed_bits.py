"""Heavy hitters bit by bit: hash items to cells, recover each cell's dominant item from one oracle a bit.

``warm_up`` is the simple form. ``coded`` adds repetitions, an error-correcting code and the partitioned
oracle. Neither iterates: each is one plan, the code's decoder its only Python step over aggregated rows.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.functions.codes import Code
from ldp_hist.functions.encoding import Encoding
from ldp_hist.functions.hadamard import fwht_groups, had_sign
from ldp_hist.functions.hashing import digest, hex_slice, sign_digit
from ldp_hist.functions.randomizers import randomised
from ldp_hist.functions.randomness import coin
from ldp_hist.operators.sign_matrix_oracle import linear_sign, partitioned_estimates
from ldp_hist.plans.params import Params, cells_for, note
from ldp_hist.plans.privacy import Ledger


def _draws(p: Params, user: Column, repeats: int, bits: int, inner: int) -> dict[str, Column]:
    """rep, bit, sub, col and col_sign of a user: one digest apart from the oracle's."""
    d = digest("bits", p.seed, user)
    return {
        "rep": (hex_slice(d, 1, 8) % repeats).cast("int"), "bit": (hex_slice(d, 9, 8) % bits).cast("int"), "sub": (hex_slice(d, 17, 8) % inner).cast("int"),
        "col": hex_slice(d, 25, 8) % (4 * p.T), "col_sign": sign_digit(d, 33),
    }


def cell_of(p: Params, rep: Column, code: Column) -> Column:
    return hex_slice(digest("hcell", p.seed, rep, code), 1, 8) % p.T


def bit_reports(pop: DataFrame, p: Params, code_bit, length: int, repeats: int = 1, inner: int = 1, ledger: Ledger | None = None) -> DataFrame:
    """(rep, bit, sub, col, y): the first report of each user, half the budget, on (own cell, own code bit)."""
    (ledger or Ledger.of(p)).spend("code bit", p.eps / 2)
    d = _draws(p, F.col("user_key"), repeats, length, inner)
    own = pop.withColumns(d)
    key = cell_of(p, F.col("rep"), F.col("code")) * 2 + code_bit(F.col("code"), F.col("bit"))
    y = randomised(linear_sign(key, F.col("col"), F.col("col_sign")), p.eps / 2, coin(1, F.col("user_key"), p.coins))
    return own.select("rep", "bit", "sub", "col", (y * F.col("col_sign")).alias("y"))


def cell_bits(reports: DataFrame, p: Params, inner: int = 1) -> DataFrame:
    """(rep, cell, bit, value, weight): the likelier value of each bit of each cell; a tie gives 0.

    Counters by (rep, bit, sub, column), a transform along the columns, a median over the subsets.
    """
    sums = reports.groupBy("rep", "bit", "sub", "col").agg(F.sum(F.col("y").cast("long")).alias("s"))
    cells = fwht_groups(sums, ["rep", "bit", "sub"], "col", 4 * p.T).where(f"cell BETWEEN 1 AND {2 * p.T}")
    keyed = cells.select("rep", "bit", ((F.col("cell") - 1) / 2).cast("long").alias("at"), ((F.col("cell") - 1) % 2).alias("b"), "v")
    # A subset without a user has no counters; it counts as a zero in the median.
    answers = keyed.groupBy("rep", "bit", F.col("at").alias("cell"), "b").agg(F.collect_list("v").alias("vs"))
    padded = F.concat("vs", F.array_repeat(F.lit(0).cast("long"), (F.lit(inner) - F.size("vs")).cast("int")))
    ordered = F.array_sort(padded)
    median = (F.get(ordered, F.lit((inner - 1) // 2)) + F.get(ordered, F.lit(inner // 2))) / 2
    per_bit = answers.select("rep", "bit", "cell", "b", median.alias("est"))
    one, zero = F.max(F.when(F.col("b") == 1, F.col("est"))), F.max(F.when(F.col("b") == 0, F.col("est")))
    return per_bit.groupBy("rep", "cell", "bit").agg(F.when(one > zero, 1).otherwise(0).alias("value"), (F.abs(one - zero)).alias("weight"))


def _message_bit(width: int):
    """Bit ``i`` of the item's code, most significant first."""
    masks = F.array(*[F.lit(1 << (width - 1 - i)).cast("long") for i in range(width)])
    return lambda code, bit: F.when(code.bitwiseAND(F.element_at(masks, bit + 1)) != 0, 1).otherwise(0)


def _code_bit(code: Code):
    """Bit ``i`` of the code word: the parity of the message bits under a public mask."""
    masks = F.array(*[F.lit(m).cast("long") for m in code.masks()])
    return lambda value, bit: (F.bit_count(value.bitwiseAND(F.element_at(masks, bit + 1))) % 2).cast("int")


def _final(pop: DataFrame, cands: DataFrame, p: Params, ledger: Ledger) -> DataFrame:
    """(code, est) from the second report: a partitioned oracle over whole items with the other half of the budget."""
    named = pop.select("user_key", F.col("code").cast("string").alias("item"))
    asked = cands.select(F.col("code").cast("string").alias("item"))
    return partitioned_estimates(named, asked, p, eps=p.eps / 2, phase=2, ledger=ledger).select(F.col("item").cast("long").alias("code"), "est")


def warm_up_cells(pop: DataFrame, p: Params, encoding: Encoding, repeats: int = 1, ledger: Ledger | None = None) -> DataFrame:
    """(rep, cell, bit, value, weight) of the simple form."""
    coded = pop.withColumn("code", encoding.encode(F.col("item")))
    return cell_bits(bit_reports(coded, p, _message_bit(encoding.width), encoding.width, repeats, ledger=ledger), p)


def warm_up(pop: DataFrame, p: Params, encoding: Encoding, repeats: int = 1, n: int | None = None) -> DataFrame:
    """(code, item, est): the simple bit-by-bit protocol, a list of at most T items a repetition."""
    width, ledger = encoding.width, Ledger.of(p)
    if n is not None:
        note("warm_up", n, p, width)
    bits = warm_up_cells(pop, p, encoding, repeats, ledger)
    codes = bits.groupBy("rep", "cell").agg(F.sum(F.col("value").cast("long") * F.expr(f"shiftleft(1L, {width - 1} - bit)")).alias("code")).select("code").distinct()
    coded = pop.withColumn("code", encoding.encode(F.col("item")))
    return _final(coded, codes, p, ledger).select("code", encoding.decode(F.col("code")).alias("item"), "est")


def encoded(message: Column, code: Code) -> Column:
    """The code word of a message as an array of bits: the code is linear, so a bit is the parity of a mask."""
    return F.transform(F.array(*[F.lit(m).cast("long") for m in code.masks()]), lambda m: (F.bit_count(message.bitwiseAND(m)) % 2).cast("int"))


def decoder(code: Code):
    """The decoder as a column function over words (arrays of 0, 1 and -1): Arrow batches of aggregated rows, never users."""
    @F.pandas_udf("long")
    def decode(words: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for batch in words:
            yield pd.Series([code.decode(np.array(w, np.uint8)) for w in batch], dtype="Int64")

    return decode


def coded_words(pop: DataFrame, p: Params, encoding: Encoding, code: Code, repeats: int = 3, inner: int = 3, ledger: Ledger | None = None) -> DataFrame:
    """(rep, cell, word): the code word read off each of the ``repeats`` times T cells, 0, 1 or -1 a bit.

    A bit that no user was dealt to is an erasure (-1), which the code is there to fill in; the word stays.
    """
    coded = pop.withColumn("code", encoding.encode(F.col("item")))
    bits = cell_bits(bit_reports(coded, p, _code_bit(code), code.length, repeats, inner, ledger), p, inner)
    read = bits.groupBy("rep", "cell").agg(F.map_from_entries(F.collect_list(F.struct("bit", "value"))).alias("read"))
    every = pop.sparkSession.range(repeats * p.T).select(F.floor(F.col("id") / p.T).cast("int").alias("rep"), (F.col("id") % p.T).alias("cell"))
    word = F.transform(F.sequence(F.lit(0), F.lit(code.length - 1)), lambda i: F.coalesce(F.try_element_at("read", i), F.lit(-1)))
    return every.join(read, ["rep", "cell"], "left").select("rep", "cell", word.alias("word"))


def decoded(words: DataFrame, code: Code) -> DataFrame:
    """(code): the messages of the words that decode, each once."""
    if code.kind == "concat":
        found = words.select(decoder(code)("word").alias("code"))
    else:
        w = code.width

        def votes(i: int) -> Column:
            return sum((F.when(F.get("word", F.lit(at)) >= 0, 2 * F.get("word", F.lit(at)) - 1).otherwise(0) for at in range(i, code.length, w)), F.lit(0))

        message = sum((F.when(votes(i) > 0, F.lit(1 << w - 1 - i)).otherwise(F.lit(0)).cast("long") for i in range(w)), F.lit(0).cast("long"))
        found = words.where(F.exists("word", lambda b: b >= 0)).select(message.alias("code"))
    return found.where(F.col("code").isNotNull()).distinct()


def coded(pop: DataFrame, p: Params, encoding: Encoding, kind: str = "concat", repeats: int = 3, inner: int = 3, floor: str = "sqrt_n") -> DataFrame:
    """(code, item, est): the full bit-by-bit protocol.

    Words that don't decode go; items estimated at no more than sqrt(n) go too (``floor='none'`` keeps
    them), which is what keeps the list near sqrt(n) long.
    """
    code, ledger = Code(kind, encoding.width), Ledger.of(p)
    found = decoded(coded_words(pop, p, encoding, code, repeats, inner, ledger), code)
    own = pop.withColumn("code", encoding.encode(F.col("item")))
    hist = _final(own, found, p, ledger).select("code", encoding.decode(F.col("code")).alias("item"), "est")
    if floor != "sqrt_n":
        return hist
    n = pop.count()
    note("coded", n, p.but(R=repeats), code.length)
    return hist.where(F.col("est") > F.sqrt(F.lit(float(n))))


def assisted_warm_up(pop: DataFrame, p: Params, encoding: Encoding, kind: str = "repeat3", repeats: int = 1) -> DataFrame:
    """(code, item, est): the simple protocol with an error-correcting code around its bits.

    The simple protocol needs every bit of a heavy item's cell to be right, which costs its error a log log factor; with a code a part of the
    bits is enough. There are as many bit oracles as code bits, over one set of users each, and no inner subsets.
    """
    return coded(pop, p, encoding, kind, repeats, 1, floor="none")


def regime(pop: DataFrame, p: Params, encoding: Encoding, cells: str, n: int, repeats: int = 1, most: int = 1 << 16) -> DataFrame:
    """(code, item, est): the simple protocol with as many cells as the regime asks for.

    ``n2`` has no collision at all, ``n`` none between heavy items, ``sqrt`` one with constant probability, which repetition makes small. A
    run whose regime asks for over ``most`` cells a bit is refused: that is the cost that the later protocols avoid.
    """
    T = cells_for(n, cells)
    if T > most:
        raise ValueError(f"{T} cells for {n} users: the regime {cells} is for smaller populations")
    return warm_up(pop, p.but(T=T), encoding, repeats, n)


def discover_predecessor(pop: DataFrame, p: Params, encoding: Encoding, n: int, most: int = 1 << 16) -> DataFrame:
    """(code, item, est): the earlier protocol of optimal error: a cell an item, one bit oracle a code bit, all answers by direct sums.

    Its hash has no collisions (n squared cells, ``most`` at most) and each of its oracles answers every (cell, bit) by a sum over the
    bit's users, instead of one transform: users times cells in all.
    """
    T, width, ledger = min(most, cells_for(n, "n2")), encoding.width, Ledger.of(p)
    wide = p.but(T=T)
    coded = pop.withColumn("code", encoding.encode(F.col("item")))
    reports = bit_reports(coded, wide, _message_bit(width), width, ledger=ledger)
    asked = pop.sparkSession.range(2 * T).select(F.col("id").alias("x"), F.floor(F.col("id") / 2).alias("cell"), (F.col("id") % 2).alias("b"))
    sums = reports.select("bit", "col", "y").join(asked).groupBy("bit", "cell", "b").agg(F.sum(F.col("y") * had_sign(F.col("x") + 1, F.col("col"))).alias("v"))
    one, zero = F.max(F.when(F.col("b") == 1, F.col("v"))), F.max(F.when(F.col("b") == 0, F.col("v")))
    bits = sums.groupBy("cell", "bit").agg(F.when(one > zero, 1).otherwise(0).alias("value"))
    codes = bits.groupBy("cell").agg(F.sum(F.col("value").cast("long") * F.expr(f"shiftleft(1L, {width - 1} - bit)")).alias("code")).select("code").distinct()
    return _final(coded, codes, p, ledger).select("code", encoding.decode(F.col("code")).alias("item"), "est")
