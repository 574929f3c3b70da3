"""Secret scans: fixed patterns, and a battery of randomness tests. DataFrame functions only."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ldp_hist.llm.shared import materialise

# The patterns of the contract and the alphabets of common encodings.
ASSIGN = r"""(?i)(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
# Runs of [0-9a-f]+ that have 16 characters or more, and of TOKEN's own set. Looking behind tries each run once.
HEX = r"(?<![0-9a-f])[0-9a-f]{16,}+"
TOKEN = r"(?<![A-Za-z0-9+/_-])[A-Za-z0-9+/_-]{20,}+"
KINDS = ("assign", "access", "hex", "random")
DIGITS, UPPER, LOWER = "0123456789", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
ENCODINGS = (
    ("decimal", r"^[0-9]+$", DIGITS),
    ("hex", r"^([0-9a-f]+|[0-9A-F]+)$", DIGITS + "ABCDEF"),
    ("base32", r"^[A-Z2-7]+$", UPPER + "234567"),
    ("alphanumeric", r"^[A-Za-z0-9]+$", UPPER + LOWER + DIGITS),
    ("base64", r"^[A-Za-z0-9+/]+$", UPPER + LOWER + DIGITS + "+/"),
    ("base64url", r"^[A-Za-z0-9_-]+$", UPPER + LOWER + DIGITS + "-_"),
    ("mixed", r"", UPPER + LOWER + DIGITS + "+/-_"),
)
#: Share of text-like tokens tolerated among those reported, and the p-values that may serve as a threshold.
FALSE_DISCOVERY, LEVELS = 0.05, (0.001, 0.01, 0.05, 0.1, 0.2)
#: Fewer tokens than this say nothing about the share of text among them; the level that a token gets then.
FEW, ALONE = 40, 0.05


#: Arrays are folded in parts of this many, so that no step copies what the parts before it made.
PART = 256


def _scan(items: Column, zero: Column, out: str, step: Callable[[Column, Column], tuple[Column, Column]]) -> Column:
    """What ``step`` emits for every item in turn (an array of SQL type ``out``); it takes the state and gives the next one.

    A fold that appends to its result copies it each time, the square of the length in all; here the copies are of
    parts only, and one list of parts.
    """
    none, nothing = F.expr(f"cast(array() as array<{out}>)"), F.expr(f"cast(array() as array<array<{out}>>)")

    def one(state: Column, x: Column) -> Column:
        after, made = step(state["at"], x)
        return F.struct(after.alias("at"), F.concat(state["out"], F.array(made)).alias("out"))

    def part(state: Column, items: Column) -> Column:
        done = F.aggregate(items, F.struct(state["at"].alias("at"), none.alias("out")), one)
        return _let(done, lambda d: F.struct(d["at"].alias("at"), F.concat(state["out"], F.array(d["out"])).alias("out")))

    def whole(held: Column) -> Column:
        parts = F.transform(F.sequence(F.lit(0), F.floor((F.size(held) - 1) / PART).cast("int")), lambda i: F.slice(held, i * PART + 1, PART))
        return F.aggregate(parts, F.struct(zero.alias("at"), nothing.alias("out")), part, lambda state: F.flatten(state["out"]))

    return _let(items, lambda held: F.when(F.size(held) > 0, whole(held)).otherwise(none))


def spans(text: Column, pattern: str) -> Column:
    """array<struct<s, e, hit>>: where ``pattern`` matches, leftmost and without overlap, in code points.

    The text between the matches is what splitting leaves, so running lengths of gaps and matches give
    every position; the arrays are folded in pairs by their number, not by searching the text again.
    """
    lengths = _let(F.split(text, pattern, -1), lambda gaps: F.transform(
        F.regexp_extract_all(text, F.lit(pattern), F.lit(0)),
        lambda h, i: F.struct(F.char_length(F.get(gaps, i)).alias("gap"), F.char_length(h).alias("n"), h.alias("hit"))))

    def step(at: Column, x: Column) -> tuple[Column, Column]:
        s, e = at + x["gap"], at + x["gap"] + x["n"]
        return e, F.struct(s.alias("s"), e.alias("e"), x["hit"].alias("hit"))

    empty = F.expr("cast(array() as array<struct<s:int,e:int,hit:string>>)")
    return F.when(text.rlike(pattern), _scan(lengths, F.lit(0), "struct<s:int,e:int,hit:string>", step)).otherwise(empty)


def _free(tokens: Column, base: Column) -> Column:
    """The ``tokens`` that overlap no ``base`` span, by two passes over both in order of their starts.

    On the way forward a token is struck by the furthest end of the base spans before it, on the way back by the
    nearest start of those after it.
    """
    kind = "struct<s:int,token:int,e:int,hit:string,struck:boolean>"

    def item(s: Column, token: Column, e: Column, hit: Column, struck: Column) -> Column:
        return F.struct(s.alias("s"), token.alias("token"), e.alias("e"), hit.alias("hit"), struck.alias("struck"))

    def forward(end: Column, x: Column) -> tuple[Column, Column]:
        return F.when(x["token"] == 0, F.greatest(end, x["e"])).otherwise(end), item(x["s"], x["token"], x["e"], x["hit"], x["s"] < end)

    def back(start: Column, x: Column) -> tuple[Column, Column]:
        return F.when(x["token"] == 0, x["s"]).otherwise(start), item(x["s"], x["token"], x["e"], x["hit"], x["struck"] | (start < x["e"]))

    no = F.lit(False)
    both = F.array_sort(F.concat(
        F.transform(base, lambda b: item(b["s"], F.lit(0), b["e"], F.lit(""), no)), F.transform(tokens, lambda t: item(t["s"], F.lit(1), t["e"], t["hit"], no))))
    seen = F.reverse(_scan(F.reverse(_scan(both, F.lit(0), kind, forward)), F.lit((1 << 31) - 1), kind, back))
    left = F.transform(F.filter(seen, lambda x: (x["token"] == 1) & ~x["struck"]), lambda x: F.struct(x["s"].alias("s"), x["e"].alias("e"), x["hit"].alias("hit")))
    return F.when((F.size(tokens) > 0) & (F.size(base) > 0), left).otherwise(tokens)


def _tail(z: Column) -> Column:
    """Two-sided tail of the normal distribution, by a rational approximation good to 1e-7."""
    x = F.least(F.abs(z), F.lit(37.0))
    t = 1 / (1 + 0.2316419 * x)
    series = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    return F.least(F.lit(1.0), 2 * series * F.exp(-x * x / 2) / math.sqrt(2 * math.pi))


def _upper_tail(z: Column) -> Column:
    half = _tail(z) / 2
    return F.when(z > 0, half).otherwise(1 - half)


def _let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of a ``value`` that is computed once, however often ``body`` names it."""
    return F.get(F.transform(F.array(value), body), 0)


def _chi_squared(token: Column, n: Column, k: int) -> Column:
    symbols = F.array_distinct(F.split(token, ""))
    squares = F.aggregate(symbols, F.lit(0.0), lambda a, c: a + F.pow(n - F.char_length(F.replace(token, c, F.lit(""))), F.lit(2.0)))
    # The statistic's exact mean and variance under the multinomial, rather than those of the limit.
    return _let((squares * k / n - n - (k - 1.0)) / F.sqrt(2.0 * (k - 1) * (n - 1) / n), _upper_tail)


def _runs(token: Column, n: Column, alphabet: str) -> Column:
    low = (len(alphabet) + 1) // 2
    halves = F.translate(token, alphabet, "0" * low + "1" * (len(alphabet) - low))

    def of(x: Column) -> Column:
        ones = n - x["zeros"]
        expected = 1 + 2 * ones * x["zeros"] / n
        z = _let(expected, lambda e: (x["runs"] - e) / F.sqrt(F.greatest((e - 1) * (e - 2) / (n - 1), F.lit(1e-9))))
        return F.when(ones * x["zeros"] == 0, F.pow(F.lit(0.5), n - 1)).otherwise(_let(z, _tail))

    def counted(h: Column) -> Column:
        runs = F.char_length(F.regexp_replace(h, "0+|1+", "r")).cast("double")
        return F.struct(F.char_length(F.replace(h, F.lit("1"), F.lit(""))).cast("double").alias("zeros"), runs.alias("runs"))

    return _let(_let(halves, counted), of)


def _serial(token: Column, n: Column, alphabet: str) -> Column:
    """Lag-one correlation from running sums: one pass, with the mean taken out at the end."""
    at = F.transform(F.split(token, ""), lambda c: F.instr(F.lit(alphabet), c).cast("double"))
    start = F.struct(F.lit(0.0).alias("first"), F.lit(0.0).alias("last"), F.lit(0.0).alias("sum"), F.lit(0.0).alias("squares"), F.lit(0.0).alias("lag"))

    def step(a: Column, x: Column) -> Column:
        first = F.when(a["last"] == 0, x).otherwise(a["first"])  # symbols are numbered from 1
        return F.struct(first.alias("first"), x.alias("last"), (a["sum"] + x).alias("sum"), (a["squares"] + x * x).alias("squares"), (a["lag"] + a["last"] * x).alias("lag"))

    def of(a: Column) -> Column:
        middle = a["sum"] / n
        power = a["squares"] - a["sum"] * middle
        lag = a["lag"] - middle * (2 * a["sum"] - a["first"] - a["last"]) + (n - 1) * middle * middle
        return F.when(power <= 1e-9, F.lit(0.0)).otherwise(_let((lag / power + 1 / n) * F.sqrt(n), _tail))

    return _let(F.aggregate(at, start, step), of)


def _tests(token: Column, alphabet: str) -> Column:
    """The combined p-value that ``token`` is uniform over ``alphabet``: chi-squared, runs, serial correlation.

    Bonferroni over the three, since they share the data.
    """

    def of(t: Column) -> Column:
        n = F.char_length(t).cast("double")
        return 3 * F.least(_chi_squared(t, n, len(alphabet)), _runs(t, n, alphabet), _serial(t, n, alphabet))

    return F.least(F.lit(1.0), _let(token, of))


def battery(token: Column) -> Column:
    """struct<encoding, p>: the narrowest encoding that holds the token, and the p-value of the tests in it."""
    out = None
    for name, pattern, alphabet in reversed(ENCODINGS):
        p = _tests(F.upper(token) if name == "hex" else token, alphabet)
        one = F.struct(F.lit(name).alias("encoding"), p.alias("p"))
        out = one if out is None else F.when(token.rlike(pattern), one).otherwise(out)
    return out


def thresholds(tested: DataFrame) -> dict[tuple[str, int], float]:
    """For each encoding and power of two of the length, the least level that keeps the false share in bounds.

    p-values of random tokens are uniform, those of text-like tokens near zero. So twice the tokens above
    one half estimate the random ones, and what a level accepts beyond their share is text-like; the
    least level whose share of it is at most ``FALSE_DISCOVERY`` is taken. Short lengths hold text that the tests cannot
    tell from random and get a stricter level by that, or none (2.0, above every p-value). Where a length has fewer than
    ``FEW`` tokens, those of the nearest lengths of its encoding are counted with it; an encoding that
    has fewer altogether gets ``ALONE``, which random tokens pass in 19 of 20 cases.
    """
    counts = tested.groupBy("encoding", "stratum").agg(
        F.count("*").alias("n"), F.sum(F.when(F.col("p") > 0.5, 1).otherwise(0)).alias("high"),
        *[F.sum(F.when(F.col("p") >= level, 1).otherwise(0)).alias(f"at{i}") for i, level in enumerate(LEVELS)],
    )
    rows = counts.collect()  # at most seven encodings times 31 lengths
    out = {}
    for r in rows:
        own = [x for x in rows if x["encoding"] == r["encoding"]]
        reach = next((d for d in range(32) if sum(x["n"] for x in own if abs(x["stratum"] - r["stratum"]) <= d) >= FEW), None)
        out[r["encoding"], r["stratum"]] = ALONE if reach is None else level_for([x for x in own if abs(x["stratum"] - r["stratum"]) <= reach])
    return out


def level_for(rows: list) -> float:
    """The level for tokens counted in ``rows`` (high, at0, at1, ...)."""
    random = 2 * sum(r["high"] for r in rows)
    for i, level in enumerate(LEVELS):
        accepted = sum(r[f"at{i}"] for r in rows)
        if accepted and accepted - (1 - level) * random <= FALSE_DISCOVERY * accepted:
            return level
    return 2.0


def scan_secrets(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans and n_random for every row of ``docs``.

    Base spans are those of the three patterns. The battery looks at every other run of 20 or more letters,
    digits, ``+/_-``: it infers the narrowest encoding that holds the run, tests chi-squared uniformity over its
    alphabet, runs and serial correlation, and reports runs that stay random at the level which
    ``thresholds`` sets for their encoding and length over all documents. A run that overlaps a base span is left out.

    Offsets are code points with an exclusive end. Null texts count as empty: no spans. Repeated rows get
    equal answers, other columns are ignored, empty tables give empty results.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    found = docs.select(
        F.col("doc_id").cast("long").alias("doc_id"),
        spans(text, ASSIGN).alias("assign"), spans(text, ACCESS).alias("access"), spans(text, HEX).alias("hex"), spans(text, TOKEN).alias("tokens"),
    )
    base = found.withColumns({
        "assign": F.filter("assign", lambda x: F.char_length(F.regexp_extract(x["hit"], ASSIGN, 2)) >= 12),
        "access": F.filter("access", lambda x: F.char_length(x["hit"]) >= 18),
    })

    def marked(name: str, kind: int) -> Column:
        return F.transform(name, lambda x: F.struct(x["s"].alias("s"), F.lit(kind).alias("kind"), x["e"].alias("e")))

    base = base.withColumn("base", F.array_sort(F.concat(marked("assign", 0), marked("access", 1), marked("hex", 2))))
    free = base.withColumn("tokens", _free(F.col("tokens"), F.col("base")))

    def tested(t: Column) -> Column:
        return _let(battery(t["hit"]), lambda b: result(t, b))

    def result(t: Column, b: Column) -> Column:
        return F.struct(t["s"].alias("s"), t["e"].alias("e"), b["encoding"].alias("encoding"), F.floor(F.log2((t["e"] - t["s"]).cast("double"))).cast("int").alias("stratum"), b["p"].alias("p"))

    kept = materialise(free.select(
        "doc_id", F.size("assign").cast("long").alias("n_assign"), F.size("access").cast("long").alias("n_access"), F.size("hex").cast("long").alias("n_hex"),
        "base", F.transform("tokens", tested).alias("tokens"),
    ))
    levels = thresholds(kept.select(F.explode("tokens").alias("t")).select("t.*"))
    level = F.lit(2.0)
    if levels:
        table = F.create_map(*[F.lit(v) for (e, s), at in sorted(levels.items()) for v in (f"{e}:{s}", at)])
        random = F.filter("tokens", lambda t: t["p"] >= F.coalesce(F.element_at(table, F.concat_ws(":", t["encoding"], t["stratum"].cast("string"))), level))
    else:
        random = F.filter("tokens", lambda t: F.lit(False))
    done = kept.withColumn("random", random)

    def listed(array: Column) -> Column:
        names = F.array(*[F.lit(k) for k in KINDS])
        return F.array_join(F.transform(array, lambda x: F.concat_ws(":", F.get(names, x["kind"]), x["s"].cast("string"), x["e"].cast("string"))), ",")

    extra = F.transform("random", lambda x: F.struct(x["s"].alias("s"), F.lit(3).alias("kind"), x["e"].alias("e")))
    return done.select(
        "doc_id", "n_assign", "n_access", "n_hex", F.sha2(listed(F.col("base")).cast("binary"), 256).alias("base_sha256"),
        listed(F.array_sort(F.concat("base", extra))).alias("spans"), F.size("random").cast("long").alias("n_random"),
    )
