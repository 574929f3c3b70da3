"""Hashes, transforms, codes, privacy, parameters: identities that hold exactly."""

import math
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from ldp_hist.functions import codes, encoding, hadamard, hashing
from ldp_hist.functions.randomizers import debias, keep_probability, privacy_loss
from ldp_hist.plans import cost, dispatch, params, privacy


def test_transform_is_its_own_inverse():
    x = np.random.default_rng(1).integers(-9, 9, 64)
    assert (hadamard.fwht(hadamard.fwht(x)) == 64 * x).all()
    w = np.array([[1 - 2 * ((r & c).bit_count() % 2) for c in range(64)] for r in range(64)])
    assert (hadamard.fwht(x) == w.T @ x).all() and (w @ w.T == 64 * np.eye(64)).all()


@pytest.mark.parametrize("width", [5, 10, 30])
def test_concatenated_code_corrects_an_eighth(width):
    code, rng = codes.Code("concat", width), random.Random(width)
    assert code.length == 32 * width // 5 and code.corrects * 8 > code.length
    for trial in range(40 if width < 30 else 12):
        message = rng.randrange(1 << width)
        word = code.encode(message)
        wrong = rng.sample(range(code.length), code.corrects)
        if trial % 2:  # a burst that ruins whole symbols
            start = rng.randrange(code.length)
            wrong = [i % code.length for i in range(start, start + code.corrects)]
        word[wrong] ^= 1
        assert code.decode(word) == message


def test_codes_are_linear_and_short_ones_exhaustive():
    for kind, width in (("none", 4), ("repeat3", 4), ("concat", 5)):
        code = codes.Code(kind, width)
        for m in range(1 << width):
            word = code.encode(m)
            assert [int(b) for b in word] == [(m & mask).bit_count() % 2 for mask in code.masks()]
            assert code.decode(word) == m
    repeat = codes.Code("repeat3", 5)
    for i in range(15):
        word = repeat.encode(19)
        word[i] ^= 1
        assert repeat.decode(word) == 19


def test_privacy_is_what_is_claimed():
    for eps in (0.25, 0.9, 2.0):
        assert privacy.mechanism_loss("single_report", eps) == pytest.approx(eps, abs=1e-12)
        assert privacy.mechanism_loss("two_reports", eps) == pytest.approx(eps, abs=1e-12)
        assert privacy.mechanism_loss("doubled_report", eps) > eps + 0.1
    assert privacy.mechanism_loss("linear_report", 0.5) == pytest.approx(privacy_loss(0.5, "linear"))
    assert privacy_loss(0.5, "linear") > 0.5
    for method in ("dictionary", "tree", "warm_up", "coded", "partitioned", "sign_matrix"):
        assert privacy.ledger_of(method, 2.0).loss == pytest.approx(2.0)
    assert privacy.ledger_of("tree", 2.0, windows=3).loss == pytest.approx(6.0)
    assert privacy.Ledger(1.0, secret_coins=False).loss == math.inf
    with pytest.raises(ValueError):
        privacy.Ledger(1.0).spend("too much", 1.1)
    with pytest.raises(ValueError):
        keep_probability(1.5, "linear")
    assert debias(1.0) == pytest.approx(1 / (2 * keep_probability(1.0) - 1))


def test_parameters():
    assert params.pow2(65) == 128 and params.pow2(64) == 64
    with pytest.raises(ValueError):
        params.Params(m=48)
    with pytest.raises(ValueError):
        params.Params(eps=0)
    theory = params.theory_tree(10**7, 30, 2.0)
    assert 3 * theory["eta"] > 10**7  # vacuous below this size, as the closed form says
    assert params.check("sketch", 10**6, params.TINY) and not params.check("sign_matrix", 100, params.Params(eps=1.0))
    assert params.check("coded", 10**6, params.TINY, 30) and params.check("partitioned", 100, params.TINY)
    assert params.suggest_pairs(401_563, 6) % 2 == 1 and params.cells_for(100, "sqrt") == 16
    assert params.warm_up(10**6, 30, 1.0)["T"] >= 1 and params.partitioned_full(10**6, 10, 0.05, 1.0)["R"] > params.partitioned_small(10**6, 10, 0.05, 1.0)["R"]
    assert cost.operations("transform", 10**6, params.TINY, 6, 1000)["additions"] < cost.operations("direct", 10**6, params.TINY, 6, 1000)["additions"]
    assert dispatch.choose_method(10**6, 5) == "enumerate" and dispatch.choose_method(10**4, 30) == "tree" and dispatch.choose_method(10**4, 30, one_round=True) == "coded"


def test_encodings(spark):
    words = ["cat", "elephants", None, "naïve", "a"]
    df = spark.createDataFrame([(w,) for w in words], "item string")
    six = encoding.SIX_LETTERS
    got = df.select("item", six.decode(six.encode(F.col("item"))).alias("back")).collect()
    assert {r["item"]: r["back"] for r in got} == {"cat": "cat___", "elephants": "elepha", None: "______", "naïve": "naave_", "a": "a_____"}
    known = encoding.DictEncoding.of(["x", "y", "z"])
    assert [r[0] for r in spark.createDataFrame([("y",), ("?",), (None,)], "item string").select(known.decode(known.encode(F.col("item")))).collect()] == ["y", None, None]
    code = 0b10110
    row = spark.range(1).select(*[encoding.integers(5).prefix(F.lit(code).cast("long"), F.lit(k)).alias(f"p{k}") for k in range(1, 6)]).first()
    assert list(row) == [code >> (5 - k) for k in range(1, 6)]
    kids = six.children(spark.createDataFrame([(3,)], "prefix long")).collect()
    assert sorted(r[0] for r in kids) == [96 + i for i in range(27)]
    assert spark.range(1).select(encoding.bucket(F.lit(7.3), 0, 2.5)).first()[0] == 2


def test_hash_families(spark):
    xs = spark.range(2000).select("id", hashing.affine_hash(1, F.col("id"), 16).alias("a"), hashing.poly_hash(1, F.col("id"), 16, 4).alias("p")).collect()
    for name in ("a", "p"):
        counts = np.bincount([r[name] for r in xs], minlength=16)
        assert counts.min() > 60 and counts.max() < 200


def test_erasures():
    """Against the nearest code word over what is known, for words with both erasures and wrong bits."""
    code, rng = codes.Code("concat", 5), random.Random(4)
    words = np.array([code.encode(m) for m in range(32)])
    for _ in range(200):
        message = rng.randrange(32)
        word = code.encode(message).astype(np.int8)
        places = rng.sample(range(code.length), 10)
        word[places[:6]] = -1  # half as bad as a wrong bit each: 6/2 + 4 is within what is corrected
        word[places[6:]] ^= 1
        assert code.decode(word) == message
        known = word >= 0
        assert np.count_nonzero((words[message] != word) & known) == min(np.count_nonzero((w != word) & known) for w in words)
    for kind in ("none", "repeat3", "concat"):
        assert codes.Code(kind, 5).decode(np.full(codes.Code(kind, 5).length, -1)) is None
    repeat = codes.Code("repeat3", 4)
    word = repeat.encode(11).astype(np.int8)
    word[[0, 4, 5]] = -1
    assert repeat.decode(word) == 11 and codes.Code("none", 4).decode(np.array([1, -1, 1, 1])) == 11
