"""Public hash functions as column expressions; DuckDB computes the same integers from the same text."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: A Mersenne prime: products of two residues stay below 2**62.
PRIME = (1 << 31) - 1


def digest(tag: str, seed, *keys: Column) -> Column:
    """SHA-256 (hex) of tag, seed and keys, joined by colons."""
    parts = [F.lit(tag), (seed if isinstance(seed, Column) else F.lit(seed)).cast("string"), *(k.cast("string") for k in keys)]
    return F.sha2(F.concat_ws(":", *parts), 256)


def hex_slice(d: Column, start: int, length: int) -> Column:
    """``length`` hex digits (13 at most) from ``start`` (1-based), as a long."""
    return F.conv(F.substring(d, start, length), 16, 10).cast("long")


def sign_of(bit: Column) -> Column:
    return (1 - 2 * bit).cast("int")


def sign_digit(d: Column, at: int) -> Column:
    """The sign that one hex digit stands for: -1 for an odd one."""
    return F.when(F.instr(F.lit("13579bdf"), F.substring(d, at, 1)) > 0, -1).otherwise(1)


def bucket_hash(seed, j: Column, x: Column, m: int) -> Column:
    """h_j(x) in 0..m-1."""
    return hex_slice(digest("pair", seed, j, x), 1, 8) % m


def sign_hash(seed, j: Column, x: Column) -> Column:
    """g_j(x), +1 or -1."""
    return sign_digit(digest("pair", seed, j, x), 9)


def coefficients(seed: int, name: str, count: int) -> list[int]:
    """``count`` public residues modulo PRIME, drawn on the driver."""
    import hashlib

    return [int(hashlib.sha256(f"{name}:{seed}:{i}".encode()).hexdigest()[:12], 16) % PRIME for i in range(count)]


def affine_hash(seed: int, x: Column, m: int) -> Column:
    """A pairwise independent hash of an integer below PRIME."""
    a, b = coefficients(seed, "affine", 2)
    return ((x.cast("long") * (a or 1) + b) % PRIME) % m


def poly_hash(seed: int, x: Column, m: int, k: int) -> Column:
    """A k-wise independent hash: a polynomial of degree k-1 modulo PRIME, by Horner's rule."""
    out = F.lit(0).cast("long")
    for c in coefficients(seed, f"poly{k}", k):
        out = (out * x.cast("long") + c) % PRIME
    return out % m
