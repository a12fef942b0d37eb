"""Encodings of records: grams, bit vectors, grids. All row-local expressions."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from veil.functions.hashing import hash_int


def qgrams(text: Column, q: int = 3) -> Column:
    """Consecutive character grams in order; null and shorter texts give an empty array."""
    n = F.length(text) - (q - 1)
    grams = F.transform(F.sequence(F.lit(1), n), lambda i: F.substr(text, i, F.lit(q)))
    return F.when(n >= 1, grams).otherwise(F.array().cast("array<string>"))


def bloom(text: Column, q: int = 3, bits: int = 50, hashes: int = 1) -> Column:
    """Bit vector of the grams' hashes in one long (``bits`` up to 63)."""
    if not 1 <= bits <= 63:
        raise ValueError("bits must be between 1 and 63")
    zero = F.lit(0).cast("long")

    def with_gram(acc: Column, g: Column) -> Column:
        for k in range(hashes):
            h = hash_int(g if k == 0 else F.concat(F.lit(f"{k}|"), g))
            acc = acc.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(h, F.lit(bits)).cast("int")))
        return acc

    return F.when(text.isNotNull(), F.aggregate(qgrams(text, q), zero, with_gram))


def grid(v: Column, size: float, cells: int) -> Column:
    """Cell number of a coordinate; values outside go to the edge cells."""
    return F.greatest(F.lit(0), F.least(F.lit(cells - 1), F.floor(v / size))).cast("long")


def truncate(v: Column, decimals: int = 6) -> Column:
    """Cut to a fixed number of decimals, as decimal."""
    return (F.floor(v * 10**decimals) / 10**decimals).cast(f"decimal(18,{decimals})")


def shift(v: Column, u: Column, theta: float) -> Column:
    """Move a coordinate by at most ``theta`` either way, by a uniform."""
    return v + theta * (2 * u - 1)


def drop_character(text: Column, u: Column) -> Column:
    """Lose one inner character, chosen by a uniform; shorter texts than three stay."""
    k = (F.floor(u * (F.length(text) - 2)) + 1).cast("int")
    cut = F.concat(F.substr(text, F.lit(1), k), F.substr(text, k + 2))
    return F.when(F.length(text) >= 3, cut).otherwise(text)


def sign_bits(v: Column, planes: list[list[float]]) -> Column:
    """Sides of a vector with respect to planes, as bits of a long."""
    bits = F.lit(0).cast("long")
    for i, plane in enumerate(planes):
        dot = F.aggregate(F.zip_with(v, F.array(*map(F.lit, plane)), lambda a, b: a.cast("double") * b), F.lit(0.0), lambda s, x: s + x)
        bits = bits + F.when(dot >= 0, 1 << i).otherwise(0)
    return bits
