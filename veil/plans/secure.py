"""The secure comparison as a unit of cost.

``ideal`` is what all protocols use: a rule as a column. The rest shows the
comparison carried out with additively homomorphic numbers. Keys are small and
for tests only; the final comparison of blinded numbers is the ideal one, not a
garbled circuit. Never use this to protect data.
"""

from __future__ import annotations

import math
import random
import time
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veil.functions.rules import Rule
from veil.sources.shared import in_arrow


def ideal(rule: Rule) -> Column:
    """The pair where the rule holds, null elsewhere."""
    return F.when(rule.condition(), F.struct(F.col("a.rid").alias("a_id"), F.col("b.rid").alias("b_id")))


@dataclass(frozen=True)
class Key:
    """A key pair of the additive scheme with generator n + 1."""

    n: int
    lam: int
    mu: int

    def encrypt(self, m: int, rng: random.Random) -> int:
        n2 = self.n * self.n
        while math.gcd(r := rng.randrange(2, self.n), self.n) != 1:
            pass
        return (1 + m % self.n * self.n) * pow(r, self.n, n2) % n2

    def decrypt(self, c: int) -> int:
        return (pow(c, self.lam, self.n * self.n) - 1) // self.n * self.mu % self.n

    def add(self, x: int, y: int) -> int:
        """Cipher of the sum of two hidden numbers."""
        return x * y % (self.n * self.n)

    def scale(self, x: int, k: int) -> int:
        """Cipher of a hidden number times a known one; a factor of -1 is one inverse."""
        return pow(x, -1 if k == -1 else k % self.n, self.n * self.n)


def _prime(bits: int, rng: random.Random) -> int:
    def probable(p: int) -> bool:
        d, s = p - 1, 0
        while d % 2 == 0:
            d, s = d // 2, s + 1
        for _ in range(20):
            x = pow(rng.randrange(2, p - 1), d, p)
            if x in (1, p - 1):
                continue
            for _ in range(s - 1):
                x = x * x % p
                if x == p - 1:
                    break
            else:
                return False
        return True

    while True:
        p = rng.getrandbits(bits) | 1 | 1 << (bits - 1)
        if probable(p):
            return p


def key(bits: int = 256, seed: int = 1) -> Key:
    """A test key of ``bits`` bits from a seed."""
    rng = random.Random(seed)
    p, q = _prime(bits // 2, rng), _prime(bits // 2, rng)
    while q == p:
        q = _prime(bits // 2, rng)
    lam = math.lcm(p - 1, q - 1)
    return Key(p * q, lam, pow(lam, -1, p * q))


def hamming_terms(a: Column, b: Column) -> Column:
    """Sum of a + b - 2ab over the bits: what the homomorphic side computes."""
    return F.bit_count(a) + F.bit_count(b) - 2 * F.bit_count(a.bitwiseAND(b))


def square_terms(a: Column, b: Column) -> Column:
    """Sum of a^2 - 2ab + b^2 over integer arrays."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * x - 2 * x * y + y * y), F.lit(0).cast("long"), lambda s, v: s + v)


def _blinded(batches: Iterator[pa.RecordBatch], schema: pa.Schema, k: Key, theta: int, bits: int, seed: int) -> Iterator[pa.RecordBatch]:
    hidden: dict[int, list[tuple[int, int]]] = {}  # Alice encrypts a vector once; Bob inverts each cipher once
    for b in batches:
        out = []
        for a_id, b_id, va, vb in zip(*(b.column(c).to_pylist() for c in ("a_id", "b_id", "va", "vb"))):
            if va is None or vb is None:
                continue
            began = time.perf_counter()
            if va not in hidden:
                own = random.Random(f"{seed}|a|{va}")
                hidden[va] = [(c, k.scale(c, -1)) for c in (k.encrypt(va >> i & 1, own) for i in range(bits))]
            rng = random.Random(f"{seed}|b|{a_id}|{b_id}")  # fresh blinds for every pair, the same after a retry
            total = k.encrypt(vb.bit_count() + (blind := rng.randrange(1 << 40)), rng)
            for i, pair in enumerate(hidden[va]):
                total = k.add(total, pair[vb >> i & 1])
            seen = k.decrypt(total)
            out.append((a_id, b_id, seen <= theta + blind, time.perf_counter() - began))
        cols = list(zip(*out)) if out else [[] for _ in schema]
        yield pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(cols, schema)], schema=schema)


def _squares(batches: Iterator[pa.RecordBatch], schema: pa.Schema, k: Key, theta: int, seed: int) -> Iterator[pa.RecordBatch]:
    for b in batches:
        out = []
        for a_id, b_id, xa, xb in zip(*(b.column(c).to_pylist() for c in ("a_id", "b_id", "xa", "xb"))):
            if xa is None or xb is None:
                continue
            own, rng = random.Random(f"{seed}|a|{a_id}"), random.Random(f"{seed}|b|{a_id}|{b_id}")
            sent = [k.encrypt(v, own) for v in xa], k.encrypt(sum(v * v for v in xa), own)  # Alice: her numbers, and their squares' sum
            total = k.add(sent[1], k.encrypt(sum(v * v for v in xb) + (blind := rng.randrange(1 << 40)), rng))
            for c, v in zip(sent[0], xb):
                total = k.add(total, k.scale(c, -2 * v))
            out.append((a_id, b_id, k.decrypt(total) <= theta * theta + blind))
        cols = list(zip(*out)) if out else [[] for _ in schema]
        yield pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(cols, schema)], schema=schema)


def blinded_distance(pairs: DataFrame, theta: int, k: Key | None = None, seed: int = 1) -> DataFrame:
    """``a_id, b_id, matched`` of ``a_id, b_id, xa, xb`` (arrays of long): blinded homomorphic squared distance against theta squared."""
    return in_arrow(pairs.select("a_id", "b_id", "xa", "xb"), _squares, "a_id long, b_id long, matched boolean", k or key(), theta, seed)


def blinded_match(pairs: DataFrame, theta: int, bits: int = 50, k: Key | None = None, seed: int = 1) -> DataFrame:
    """``a_id, b_id, matched, seconds`` of ``a_id, b_id, va, vb``: blinded homomorphic Hamming comparison.

    Bob adds a random offset, drawn anew for every pair, before Alice decrypts;
    offset distance and offset threshold are compared. Pairs with a null vector have no row. ``seconds``
    is measured.
    """
    n = int(pairs.sparkSession.conf.get("spark.sql.shuffle.partitions"))  # few bytes but much work: not to be coalesced
    return in_arrow(pairs.select("a_id", "b_id", "va", "vb").repartition(n, "va"), _blinded, "a_id long, b_id long, matched boolean, seconds double", k or key(), theta, bits, seed)
