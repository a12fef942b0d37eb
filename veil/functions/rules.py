"""Matching rules: boolean expressions over two records.

A rule gives its condition over aliases ``a`` and ``b``, the equality columns
that Catalyst can turn into join keys, the attributes it reads, and, where one
exists, the size of the ball of records that match a given one. A record with a
null attribute matches nothing.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from math import comb

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Rule:
    attributes: tuple[str, ...]
    keys: tuple[str, ...] = ()
    parts: tuple["Rule", ...] = field(default=())

    def condition(self, a: str = "a", b: str = "b") -> Column:
        raise NotImplementedError

    def ball_size(self) -> int | None:
        """Number of values within the rule of one value, itself included; None where unknown."""
        return None

    def lossless_index(self) -> tuple[Column, Column] | None:
        """Arrays of keys (long) of a record of A and of B; accepted pairs share a key. None where the rule has no such index.

        Columns refer to a party's own attributes. Keys may collide, as the
        condition is checked on every pair that meets.
        """
        return None


@dataclass(frozen=True)
class Equal(Rule):
    def condition(self, a: str = "a", b: str = "b") -> Column:
        return F.col(f"{a}.{self.attributes[0]}") == F.col(f"{b}.{self.attributes[0]}")

    def ball_size(self) -> int:
        return 1

    def lossless_index(self) -> tuple[Column, Column]:
        own = F.array(_keyed(F.col(self.attributes[0])))
        return own, own


def _keyed(*parts: Column) -> Column:
    return F.xxhash64(*parts)


def equal(col: str) -> Rule:
    return Equal((col,), (col,))


@dataclass(frozen=True)
class Euclidean(Rule):
    """Distance of scaled columns at most theta; squares are compared, so no root is taken."""

    theta: float = 0.0
    scales: tuple[float, ...] = ()

    def condition(self, a: str = "a", b: str = "b") -> Column:
        terms = [
            ((F.col(f"{a}.{c}") - F.col(f"{b}.{c}")) / s) * ((F.col(f"{a}.{c}") - F.col(f"{b}.{c}")) / s)
            for c, s in zip(self.attributes, self.scales)
        ]
        total = terms[0]
        for t in terms[1:]:
            total = total + t
        return total <= F.lit(self.theta * self.theta)

    def ball_size(self) -> int | None:
        """Integer points of a disc for two unscaled columns."""
        if len(self.attributes) != 2 or any(s != 1 for s in self.scales):
            return None
        r = int(self.theta)
        t2 = int(self.theta * self.theta)
        return sum(2 * _isqrt(t2 - x * x) + 1 for x in range(-r, r + 1))


    def lossless_index(self) -> tuple[Column, Column]:
        """Grid cells as wide as the distance: a cell of A meets itself and its neighbours."""
        cells = [F.col(c) if not self.theta else F.floor(F.col(c) / (self.theta * s)).cast("double") for c, s in zip(self.attributes, self.scales)]
        steps = [()]
        for _ in self.attributes:
            steps = [(*x, i) for x in steps for i in ((-1, 0, 1) if self.theta else (0,))]
        none = F.greatest(*[c.isNull() for c in cells], F.lit(False))
        near = F.array(*[_keyed(*[c + i for c, i in zip(cells, step)]) for step in steps])
        return F.when(~none, near), F.when(~none, F.array(_keyed(*[c + 0 for c in cells])))


def _isqrt(n: int) -> int:
    from math import isqrt

    return isqrt(n)


def euclidean(cols: list[str], theta: float, scales: list[float] | None = None) -> Rule:
    return Euclidean(tuple(cols), (), (), theta, tuple(scales or [1.0] * len(cols)))


@dataclass(frozen=True)
class VectorDistance(Rule):
    """Euclidean distance of array columns at most theta."""

    theta: float = 0.0

    def condition(self, a: str = "a", b: str = "b") -> Column:
        c = self.attributes[0]
        sq = F.zip_with(F.col(f"{a}.{c}"), F.col(f"{b}.{c}"), lambda x, y: (x.cast("double") - y) * (x.cast("double") - y))
        return F.aggregate(sq, F.lit(0.0), lambda s, x: s + x) <= self.theta**2


def vector_distance(col: str, theta: float) -> Rule:
    return VectorDistance((col,), (), (), theta)


@dataclass(frozen=True)
class Hamming(Rule):
    theta: int = 0
    bits: int = 50

    def condition(self, a: str = "a", b: str = "b") -> Column:
        c = self.attributes[0]
        return F.bit_count(F.col(f"{a}.{c}").bitwiseXOR(F.col(f"{b}.{c}"))) <= self.theta

    def ball_size(self) -> int:
        return sum(comb(self.bits, i) for i in range(self.theta + 1))


    def lossless_index(self) -> tuple[Column, Column]:
        """The bits in ``theta + 1`` pieces: one of them is equal."""
        v, n = F.col(self.attributes[0]), self.theta + 1
        cuts = [self.bits * i // n for i in range(n + 1)]
        piece = lambda lo, hi: F.shiftright(v, lo).bitwiseAND(F.lit((1 << (hi - lo)) - 1).cast("long"))
        own = F.when(v.isNotNull(), F.array(*[_keyed(F.lit(i), piece(cuts[i], cuts[i + 1])) for i in range(n)]))
        return own, own


def hamming(col: str, theta: int, bits: int = 50) -> Rule:
    return Hamming((col,), (), (), theta, bits)


@dataclass(frozen=True)
class GramSimilarity(Rule):
    """Jaccard similarity of gram arrays at least ``least``; two empty arrays do not match."""

    least: float = 0.0

    def condition(self, a: str = "a", b: str = "b") -> Column:
        x, y = F.col(f"{a}.{self.attributes[0]}"), F.col(f"{b}.{self.attributes[0]}")
        return F.size(F.array_intersect(x, y)) >= F.greatest(F.lit(1.0), self.least * F.size(F.array_union(x, y)))


    def lossless_index(self) -> tuple[Column, Column] | None:
        """Prefixes in the order of hashes: of n grams a similar set shares one of the first n - ceil(least n) + 1."""
        if self.least <= 0:
            return None
        hashes = F.array_sort(F.array_distinct(F.transform(F.col(self.attributes[0]), lambda g: F.xxhash64(g))))
        n = F.size(hashes)
        own = F.slice(hashes, 1, F.greatest(F.lit(0), n - F.ceil(F.lit(self.least) * n - 1e-9).cast("int") + 1))
        return own, own


def qgram(col: str, least: float) -> Rule:
    return GramSimilarity((col,), (), (), least)


@dataclass(frozen=True)
class Edit(Rule):
    most: int = 0

    def condition(self, a: str = "a", b: str = "b") -> Column:
        c = self.attributes[0]
        d = F.levenshtein(F.col(f"{a}.{c}"), F.col(f"{b}.{c}"), self.most)
        return (d >= 0) & (d <= self.most)


    def lossless_index(self) -> tuple[Column, Column]:
        """A's text in ``most + 1`` pieces: one is untouched and stands in B's text at most ``most`` places away.

        Texts too short for pieces meet by one common key.
        """
        t, n = F.col(self.attributes[0]), self.most + 1
        size = F.floor(F.length(t) / n).cast("int")
        pieces = F.transform(F.sequence(F.lit(0), F.lit(self.most)), lambda i: _keyed(F.substr(t, i * size + 1, size)))
        short = F.array(_keyed(F.lit("")))
        sizes = F.filter(F.sequence(F.floor(F.greatest(F.length(t) - self.most, F.lit(0)) / n).cast("int"), F.floor((F.length(t) + self.most) / n).cast("int")), lambda k: k > 0)
        spots = F.transform(sizes, lambda k: F.transform(F.sequence(F.lit(1), F.greatest(F.length(t) - k + 1, F.lit(1))), lambda i: _keyed(F.substr(t, i, k))))
        mine = F.when(size > 0, F.array_distinct(pieces)).otherwise(short)
        other = F.array_distinct(F.concat(F.flatten(spots), F.when(F.length(t) <= 2 * self.most, short).otherwise(F.array().cast("array<bigint>"))))
        return F.when(t.isNotNull(), mine), F.when(t.isNotNull(), other)


def edit(col: str, most: int) -> Rule:
    return Edit((col,), (), (), most)


@dataclass(frozen=True)
class Digits(Rule):
    """Digit strings of one length that differ in at most ``most`` places."""

    most: int = 0

    def condition(self, a: str = "a", b: str = "b") -> Column:
        c = self.attributes[0]
        x, y = (F.regexp_replace(F.col(f"{s}.{c}"), "[^0-9]", "") for s in (a, b))
        off = F.zip_with(F.split(x, ""), F.split(y, ""), lambda p, q: (p != q).cast("int"))
        return (F.length(x) == F.length(y)) & (F.aggregate(off, F.lit(0), lambda s, v: s + v) <= self.most)


    def lossless_index(self) -> tuple[Column, Column]:
        """The digits in ``most + 1`` pieces by place: one of them is equal, and so is the length."""
        x, n = F.regexp_replace(F.col(self.attributes[0]), "[^0-9]", ""), self.most + 1
        size = F.length(x)
        cut = lambda i: F.floor(size * i / n).cast("int")
        own = F.array(*[_keyed(size, F.lit(i), F.substr(x, cut(i) + 1, cut(i + 1) - cut(i))) for i in range(n)])
        own = F.when(F.col(self.attributes[0]).isNotNull(), own)
        return own, own


def digits(col: str, most: int) -> Rule:
    return Digits((col,), (), (), most)


@dataclass(frozen=True)
class Phonetic(Rule):
    def condition(self, a: str = "a", b: str = "b") -> Column:
        return F.soundex(F.col(f"{a}.{self.attributes[0]}")) == F.soundex(F.col(f"{b}.{self.attributes[0]}"))


    def lossless_index(self) -> tuple[Column, Column]:
        own = F.array(_keyed(F.soundex(F.col(self.attributes[0]))))
        return own, own


def phonetic(col: str) -> Rule:
    return Phonetic((col,))


@dataclass(frozen=True)
class AllOf(Rule):
    def condition(self, a: str = "a", b: str = "b") -> Column:
        ordered = sorted(self.parts, key=lambda r: not r.keys)
        out = ordered[0].condition(a, b)
        for r in ordered[1:]:
            out = out & r.condition(a, b)
        return out

    def lossless_index(self) -> tuple[Column, Column] | None:
        """The index of the part that comes first, equality parts joined to every key."""
        keys = [F.col(k) for k in self.keys]
        found = [x for r in self.parts if not r.keys and (x := r.lossless_index())]
        if not found:
            return (F.array(_keyed(*keys)), F.array(_keyed(*keys))) if keys else None
        return found[0] if not keys else tuple(F.transform(x, lambda k: _keyed(k, *keys)) for x in found[0])

    def ball_size(self) -> int | None:
        sizes = [r.ball_size() for r in self.parts]
        if any(s is None for s in sizes):
            return None
        out = 1
        for s in sizes:
            out *= s
        return out


def all_of(*parts: Rule) -> Rule:
    attributes = tuple(dict.fromkeys(c for r in parts for c in r.attributes))
    return AllOf(attributes, tuple(k for r in parts for k in r.keys), parts)
