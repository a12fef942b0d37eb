"""Pairs of points of one key within a scaled distance, met in blocks and never written.

For rules that join equality parts with one Euclidean part. Each record is
shuffled once, by the equality parts. Inside a key both parties are sorted by
bin, by strips of the first coordinate as wide as the distance, and by the last
coordinate; runs of Alice's records meet the runs of Bob's that are in reach, and
the rule's own arithmetic decides every pair. What leaves a task are counts or
one row per record, so disk grows with the records and not with the pairs.
"""

from __future__ import annotations

from collections import Counter, defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veil.functions.rules import Euclidean, Rule
from veil.operators.blocking import Blocking
from veil.sources.shared import ship

#: Rows of Alice and of Bob in a block: what fits the caches.
ROWS, COLUMNS = 64, 2048
#: Strips and reaches are this much wider than the distance, so rounding loses no pair.
SLACK = 1 + 1e-9
#: No rank, place or id yet.
MOST = np.iinfo(np.int64).max


def euclidean_part(rule: Rule) -> Euclidean | None:
    """The distance of a rule made of equality parts and one Euclidean part with a positive distance; else None."""
    parts = [rule] if isinstance(rule, Euclidean) else [r for r in rule.parts if not r.keys]
    one = parts[0] if len(parts) == 1 else None
    return one if isinstance(one, Euclidean) and one.theta > 0 and set(rule.attributes) == {*rule.keys, *one.attributes} else None


class Side:
    """One party's points of a key, sorted by bin, strip and last coordinate."""

    def __init__(self, t: pa.Table, part: Euclidean):
        self.rid = t.column("rid").to_numpy()
        self.x = [t.column(f"x{i}").to_numpy() for i in range(len(part.attributes))]
        self.bin = t.column("bin").to_numpy()
        self.extra = {c: t.column(c).to_numpy(zero_copy_only=False) for c in t.column_names if c in ("kept", "pos")}
        width = part.theta * part.scales[0] * SLACK
        strip = np.clip(np.floor(self.x[0] / width), -(2.0**40), 2.0**40).astype(np.int64)
        order = np.lexsort((self.x[-1], strip, self.bin))
        self.rid, self.bin, strip = self.rid[order], self.bin[order], strip[order]
        self.x = [np.ascontiguousarray(v[order]) for v in self.x]
        self.extra = {c: v[order] for c, v in self.extra.items()}
        new = np.flatnonzero(np.r_[True, (np.diff(strip) != 0) | (np.diff(self.bin) != 0)]) if len(strip) else np.array([], int)
        self.runs = [(int(self.bin[i]), int(strip[i]), int(i), int(j)) for i, j in zip(new, np.r_[new[1:], len(strip)])]


def blocks(a: Side, b: Side, part: Euclidean) -> Iterator[tuple[int, int, int, int, int, int, np.ndarray, np.ndarray]]:
    """``a_bin, b_bin, i, j, k, l, d, hit``: squared distances of Alice's rows i..j to Bob's k..l and whether they are near."""
    by_strip = defaultdict(list)
    for bin_, strip, k, l in b.runs:
        by_strip[strip].append((bin_, k, l))
    ya, yb = a.x[-1], b.x[-1]
    limit, wide = part.theta * part.theta, part.theta * part.scales[-1] * SLACK
    for a_bin, strip, start, end in a.runs:
        near = [r for s in (strip - 1, strip, strip + 1) for r in by_strip.get(s, ())]
        for i in range(start, end, ROWS):
            j = min(i + ROWS, end)
            low, high = ya[i], ya[j - 1]
            reach = wide + 1e-12 * max(abs(low), abs(high))
            for b_bin, first, last in near:
                k0 = first + int(np.searchsorted(yb[first:last], low - reach, "left"))
                k1 = first + int(np.searchsorted(yb[first:last], high + reach, "right"))
                for k in range(k0, k1, COLUMNS):
                    l = min(k + COLUMNS, k1)
                    d = None
                    for u, v, s in zip(a.x, b.x, part.scales):
                        e = np.subtract(u[i:j, None], v[None, k:l])
                        e /= s
                        e *= e
                        d = e if d is None else np.add(d, e, out=d)
                    yield a_bin, b_bin, i, j, k, l, d, d <= limit


def _points(party: DataFrame, rule: Rule, blocking: Blocking, *extra: str) -> DataFrame:
    """Keys, coordinates, id and bin of the records that can match at all: no nulls, finite numbers."""
    part = euclidean_part(rule)
    x = [F.col(c).cast("double") for c in part.attributes]
    ok: Column = F.lit(True)
    for v in x:
        ok = ok & v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf"))
    for k in rule.keys:
        ok = ok & F.col(k).isNotNull()
    keys = [F.col(k).alias(f"k{i}") for i, k in enumerate(rule.keys)] or [F.lit(0).alias("k0")]
    return blocking.assign(party.filter(ok)).select(*keys, F.col("rid").alias("rid"), *[v.alias(f"x{i}") for i, v in enumerate(x)], "bin", *extra)


def _cogroup(a: DataFrame, b: DataFrame, rule: Rule, f, ddl: str) -> DataFrame:
    ship(a.sparkSession)
    keys = [f"k{i}" for i in range(max(1, len(rule.keys)))]
    return a.groupBy(*keys).cogroup(b.groupBy(*keys)).applyInArrow(f, ddl)


def pair_counts(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking) -> DataFrame:
    """``a_bin, b_bin, n, n_found``: accepted pairs per bin pair, and those of which both records have ``kept`` (all, where parties do not carry it).

    The blocking gives every record one bin and need not hold every match.
    """
    part = euclidean_part(rule)
    marked = "kept" in a.columns
    extra = ("kept",) if marked else ()

    def count(x: pa.Table, y: pa.Table) -> pa.Table:
        n, found = Counter(), Counter()
        with np.errstate(all="ignore"):
            p, q = Side(x, part), Side(y, part)
            for a_bin, b_bin, i, j, k, l, _, hit in blocks(p, q, part):
                every = int(np.count_nonzero(hit))
                n[a_bin, b_bin] += every
                found[a_bin, b_bin] += int(np.count_nonzero(hit[p.extra["kept"][i:j]][:, q.extra["kept"][k:l]])) if marked and every else every
        rows = [(*k, v, found[k]) for k, v in n.items() if v]
        cols = list(zip(*rows)) if rows else [[], [], [], []]
        return pa.table([pa.array(c, pa.int64()) for c in cols], ["a_bin", "b_bin", "n", "n_found"])

    met = _cogroup(_points(a, rule, blocking, *extra), _points(b, rule, blocking, *extra), rule, count, "a_bin long, b_bin long, n long, n_found long")
    return met.groupBy("a_bin", "b_bin").agg(F.sum("n").alias("n"), F.sum("n_found").alias("n_found"))


def nearest(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking) -> DataFrame:
    """``a_id, b_id``: each matching record of A with its nearest match, ties to the smaller id."""
    part = euclidean_part(rule)

    def find(x: pa.Table, y: pa.Table) -> pa.Table:
        with np.errstate(all="ignore"):
            p, q = Side(x, part), Side(y, part)
            best, who = np.full(len(p.rid), np.inf), np.full(len(p.rid), np.iinfo(np.int64).max)
            for _, _, i, j, k, l, d, hit in blocks(p, q, part):
                least = d.min(axis=1)
                rows = np.flatnonzero((least <= part.theta * part.theta) & (least <= best[i:j]))
                if not len(rows):
                    continue
                ids = np.where(d[rows] == least[rows, None], q.rid[k:l], np.iinfo(np.int64).max).min(axis=1)
                at = i + rows
                better = (least[rows] < best[at]) | (ids < who[at])
                best[at[better]], who[at[better]] = least[rows][better], ids[better]
            got = np.isfinite(best)
        return pa.table([pa.array(p.rid[got], pa.int64()), pa.array(who[got], pa.int64())], ["a_id", "b_id"])

    return _cogroup(_points(a, rule, blocking), _points(b, rule, blocking), rule, find, "a_id long, b_id long")


def _merge(label: np.ndarray, u: np.ndarray, v: np.ndarray) -> None:
    """Joins the trees of the edges ``u, v``: afterwards every node points to the smallest node of its component."""
    while len(u):
        x, y = label[u], label[v]
        apart = x != y
        u, v, x, y = u[apart], v[apart], x[apart], y[apart]
        np.minimum.at(label, np.maximum(x, y), np.minimum(x, y))
        while not np.array_equal(up := label[label], label):
            label[:] = up


def _first_seen(m: Side, w: Side, part: Euclidean, ranks: dict[tuple[int, int], int]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Component of every record (Alice's, then Bob's), and each of Alice's records' matches, rank and Bob's place of its first compared match."""
    n = len(m.rid)
    label = np.arange(n + len(w.rid))
    t, q = np.full(n, MOST), np.full(n, MOST)
    matches = np.zeros(n, np.int64)
    for a_bin, b_bin, i, j, k, l, _, hit in blocks(m, w, part):
        some = np.count_nonzero(hit, axis=1)
        if not some.any():
            continue
        matches[i:j] += some
        r, c = np.nonzero(hit & (label[i:j, None] != label[None, n + k : n + l]))
        _merge(label, i + r, n + k + c)
        rank = ranks.get((a_bin, b_bin))
        if rank is None:
            continue
        first = np.where(hit, w.extra["pos"][None, k:l], MOST).min(axis=1)
        at = i + np.flatnonzero((some > 0) & ((rank < t[i:j]) | ((rank == t[i:j]) & (first < q[i:j]))))
        t[at], q[at] = rank, first[at - i]
    return label, matches, t, q


def _lead(label: np.ndarray, p: np.ndarray, t: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Per component the record of Alice that its first compared match has; -1 where none is compared."""
    own = label[: len(p)]
    seeds = np.flatnonzero(t < MOST)
    seeds = seeds[np.lexsort((q[seeds], p[seeds], t[seeds], own[seeds]))]
    roots, at = np.unique(own[seeds], return_index=True)
    lead = np.full(len(label), -1)
    lead[roots] = seeds[at]
    return lead


def retirements(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking, ranks: dict[tuple[int, int], int]) -> DataFrame:
    """``rid, t, p, q`` of each record of A whose component of matches holds a compared match: the place of the first one.

    Parties carry ``pos``, their place in their bin; ``ranks`` numbers the bin
    pairs that are compared, a bounded table of the declared bins. Components
    never leave a key; edges inside what is already joined are dropped in their block.
    """
    part = euclidean_part(rule)

    def find(x: pa.Table, y: pa.Table) -> pa.Table:
        with np.errstate(all="ignore"):
            m, w = Side(x, part), Side(y, part)
            label, matches, t, q = _first_seen(m, w, part, ranks)
            own, p = label[: len(m.rid)], m.extra["pos"]
            lead = _lead(label, p, t, q)
            rows = np.flatnonzero((matches > 0) & (lead[own] >= 0))
            by = lead[own[rows]]
        return pa.table([pa.array(v, pa.int64()) for v in (m.rid[rows], t[by], p[by], q[by])], ["rid", "t", "p", "q"])

    return _cogroup(_points(a, rule, blocking, "pos"), _points(b, rule, blocking, "pos"), rule, find, "rid long, t long, p long, q long")


def chased(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking, ranks: dict[tuple[int, int], int]) -> DataFrame:
    """``side, rid, bin, pos, matches, t, p, q, first`` of each record of both parties that matches at all.

    ``side`` is 0 for A and 1 for B; ``matches`` counts A's matches (B's rows: 0);
    ``t, p, q`` is the place of the first compared match of the record's
    component, null where none is compared; ``first`` marks the one record of A
    that this match has. Parties and ``ranks`` as in ``retirements``.
    """
    part, names = euclidean_part(rule), ["side", "rid", "bin", "pos", "matches", "t", "p", "q"]

    def find(x: pa.Table, y: pa.Table) -> pa.Table:
        with np.errstate(all="ignore"):
            m, w = Side(x, part), Side(y, part)
            n = len(m.rid)
            label, matches, t, q = _first_seen(m, w, part, ranks)
            p = m.extra["pos"]
            lead = _lead(label, p, t, q)
            mine, other = np.flatnonzero(matches), np.flatnonzero(label[n:] < n)  # the smallest node of what matches is Alice's
            by = lead[np.r_[label[:n][mine], label[n:][other]]]
            none = by < 0
            place = [np.r_[v, 0][by] for v in (t, p, q)]
            put = lambda v, u: np.r_[v[mine], u[other]]
            own = [np.repeat([0, 1], [len(mine), len(other)]), put(m.rid, w.rid), put(m.bin, w.bin), put(p, w.extra["pos"]), put(matches, np.zeros(len(w.rid), np.int64))]
            first = np.r_[by[: len(mine)] == mine, np.zeros(len(other), bool)]
        cols = [pa.array(v, pa.int64()) for v in own] + [pa.array(v, pa.int64(), mask=none) for v in place]
        return pa.table([*cols, pa.array(first, pa.bool_())], [*names, "first"])

    ddl = ", ".join(f"{c} long" for c in names) + ", first boolean"
    return _cogroup(_points(a, rule, blocking, "pos"), _points(b, rule, blocking, "pos"), rule, find, ddl)
