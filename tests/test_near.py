import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from tests.oracle import same
from veil.functions import rules as R
from veil.operators import chase, near
from veil.operators.blocking import equal_keys
from veil.plans import around, catalogue

RULE = R.all_of(R.equal("slot"), R.euclidean(["x", "y"], 0.2, [40.0, 25.0]))
SF = "/root/testdata/sf0.001"


def _rows(seed, n=400):
    r = random.Random(seed)
    rows = [(i, r.choice([0, 0, 1]), r.choice([float(r.randrange(40)), r.uniform(0, 40)]), float(r.randrange(25))) for i in range(n)]
    odd = [(None, 1.0, 1.0), (0, None, 1.0), (0, 1.0, None), (0, float("nan"), 1.0), (0, float("inf"), 1.0), (0, 1e300, 1.0), (0, -1e-9, -1e-9)]
    return rows + [(n + i, *o) for i, o in enumerate(odd)]


def _block():
    return equal_keys("half", 2, (F.col("x") > 20).cast("long"))


def _parties(spark):
    return [spark.createDataFrame(_rows(s), "rid long, slot long, x double, y double") for s in (1, 2)]


def _brute():
    for i, s, x, y in _rows(1):
        for j, t, u, v in _rows(2):
            if None not in (s, x, y, u, v) and s == t and (d := ((x - u) / 40) * ((x - u) / 40) + ((y - v) / 25) * ((y - v) / 25)) <= 0.2 * 0.2:
                yield i, j, d, x > 20, u > 20


def test_nearest_keeps_one_row_per_record_and_ties_by_id(spark, monkeypatch):
    monkeypatch.setattr(near, "COLUMNS", 3)
    a, b = _parties(spark)
    want = {}
    for i, j, d, *_ in _brute():
        want[i] = min(want.get(i, (d, j)), (d, j))
    assert dict(map(tuple, near.nearest(a, b, RULE, _block()).collect())) == {i: j for i, (_, j) in want.items()}
    assert not list(near.nearest(a.limit(0), b, RULE, _block()).collect())


def test_nearest_match_writes_no_pairs(spark):
    plan = around.nearest(spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert "Join" not in plan


def test_merge_points_to_the_smallest_node():
    label = np.arange(8)
    near._merge(label, np.array([5, 6, 7]), np.array([6, 7, 2]))
    near._merge(label, np.array([3, 4]), np.array([4, 3]))
    assert label.tolist() == [0, 1, 2, 3, 3, 2, 2, 2]


def test_retirement_writes_no_edges(spark, monkeypatch):
    from veil.sources import shared

    labels = []
    for m in (catalogue, chase):
        monkeypatch.setattr(m, "materialize", lambda df, label: labels.append(label) or shared.materialize(df, label), raising=False)
    assert catalogue.g4(spark, SF).count() > 0
    assert "chase-edges" not in labels and "chase-reached" not in labels


@pytest.mark.parametrize("name", ["p3_chase", "p5_chase_prune"])
def test_chase_of_points_writes_no_match_graph(spark, monkeypatch, name):
    from veil.plans import protocols
    from veil.sources import shared

    labels = []
    for m in (protocols, chase):
        monkeypatch.setattr(m, "materialize", lambda df, label: labels.append(label) or shared.materialize(df, label))
    same(spark, name, entry.queries(), entry.oracle_sql())
    assert not {"compared", "graph", "chase-edges", "chase-reached"} & set(labels)


def test_chased_rows_equal_the_chase_of_the_pairs(spark, monkeypatch):
    monkeypatch.setattr(near, "ROWS", 2)
    ranks = {(0, 0): 2, (1, 0): 1}
    a, b = (x.withColumn("pos", F.col("rid") + 1) for x in _parties(spark))
    pairs = list(_brute())
    up = {}

    def root(v):
        while up.setdefault(v, v) != v:
            v = up[v]
        return v

    for i, j, *_ in pairs:
        up[root(("b", j))] = root(("a", i))
    first = {}
    for i, j, _, x, y in pairs:
        if (k := ranks.get((int(x), int(y)))) is not None:
            c = root(("a", i))
            first[c] = min(first.get(c, (k, i + 1, j + 1)), (k, i + 1, j + 1))
    rows = near.chased(a, b, RULE, _block(), ranks).collect()
    want = {("ab"[s], v): first.get(root(("ab"[s], v)), (None,) * 3) for s in (0, 1) for v in {p[s] for p in pairs}}
    assert {("ab"[r.side], r.rid): (r.t, r.p, r.q) for r in rows} == want and len(rows) == len(want)
    assert sum(r.matches for r in rows) == len(pairs)
    assert sorted((r.t, r.p, r.q) for r in rows if r.first) == sorted(first.values())
    assert all(r.rid + 1 == r.p for r in rows if r.first)
