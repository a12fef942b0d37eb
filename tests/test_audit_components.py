import random

import pytest
from pyspark.sql import functions as F

from veil.functions import encode as E
from veil.functions import rules as R
from veil.operators.components import connected_components, merge_components
from veil.sources.shared import materialize
from veil.plans import audit as A
from veil.plans import coin_flip as CF


def test_worked_example(spark):
    t = A.with_output(A.universe(spark, [1, 2, 3, 4, 5, 6]), [1, 2])
    assert t.count() == 64 and A.dp_graph(t).count() == 192
    sized = t.withColumn("output", F.concat("output", F.array(F.size("members").cast("long") + 100)))
    assert A.output_classes(sized).count() == 20 and A.equal_output_graph(sized).count() == 108
    assert sorted(r.n for r in A.output_classes(sized).collect())[-4:] == [6, 6, 6, 6]
    edges = A.constrained_neighbors(t).collect()
    m = {r.db_id: set(r.members) for r in t.collect()}
    assert len(edges) == 96
    for e in edges:
        gone, new = m[e.x_db_id] - m[e.y_db_id], m[e.y_db_id] - m[e.x_db_id]
        assert len(gone) == len(new) == 1 and not (gone | new) & {1, 2}
    me = next(i for i, s in m.items() if s == {3, 4})
    assert sum(me in (e.x_db_id, e.y_db_id) for e in edges) == 4
    far = A.path_distance(t).agg(F.max("distance")).first()[0]
    assert far == 6


def test_suppression_witness_exceeds_its_bound():
    assert A.suppression_witness(1.6, 2, 10) == pytest.approx((0.1313, 0.0146), abs=2e-4)
    assert A.suppression_witness(0.1, 2, 10) == pytest.approx((0.00057, 0.00028), abs=1e-5)


def test_local_privacy_of_profiles():
    for x in (1, 3, 6):
        assert A.local_eps_of(CF.window_profile(10, x, 1.6)) == pytest.approx(1.6)


def plain_components(edges):
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    return {x: find(x) for x in parent}


@pytest.mark.parametrize("edges", [[(i, i + 1) for i in range(60)], [(0, i) for i in range(50)], [(5, 5)], [(i, i // 2) for i in range(1, 120)]])
def test_components(spark, edges):
    r = random.Random(1)
    nodes = {x for e in edges for x in e}
    new = dict(zip(sorted(nodes), r.sample(range(1000), len(nodes))))
    edges = [(new[a], new[b]) for a, b in edges] * 2
    got = {x.node: x.component for x in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == plain_components(edges)


def test_components_grow_with_new_edges(spark):
    r = random.Random(2)
    edges = [(r.randrange(300), r.randrange(300)) for _ in range(260)] + [(500, x) for x in range(400, 500)]
    edges = [(a, b) for a, b in edges if a != b]
    old, new = edges[::2], edges[1::2]
    table = lambda rows: materialize(spark.createDataFrame(rows, "a long, b long"), "t-edges")
    got = merge_components(connected_components(table(old)), table(new))
    assert {x.node: x.component for x in got.collect()} == plain_components(edges)
    assert got.count() == len(plain_components(edges))


def test_components_of_nothing_and_the_cap(spark):
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0
    with pytest.raises(RuntimeError):
        connected_components(spark.createDataFrame([(i, i + 1) for i in range(40)], "a long, b long"), max_rounds=1)


def test_encodings(spark):
    d = spark.createDataFrame([("ab",), ("abcd",), (None,), ("",)], "s string").select("s", E.qgrams(F.col("s")).alias("g"), E.bloom(F.col("s")).alias("v")).collect()
    assert [list(r.g) for r in d] == [[], ["abc", "bcd"], [], []]
    assert [r.v for r in d][0] == 0 and d[2].v is None and bin(d[1].v).count("1") <= 2
    with pytest.raises(ValueError):
        E.bloom(F.col("s"), bits=64)


def test_ball_sizes():
    assert R.hamming("v", 5).ball_size() == 2_369_936
    assert R.euclidean(["x", "y"], 1000.0).ball_size() == 3_141_549
    assert R.all_of(R.equal("d"), R.hamming("v", 1)).ball_size() == 51 and R.edit("s", 2).ball_size() is None


def test_rules_and_nulls(spark):
    a = spark.createDataFrame([(1, "0012", "smith"), (2, None, "x")], "rid long, d string, n string")
    b = spark.createDataFrame([(7, "0013", "smyth"), (8, "013", "smith"), (9, None, None)], "rid long, d string, n string")
    from veil.operators.exact import match_join

    got = lambda rule: sorted((r.a_id, r.b_id) for r in match_join(a, b, rule).collect())
    assert got(R.digits("d", 1)) == [(1, 7)] and got(R.edit("n", 1)) == [(1, 7), (1, 8)] and got(R.phonetic("n")) == [(1, 7), (1, 8)]
