import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from tests.oracle import SF, same
from tests.test_near import RULE, _block, _brute, _parties
from veil.operators import blocking as B
from veil.operators import near
from veil.plans import measure as M
from veil.plans import protocols as P

#: Queries that count pairs where records meet: none of their jobs carries pairs of ids.
COUNTED = ["p2_prune", "p7_suppressed", "b6_multi", "m4_recall", "p11_plain", "p1_padded", "p8_allpairs", "d2_same_output", "p2_prune_product", "p13_coin_flip", "p10_expanded", "p11_plain_product", "p14_window", "p15_one_sided", "p16_symmetric", "p19_coin_flip_prune", "p8_allpairs_product", "p9_intersect", "w2s_skewed"]


@pytest.mark.parametrize("name", COUNTED)
def test_no_pairs_are_shuffled_and_counts_equal_sql(spark, name):
    df = entry.queries()[name](spark, SF)
    assert "a_id" not in df._jdf.queryExecution().optimizedPlan().toString()
    same(spark, name, entry.queries(), entry.oracle_sql())


def test_counts_by_bin_pair_and_kept_records(spark, monkeypatch):
    monkeypatch.setattr(near, "ROWS", 2)
    a, b = (x.withColumn("kept", F.col("rid") % 3 != 0) for x in _parties(spark))
    want = {}
    for i, j, _, p, q in _brute():
        n = want.setdefault((int(p), int(q)), [0, 0])
        n[0] += 1
        n[1] += i % 3 != 0 and j % 3 != 0
    assert {(r.a_bin, r.b_bin): [r.n, r.n_found] for r in near.pair_counts(a, b, RULE, _block()).collect()} == want
    live = spark.createDataFrame([(0, 0), (1, 0)], "a_bin long, b_bin long")
    got = M.tally(P.Scope(a, b, live), RULE, _block()).first()
    assert got.n_truth == sum(n for n, _ in want.values()) and got.n_found == sum(m for (_, q), (_, m) in want.items() if q == 0)
    assert M.tally(P.Scope(a.limit(0), b), RULE, _block()).first() == (0, 0, None)


def test_two_runs_are_the_same_only_if_no_bin_pair_with_matches_differs(spark):
    a, b = _parties(spark)
    live = spark.createDataFrame([(0, 0), (0, 1), (1, 0), (1, 1)], "a_bin long, b_bin long")
    assert M.same_scope(P.Scope(a, b, live), P.Scope(a, b, live), RULE, _block()).first() == (True, True)
    assert M.same_scope(P.Scope(a, b, live), P.Scope(a, b, live.filter("a_bin = b_bin")), RULE, _block()).first() == (False, True)


def test_meeting_pairs_equal_pairing(spark):
    rows = [(1, 1, 2), (2, 2, 1), (3, 3, 3), (4, None, 2), (5, 3, 1), (6, None, None)]
    df = spark.createDataFrame(rows, "rid long, x long, y long")
    blk = B.multi("m", 4, [F.col("x"), F.col("y")])
    sets = [{x, y} - {None} for _, x, y in rows]
    assert B.meeting_pairs(df, df.filter("rid < 5"), blk).first().pairs == sum(bool(p & q) for p in sets for q in sets[:4])
    assert B.meeting_pairs(df, df.limit(0), blk).first().pairs == 0
