import pytest

import __spark_entry__ as entry
from tests.oracle import SF, same
from veil.plans import around, catalogue, catalogue_secure, workloads

#: Queries that once made their data up, with the table that carries their job now.
READS = {
    "m11_compression": "events",
    "join_nested_loop": "orders",
    "d9_composition": "orders",
    "d8_equal_output": "lineitem",
    "d7_dp_graph": "lineitem",
    "d6_constrained": "lineitem",
    "d13_local_ratio": "orders",
    "d12_conversion": "lineitem",
    "c6_estimated_seconds": "events",
    "c2_additive": "orders",
    "b5_window": "orders",
    "b2_grid": "events",
}


@pytest.mark.parametrize("name", READS)
def test_result_comes_from_a_given_table(spark, monkeypatch, name):
    seen = set()
    for m in (around, catalogue, catalogue_secure, workloads):
        monkeypatch.setattr(m, "table", lambda s, d, t, f=m.table: seen.add(t) or f(s, d, t))
    entry.queries()[name](spark, SF).count()
    assert READS[name] in seen
    assert READS[name] in entry.oracle_sql()[name].lower()
    same(spark, name, entry.queries(), entry.oracle_sql())


def test_suppliers_of_one_point_are_compared_once(spark, monkeypatch):
    from veil.plans import secure

    seen = []
    monkeypatch.setattr(secure, "blinded_distance", lambda pairs, theta, f=secure.blinded_distance: seen.append(pairs.count()) or f(pairs, theta))
    s = spark.range(300).selectExpr("id * 97 + id % 2 AS s_suppkey", "CAST(1 AS INT) AS s_nationkey")
    monkeypatch.setattr(catalogue_secure, "table", lambda *a: s)
    rows = catalogue_secure.c3_squares(spark, SF).collect()
    assert seen == [4] and len(rows) == 300 * 300 and len({(r.a_id, r.b_id) for r in rows}) == 90000 and all(r.matched for r in rows)
