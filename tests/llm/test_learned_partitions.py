import numpy as np
import pytest
from pyspark.sql import functions as F

from veil.llm import learned_partitions as L

DDL = "vec_id long, embedding array<float>, score string"


def frame(spark, rows):
    return spark.createDataFrame([(i, None if v is None else [None if x is None else float(x) for x in v], "s") for i, v in rows], DDL)


def brute(rows, k):
    x = {i: np.array(v, np.float32).astype(np.float64) for i, v in rows}
    ids = np.array(sorted(x))
    m = np.stack([x[i] for i in ids])
    out = {}
    for q in ids[ids % 20 == 0]:
        s = (m * x[q]).sum(1)
        keep = ids != q
        order = np.lexsort((ids[keep], -s[keep]))[:k]
        out[int(q)] = list(zip(ids[keep][order].tolist(), s[keep][order].tolist()))
    return out


def search(spark, rows, k=20, **kw):
    out = {}
    for r in L.search(frame(spark, rows), F.col("vec_id") % 20 == 0, k, **kw).orderBy("query_id", "rank").collect():
        out.setdefault(r.query_id, []).append((r.vec_id, r.score))
    return out


def test_small_tables_are_exact_with_ties_and_invalid_vectors(spark):
    r = np.random.default_rng(1)
    good = [(i, r.normal(size=8)) for i in range(90)] + [(i, np.ones(8)) for i in range(100, 140)]
    bad = [(200, None), (220, [0.0] * 8), (240, [1.0, None] + [0.0] * 6), (260, [float("nan")] * 8), (280, [float("inf")] + [0.0] * 7), (300, [1.0, 2.0])]
    got = search(spark, good + bad + [good[0], good[100]], probes=10**6)
    assert got == brute(good, 20)


def test_few_candidates_and_empty(spark):
    rows = [(i, [1.0, float(i)]) for i in range(5)]
    assert search(spark, rows) == brute(rows, 20)
    assert search(spark, rows[:1]) == {} and search(spark, []) == {}


def test_repeated_ids_keep_all_their_vectors(spark):
    r = np.random.default_rng(4)
    rows = [(i, r.normal(size=4)) for i in range(30)] + [(5, [900.0] * 4), (20, [1.0, 0, 0, 0]), (20, [1.0, 0, 0, 0])]
    m = np.array([np.array(v, np.float32).astype(np.float64) for _, v in rows[:-1]])
    ids = np.array([i for i, _ in rows[:-1]])
    want = []
    for j in np.flatnonzero(ids % 20 == 0):
        s = (m * m[j]).sum(1)
        keep = ids != ids[j]
        order = np.lexsort((ids[keep], -s[keep]))[:20]
        want += [(ids[j], n + 1, i, x) for n, (i, x) in enumerate(zip(ids[keep][order], s[keep][order]))]
    df = frame(spark, rows + [(None, [1.0, 2, 3, 4])])
    got = [tuple(x) for x in L.search(df, F.col("vec_id") % 20 == 0, 20, probes=10**6).collect()]
    assert sorted(got) == sorted(want)


@pytest.mark.parametrize("sf", ["sf0.01", "sf0.1"])
def test_recall_on_the_given_vectors(spark, sf):
    v = spark.read.parquet(f"/root/testdata/{sf}/embeddings.parquet")
    n = v.count()
    assert L.levels(n)[0] >= 8
    wanted, found = L.recall(v, F.col("vec_id") % 20 == 0).first()
    assert wanted == 20 * v.filter("vec_id % 20 = 0").count() and found >= 0.9 * wanted
    x = dict(v.select("vec_id", "embedding").collect())
    exact = brute(list(x.items()), 20)
    got = {}
    for r in L.search(v, F.col("vec_id") % 20 == 0).collect():
        got.setdefault(r.query_id, {})[r.vec_id] = r.score
    hit = sum(len({i for i, _ in exact[q]} & got[q].keys()) for q in exact)
    assert hit >= 0.9 * wanted and all(abs(dict(exact[q]).get(i, s) - s) < 1e-12 for q in exact for i, s in got[q].items())


def test_two_levels_and_blocks_of_queries(spark, monkeypatch):
    monkeypatch.setattr(L, "MOST_PARTS", 8)
    monkeypatch.setattr(L, "PART_ROWS", 100)
    monkeypatch.setattr(L, "BLOCK_ROWS", 150)
    monkeypatch.setattr(L, "QUERY_ROWS", 7)
    r = np.random.default_rng(6)
    centres = r.normal(size=(20, 12)) * 2
    rows = [(i, centres[i % 20] + r.normal(size=12)) for i in range(1800)]
    assert L.levels(1800) == (8, 3)
    want, got = brute(rows, 20), search(spark, rows)
    hit = sum(len({i for i, _ in want[q]} & {i for i, _ in got[q]}) for q in want)
    assert got.keys() == want.keys() and hit >= 0.9 * 20 * len(want)
    assert search(spark, rows, probes=10**6) == want


def test_recall_with_several_parts(spark, monkeypatch):
    monkeypatch.setattr(L, "BLOCK_ROWS", 400)
    r = np.random.default_rng(2)
    centres = r.normal(size=(30, 16)) * 2
    rows = [(i, centres[i % 30] + r.normal(size=16)) for i in range(4000)] + [(5000 + i, centres[0]) for i in range(900)]
    want, got = brute(rows, 20), search(spark, rows)
    hit = sum(len({i for i, _ in want[q]} & {i for i, _ in got[q]}) for q in want)
    assert got.keys() == want.keys() and hit >= 0.9 * 20 * len(want)
    assert all(len(v) == 20 for v in got.values())


def test_cut_is_balanced():
    r = np.random.default_rng(3)
    x = r.normal(size=(1000, 8))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    g = L.neighbour_graph(x, 8)
    part = L.balanced_cut(x, g, 8, r)
    assert np.bincount(part, minlength=8).max() <= np.ceil(1.05 * 1000 / 8) and (part >= 0).all()
    kept = (part[g] == part[:, None]).mean()
    assert kept > 2 * (r.permutation(part)[g] == part[:, None]).mean()
