from collections import Counter

from pyspark.sql import functions as F

from veil.llm import systematic_mix as M


def plain_targets(sizes):
    """Cap and reshare until none is above."""
    names = sorted(sizes, key=lambda s: (s is None, s or ""))
    weight = {n: i % 3 + 1 for i, n in enumerate(names)}
    total, done = sum(sizes.values()), {}
    open_ = list(names)
    while open_:
        left = total - sum(done.values())
        share = {n: left * weight[n] / sum(weight[m] for m in open_) for n in open_}
        above = [n for n in open_ if share[n] > 3 * sizes[n]]
        if not above:
            return {**done, **share}
        done.update({n: 3.0 * sizes[n] for n in above})
        open_ = [n for n in open_ if n not in above]
    return done


def docs(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, source string, text string, target string")


def rows_of(counts):
    out = []
    for s, n, words in counts:
        out += [(len(out) + i, s, "w " * (words + i % 7), "t") for i in range(n)]
    return out


def test_targets_match_repeated_resharing(spark):
    for counts in ([("a", 30, 100), ("b", 2, 5), ("é", 9, 50), (None, 4, 1)], [("x", 1, 10)], [("a", 5, 0), ("b", 5, 3)], [("a", 3, 1), ("b", 400, 90), ("c", 1, 1), ("d", 2, 1)]):
        rows = rows_of(counts)
        sizes = Counter()
        for _, s, t, _ in rows:
            sizes[s] += len(t.split())
        got = {r.source: r.target for r in M.mix(M.sized(docs(spark, rows))).select("source", "target").distinct().collect()}
        want = plain_targets(dict(sizes))
        assert got.keys() == want.keys()
        for s in want:
            assert abs(got[s] - want[s]) < 1e-6 * max(1, want[s])


def test_copies_cross_integer_boundaries_and_sums_are_near(spark):
    rows = rows_of([("a", 300, 60), ("b", 900, 10), ("c", 60, 200)]) + [(5000, None, None, "t"), (5001, "a", "", "t"), (5001, "a", "", "t")]
    df = docs(spark, rows)
    one = M.mix(M.sized(df))
    got = one.groupBy("source").agg(F.sum("taken").alias("k"), F.first("target").alias("t"), F.max("copies").alias("m")).collect()
    for r in got:
        assert r.m <= 3 and (not r.t or abs(r.k - r.t) < 0.05 * r.t)
    again = M.mix(M.sized(df.repartition(5)))
    key = lambda x: sorted(map(str, x.select("doc_id", "source", "copies", "taken").collect()))
    assert key(one) == key(again)
    assert one.agg(F.sum("copies")).first()[0] == M.sample(df).count()
    assert M.sample(df).columns == df.columns and {r.target for r in M.sample(df).collect()} == {"t"}


def test_a_very_long_text_is_counted_whole(spark):
    rows = rows_of([("a", 20, 9)]) + [(900, "a", "w " * 400_000, "t")]
    got = {r.doc_id: r["size"] for r in M.mix(M.sized(docs(spark, rows))).collect()}
    assert got[900] == 400_000


def test_many_sources(spark):
    rows = [(i, f"s{i % 300}", "w " * (1 + i * i % 40), "t") for i in range(900)]
    sizes = Counter()
    for _, s, t, _ in rows:
        sizes[s] += len(t.split())
    got = {r.source: r.target for r in M.mix(M.sized(docs(spark, rows))).select("source", "target").distinct().collect()}
    want = plain_targets(dict(sizes))
    assert got.keys() == want.keys() and all(abs(got[s] - want[s]) < 1e-6 * max(1, want[s]) for s in want)


def test_empty_table(spark):
    assert M.mix(M.sized(docs(spark, []))).count() == 0 and M.sample(docs(spark, [])).count() == 0


def test_many_classes_give_the_same_copies(spark, monkeypatch):
    rows = rows_of([("a", 500, 20), ("b", 100, 40), (None, 90, 3)])
    one = lambda: sorted((r.doc_id, r.copies) for r in M.mix(M.sized(docs(spark, rows))).select("doc_id", "copies").collect())
    whole = one()
    monkeypatch.setattr(M, "LEAST_CLASSES", 1)
    assert one() == whole
    monkeypatch.setattr(M, "ROWS_PER_CLASS", 3)
    assert one() == whole and len({n for _, n in whole}) > 1
