import random

import __spark_entry__ as entry
from pyspark.sql import functions as F

from tests.oracle import SF
from veil.operators import similar


def _rows(n=240):
    """Near copies in clusters, exact copies, members that are everywhere, small and empty sets, records without a key."""
    r, rows = random.Random(5), []
    for i in range(n):
        c = random.Random(r.randrange(12))
        base = c.sample(range(1000), c.choice([3, 9, 30, 60]))
        s = {v for v in base if r.random() > 0.03} | {r.randrange(10_000) for _ in range(r.choice([0, 0, 1, 4]))} | {-1, -2}
        rows.append((i, i % 2, r.choice(["x", "x", "y", None]), sorted(s)))
    rows += [(n + i, i % 2, "x", [7, 8]) for i in range(40)] + [(n + 40 + i, i % 2, "x", []) for i in range(3)] + [(n + 43 + i, i % 2, "x", [i % 3]) for i in range(6)]
    return rows


def _brute(rows):
    out = {}
    for i, s, k, g in rows:
        links = 0 if k is None or not g else sum(
            1 for _, t, l, h in rows if t != s and l == k and 100 * len(set(g) & set(h)) >= 75 * len(set(g) | set(h))
        )
        out[i] = (min(j for j, _, l, h in rows if l == k and g == h), links)
    return out


def test_links_equal_brute_force(spark, monkeypatch):
    rows = _rows()
    want = _brute(rows)
    assert sum(n for _, n in want.values()) > 1000 and any(n == 0 for _, n in want.values())
    df = spark.createDataFrame(rows, "rid long, side int, key string, g array<long>")
    for block in (256, 3):  # 3: groups of many blocks
        monkeypatch.setattr(similar, "BLOCK", block)
        got = {r.rid: (r.class_id, r.n_links) for r in similar.link_counts(df.repartition(5), "key", F.col("g"), 0.75).collect()}
        assert got == want
    assert similar.link_counts(df.limit(0), "key", F.col("g"), 0.75).count() == 0


def test_overlaps_are_exact_over_several_steps(monkeypatch):
    import numpy as np

    monkeypatch.setattr(similar, "COLUMNS", 4)
    r = random.Random(2)
    sets = [set(r.sample(range(60), r.randrange(1, 40))) for _ in range(20)]
    got = similar.overlaps([np.array(sorted(s)) for s in sets])
    assert all(got[i, j] == len(sets[i] & sets[j]) for i in range(20) for j in range(20) if i != j)


def test_one_row_per_document_however_many_copies(spark, tmp_path):
    d = spark.read.parquet(f"{SF}/documents.parquet").limit(3)
    copies = d.crossJoin(spark.range(400).withColumnRenamed("id", "c")).withColumn("doc_id", F.col("doc_id") + 1000 * F.col("c")).drop("c")
    copies.write.parquet(f"{tmp_path}/documents.parquet")
    rows = entry.queries()["w14_texts"](spark, str(tmp_path)).collect()
    assert len(rows) == 1200 and len({r.class_id for r in rows}) == 3


def test_long_lists_and_crowded_parts_give_the_same_links(spark, monkeypatch):
    rows = _rows()
    df = spark.createDataFrame(rows, "rid long, side int, key string, g array<long>")
    monkeypatch.setattr(similar, "LIST", 3)
    monkeypatch.setattr(similar, "ENTRIES", 50)
    got = {r.rid: (r.class_id, r.n_links) for r in similar.link_counts(df, "key", F.col("g"), 0.75).collect()}
    assert got == _brute(rows)


def test_shared_members_do_not_group_unlike_sets(spark, monkeypatch):
    """A ring of sets that share rare members with their neighbours only: groups are those of the near copies, not the whole ring."""
    r, rows = random.Random(3), []
    for i in range(300):
        own = [1000 * i + j for j in range(12)] + [1000 * ((i + 1) % 300) + j for j in range(12)]
        rows.append((i, i % 2, "x", own + [-1 - v for v in r.sample(range(300), 16)]))
    rows += [(300 + i, (i + 1) % 2, "x", rows[i][3][1:]) for i in range(0, 300, 10)]
    found, groups_of = [], similar.connected_components

    def watched(edges):
        out = groups_of(edges)
        found.append(out.groupBy("component").count().agg(F.max("count")).first()[0])
        return out

    monkeypatch.setattr(similar, "connected_components", watched)
    df = spark.createDataFrame(rows, "rid long, side int, key string, g array<long>")
    got = {x.rid: (x.class_id, x.n_links) for x in similar.link_counts(df, "key", F.col("g"), 0.75).collect()}
    assert got == _brute(rows) and sum(n for _, n in got.values()) == 60
    assert found[0] <= 20


def test_sketches_rule_out_no_similar_sets():
    import numpy as np

    r = np.random.default_rng(4)
    for n in (1, 2, 5, 40, 700, 9000):
        for _ in range(20):
            a = similar.mix(r.integers(0, 1 << 60, n).astype(np.uint64))
            b = np.r_[a[n // 9 :], similar.mix(r.integers(0, 1 << 60, n // 7).astype(np.uint64))]
            both = n - n // 9
            if both >= 0.75 * (len(a) + len(b) - both):
                assert similar.may_link(len(a), len(b), similar.sketch(a), similar.sketch(b), 0.75)
    far = [similar.mix(r.integers(0, 1 << 60, 500).astype(np.uint64)) for _ in range(2)]
    assert not similar.may_link(500, 500, similar.sketch(far[0]), similar.sketch(far[1]), 0.75)


def test_runs_of_words_equal_sets_of_strings():
    import pyarrow as pa

    from veil.functions.grams import run_hashes

    texts = ["a b c d a b c", " a  b\tc\nd a\x0bb c ", "a b", "a", "", " \n", None, "a b c", "c b a", "ä ö ü", "ab c d", "a bc d", "x " * 5, "x " * 9]
    texts += [" ".join(f"w{(i * 7) % 11}" for i in range(n)) for n in (3, 50, 400_000)]
    want = []
    for t in texts:
        w = (t or "").split()
        want.append({" ".join(w[i : i + 3]) for i in range(max(len(w) - 2, 1))} if w else set())
    got = run_hashes(pa.array(texts), 3).to_pylist()
    assert got == run_hashes(pa.array(["z z z", *texts]).slice(1), 3).to_pylist()
    assert all(g == sorted(set(g)) and len(g) == len(w) for g, w in zip(got, want))
    assert all((set(g) == set(h)) == (w == v) for g, w in zip(got, want) for h, v in zip(got, want))
