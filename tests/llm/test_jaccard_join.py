import random
import re
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from veil.llm import jaccard_join as J
from veil.llm import word_hash


def brute_sets(texts):
    out = []
    for t in texts:
        low = re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
        w = re.findall(r"[^\x20\x09-\x0D]+", low)
        out.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    return out


def brute(rows):
    """doc ids with set sizes and smallest reachable ids."""
    sets = brute_sets([t for _, t in rows])
    parent = list(range(len(rows)))

    def find(i):
        while parent[i] != i:
            i = parent[i]
        return i

    for i, j in combinations(range(len(rows)), 2):
        a, b = sets[i], sets[j]
        if a and b and 100 * len(a & b) >= 75 * len(a | b):
            parent[find(i)] = find(j)
    ids = {}
    for i, (d, _) in enumerate(rows):
        if d is not None:
            ids[find(i)] = min(ids.get(find(i), d), d)
    return sorted(((d, len(sets[i]), ids.get(find(i)) if sets[i] else d) for i, (d, _) in enumerate(rows)), key=str)


def result(spark, rows):
    df = spark.createDataFrame([(d, t, 1) for d, t in rows], "doc_id long, text string, n long")
    return sorted(((r.doc_id, r.n_shingles, r.component_id) for r in J.jaccard_components(df).collect()), key=str)


def near_copies(seed, groups, size, words):
    r = random.Random(seed)
    vocab = [f"w{i}" for i in range(4000)]
    rows = []
    for g in range(groups):
        base = [r.choice(vocab) for _ in range(words)]
        for _ in range(size):
            c = list(base)
            for _ in range(r.randrange(0, max(2, words // 25))):
                c[r.randrange(len(c))] = r.choice(vocab)
            rows.append((len(rows), " ".join(c)))
    return rows


def test_edges(spark):
    rows = [(1, None), (2, ""), (3, " \n\t"), (4, "a b"), (5, "A  B"), (6, "a b c d e"), (6, "a b c d e"), (7, "x " * 3000), (8, "X " * 2999), (None, "a b"), (None, None), (9, "é b"), (10, "É b")]
    assert result(spark, rows) == brute(rows)


def test_empty(spark):
    assert result(spark, []) == []


@pytest.mark.parametrize("seed", [1, 2])
def test_many_small_groups(spark, seed):
    rows = near_copies(seed, 40, 6, 60) + near_copies(seed + 10, 20, 3, 200)
    rows = [(i, t) for i, (_, t) in enumerate(rows)]
    random.Random(seed).shuffle(rows)
    assert result(spark, rows) == brute(rows)


def test_one_large_group_with_outliers(spark):
    rows = near_copies(3, 1, 260, 120) + near_copies(4, 8, 4, 120)
    passage = " ".join(f"common{i}" for i in range(60))
    rows = [(i, t) for i, (_, t) in enumerate(rows)]
    rows += [(1000 + i, passage + " " + " ".join(f"own{i}x{j}" for j in range(15 + i % 7))) for i in range(60)]
    assert result(spark, rows) == brute(rows)


def test_long_text_in_segments():
    r = random.Random(1)
    data = " ".join(f"w{r.randrange(10**6)}" for _ in range(30_000)).encode()
    whole = word_hash.word_hashes(data)
    cut = [np.concatenate(c) for c in zip(*word_hash.segments(data, size=1 << 12))]
    assert all((a == b).all() for a, b in zip(whole, cut))


def test_representatives(spark):
    rows = near_copies(5, 5, 4, 80)
    df = spark.createDataFrame(rows + [(900, None), (901, "")], "doc_id long, text string")
    kept = {r.doc_id for r in J.keep_representatives(df).collect()}
    want = {c for _, n, c in brute(rows) if n} | {900, 901}
    assert kept == want


def test_representatives_of_null_and_repeated_ids(spark):
    def text(name):
        return " ".join(f"{name}{i}" for i in range(60))

    near = text("a") + " tail"
    rows = [(1, text("a"), "x"), (7, near, "x"), (7, text("b"), "x"), (None, text("c"), "x"), (None, text("d"), "x"), (None, text("d"), "y"), (None, text("e"), "x")]
    rows += [(None, near, "x"), (8, text("f"), "x"), (8, text("f"), "x"), (8, text("f"), None), (8, text("g"), "x"), (8, None, "x"), (8, "", "x"), (None, None, "x"), (None, None, "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string, m string").withColumn("tags", F.map_from_arrays(F.array(F.lit("t")), F.array("m")))
    kept = [(r.doc_id, r.text) for r in J.keep_representatives(df).collect()]
    want = [(1, text("a")), (7, text("b")), (8, text("f")), (8, text("g")), (8, None), (8, ""), (None, None), (None, None)]
    assert sorted(kept, key=str) == sorted(want + [(None, text(x)) for x in "cde"], key=str)
    assert J.keep_representatives(df.drop("tags")).count() == len(kept)


def test_every_link_is_counted(spark, monkeypatch):
    monkeypatch.setattr(J, "BLOCK_SETS", 50)
    rows = near_copies(6, 1, 230, 120) + near_copies(7, 12, 4, 80)
    texts = [t for _, t in rows] + [rows[0][1]] * 9 + [rows[-1][1]] * 2 + ["alone in here"] * 3 + [None, "", "a b c d e f g"]
    rows = [(i, t) for i, t in enumerate(texts)]
    sets = brute_sets(texts)
    want = [sum(1 for j, b in enumerate(sets) if j != i and a and b and 100 * len(a & b) >= 75 * len(a | b)) for i, a in enumerate(sets)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.doc_id, r.n_shingles, r.n_links, r.component_id) for r in J.jaccard_links(df).collect())
    assert [r[2] for r in got] == want and max(want) > 200
    assert sorted(((d, n, c) for d, n, _, c in got), key=str) == brute(rows)


def test_frequent_shingles_are_passed_on_early(spark, monkeypatch):
    r = random.Random(9)
    sets = {i: np.unique(np.array([r.randrange(2**64) for _ in range(3)] + [k << 56 | 5 for k in range(1, 1 + i % 7)], np.uint64)) for i in range(1, 200)}
    rows = [x for lo in range(1, 200, 10) for x in J._packed({i: sets[i] for i in range(lo, min(lo + 10, 200))}, 1)] + list(J._packed({3: sets[3]}, 1))
    schema = J.pa.schema([("bucket", "int32"), ("blob", "binary"), *[(n, J.pa.list_(J.pa.int64())) for n in ("docs", "marks", "refs", "sizes")]])

    def run():
        given = J.pa.schema([("part", "int32"), *list(schema)[1:]])
        batches = [J._batch([x], given) for x in rows]
        out = {}
        for b in J._shared_rows(iter(batches), schema, 1):
            for blob in b.column("blob").to_pylist():
                m = len(blob) // 24
                for k, ref, f in zip(np.frombuffer(blob, np.uint64, m), np.frombuffer(blob, np.int64, m, 8 * m), np.frombuffer(blob, np.uint32, m, 20 * m)):
                    out.setdefault(int(k), {}).setdefault(int(f), set()).add(int(ref))
        return out

    whole = run()
    monkeypatch.setattr(J, "LOOK_AFTER", 100)
    monkeypatch.setattr(J, "FREQUENT", 60)
    early = run()
    assert whole.keys() == early.keys() and len(whole) == 6
    for k, by in whole.items():
        ((f, refs),) = by.items()
        ((g, same),) = early[k].items()
        assert refs == same and f == len(refs) and g == (f if f < 60 else int(J.LAST))


def test_all_bits_of_a_shingle_count():
    a, b = np.array([1 << 40 | 7], np.uint64), np.array([1 << 40 | 7 | 0xABCD << 16], np.uint64)
    assert len({x[1][-8:] for s in (a, b) for x in J._packed({1: s}, 64)}) == 2


def test_small_ranges_and_frequent_shingles_keep_the_result(spark, monkeypatch):
    monkeypatch.setattr(J, "RANGE_BYTES", 2000)
    monkeypatch.setattr(J, "SLICE", 16)
    rows = near_copies(11, 1, 120, 60) + near_copies(12, 10, 3, 50)
    rows = [(i, t) for i, (_, t) in enumerate(rows)] + [(500 + i, rows[0][1]) for i in range(40)] + [(700 + i, None) for i in range(30)]
    assert result(spark, rows) == brute(rows)
