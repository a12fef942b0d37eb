import random

import pytest

from veil.llm import license_scan as L

MIT = L.TEMPLATES["mit"]


def scan(spark, texts, **kw):
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, license string")
    return sorted(map(tuple, L.scan(df, **kw).collect()), key=lambda r: (r[0], r[5]))


def test_notices_bodies_and_edges(spark):
    texts = [
        "Released under the MIT License.", "pre Licensed under CC BY-NC 4.0. post", None, "", "nothing to see", "é " * 10 + "released UNDER the mit LICENSE!", MIT, "x " * 300_000 + MIT + " y" * 1000,
        "Licensed under the Apache License, Version 2.0. Released under the MIT License.", "Released under the MIT License. " * 3, "licensed under the",
    ]
    got = scan(spark, texts)
    names = {}
    for r in got:
        names.setdefault(r[0], []).append(r[1])
    assert names == {0: ["mit-notice"], 1: ["cc-by-nc-4.0-notice"], 5: ["mit-notice"], 6: ["mit"], 7: ["mit"], 8: ["apache-2.0-notice", "mit-notice"], 9: ["mit-notice"] * 3}
    for doc, _, n, total, cover, start, end in got:
        assert n == total and cover == 1.0 and texts[doc][start:end].lower().startswith(("licensed", "released", "permission"))


def test_edited_bodies_are_found_with_their_coverage(spark):
    r = random.Random(3)
    words = MIT.split()
    texts = []
    for k in range(12):
        w = list(words)
        for _ in range(k):
            i = r.randrange(len(w))
            w[i : i + 1] = r.choice([[], ["changed"], [w[i], "added"]])
        texts.append("intro text " + " ".join(w) + " outro")
    got = {x[0]: x for x in scan(spark, texts, least=0.6)}
    assert set(got) == set(range(12))
    assert all(got[k][4] >= 1 - (k + 0.01) / len(words) * 2 for k in range(12))


def test_alignment_equals_longest_common_subsequence_inside_the_band():
    r = random.Random(4)
    import numpy as np

    for _ in range(60):
        t = [r.randrange(6) for _ in range(20)]
        d = list(t)
        for _ in range(r.randrange(5)):
            d[r.randrange(len(d))] = r.randrange(6)
        lcs = [[0] * (len(d) + 1) for _ in range(len(t) + 1)]
        for i, a in enumerate(t):
            for j, b in enumerate(d):
                ok = a == b and abs(j - i) <= L.BAND
                lcs[i + 1][j + 1] = max(lcs[i][j + 1], lcs[i + 1][j], lcs[i][j] + ok)
        got = L.align(np.array(d, np.uint64), np.array(t, np.uint64), 0)[0]
        assert got == lcs[-1][-1]


def test_winnowing_keeps_a_fingerprint_in_every_window():
    import numpy as np

    g = np.random.default_rng(1).integers(0, 50, 300).astype(np.uint64)
    at = set(L.winnow(g).tolist())
    assert all(at & set(range(i, i + L.WINDOW)) for i in range(len(g) - L.WINDOW + 1))


def test_short_templates_are_refused_and_empty_tables_pass(spark):
    with pytest.raises(ValueError):
        L.Index({"a": "two words"})
    assert scan(spark, []) == [] and scan(spark, ["Released under the MIT License."], templates={}) == []


def test_scan_equals_exhaustive_alignment_on_the_given_documents(spark):
    """Every template at every place of every document that has a license word, without index and regions."""
    import re

    def words(t):
        return re.findall(r"[^\W_]+", t.lower())

    docs = [(r.doc_id, r.text or "") for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    short = {n: words(t) for n, t in L.TEMPLATES.items() if len(words(t)) < 30}
    want = set()
    for d, t in docs:
        w = words(t)
        for n, k in short.items():
            for i in range(len(w) - len(k) + 1):
                if w[i : i + len(k)] == k:
                    want.add((d, n))
    whole = {(r[0], r[1]) for r in L.scan(spark.createDataFrame(docs, "doc_id long, text string")).collect() if r[4] == 1.0}
    assert want and want == {x for x in whole if x[1] in short}


def test_one_changed_word_of_a_short_notice_is_found(spark):
    words = "Released under the MIT License".split()
    texts = [" ".join(words[:i] + ["other"] + words[i + 1 :]) for i in range(len(words))]
    got = {r[0] for r in scan(spark, texts, templates={"mit-notice": L.TEMPLATES["mit-notice"]})}
    assert got >= {0, 1, 3, 4}  # the middle word leaves no run of three words


def test_parts_of_a_license_are_not_the_license(spark):
    texts = [MIT, MIT[: len(MIT) // 3], L.TEMPLATES["bsd-3-clause"], L.TEMPLATES["bsd-2-clause"], None]
    rows = [(None, MIT), (1, MIT), (1, MIT)]
    got = scan(spark, texts)
    assert {(r[0], r[1]) for r in got} == {(0, "mit"), (2, "bsd-3-clause"), (3, "bsd-2-clause")}
    many = L.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(str(r[0]) for r in many) == ["1", "1", "None"] and {r[1] for r in many} == {"mit"}
