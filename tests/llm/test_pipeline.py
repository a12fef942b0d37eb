import hashlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline as P
from tests.llm.test_jaccard_join import brute
from tests.llm.test_quality_ledger import brute as measure
from tests.oracle import SF
from veil.llm import chunk_bpe, pii_feistel

tokenizers = pytest.importorskip("tokenizers")


def kept(text):
    n, chars, symbols, lines, dup, repeat = measure(text)
    return not (n < 50 or 100 * repeat > 50 * n or 100 * symbols > 50 * n or 100 * dup > 50 * lines)


def test_every_stage_against_a_plain_version(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    cols = docs.columns
    one = P.quality(spark, docs, SF)
    rows = {r.doc_id: r for r in docs.collect()}
    assert one.columns == cols and {r.doc_id for r in one.collect()} == {i for i, r in rows.items() if kept(r.text)}
    two = P.near_duplicates(spark, one, SF)
    want = {c for _, n, c in brute([(r.doc_id, r.text) for r in one.collect()]) if n}
    assert two.columns == cols and sorted(r.doc_id for r in two.collect()) == sorted(want)
    three = P.personal_data(spark, two, SF)
    left = {r.doc_id: r.text for r in three.collect()}
    assert three.columns == cols and left.keys() == want
    counted = spark.createDataFrame([(i, rows[i].text) for i in want], "i long, t string").select("i", pii_feistel.count_finds(F.col("t")).alias("n")).collect()
    clean = [r.i for r in counted if r.n == 0]
    assert len(clean) > len(want) / 2 and all(left[i] == rows[i].text for i in clean)
    assert not any("@mail" in t and ".example.com" in t for t in left.values())
    four = P.mixing(spark, three, SF)
    copies = Counter(r.doc_id for r in four.collect())
    assert four.columns == cols and set(copies) <= want and max(copies.values()) <= 3
    last = P.encoding(spark, four, SF)
    t = tokenizers.Tokenizer.from_file(chunk_bpe.default_paths()[1])
    got = Counter((r.doc_id, r.ids_sha256) for r in last.collect())
    ids = lambda x: hashlib.sha256(np.array(t.encode(x, add_special_tokens=False).ids, "<u4").tobytes()).hexdigest()
    assert got == Counter({(i, ids(left[i])): n for i, n in copies.items()})


def test_run_and_empty(spark, tmp_path):
    assert P.run(spark, SF).count() > 100
    spark.read.parquet(f"{SF}/documents.parquet").filter("false").write.parquet(f"{tmp_path}/documents.parquet")
    assert P.run(spark, f"file://{tmp_path}").count() == 0


def test_nulls_repeats_and_clashing_columns(spark):
    rows = [(1, None, "a"), (2, "", None), (None, "word " * 3 + " ".join(f"w{i}" for i in range(90)), None), (3, " ".join(f"v{i}" for i in range(90)), "a"), (3, " ".join(f"v{i}" for i in range(90)), "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string").withColumns({c: F.lit("x") for c in ("size", "n_words", "component_id", "plan", "copies", "failed_bits", "label")})
    out = docs
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, out, SF)
        assert out.columns == docs.columns, name
    assert {r["size"] for r in out.collect()} == {"x"}
    assert P.encoding(spark, out, SF).count() == out.count()
