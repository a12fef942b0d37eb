import re
from collections import Counter

from pyspark.sql import functions as F

from veil.llm import quality_ledger as Q


def brute(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines = [x for x in (text or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    c = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
    pos = {i + k for i in range(len(w) - 2) if c[tuple(w[i : i + 3])] > 1 for k in range(3)}
    return len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines), len(lines) - len(set(lines)), len(pos)


TEXTS = [None, "", " \n\t\x0b", "a", "a b", "a b c a b c", "x " * 40, "a\nb\na\n\n \nb", "é ü\u00a0ß 日本 😀 <#>", " lead and trail ", "a b c d " * 5000, "# $ % & * | < >", "w" * 200_000, "a b a b a b c", "\r\na\r\n"]


def test_measures_and_edges(spark):
    rows = [(i, t, 7, "z") for i, t in enumerate(TEXTS)] + [(3, "a", 7, "z")]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_words int, failed_bits string")
    got = {r.doc_id: tuple(r[m] for m in Q.MEASURES) for r in Q.ledger(df).collect()}
    assert got == {i: brute(t) for i, t in enumerate(TEXTS)}
    assert Q.ledger(df).count() == len(rows)


def test_keep_is_the_policy_and_returns_the_columns(spark):
    rows = [(i, t) for i, t in enumerate(TEXTS)] + [(90, " ".join(f"w{i}" for i in range(80)))]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_words", F.lit("mine"))
    kept = Q.keep(df)
    assert kept.columns == df.columns and {r.doc_id for r in kept.collect()} == {90}
    assert kept.first()["n_words"] == "mine"
    assert Q.keep(df.filter("false")).count() == 0


def test_policies_share_one_ledger_and_ablation_counts(spark):
    rows = [(1, "w " * 60), (2, " ".join(f"a{i}" for i in range(60))), (3, " ".join(f"a{i} # $" for i in range(60))), (4, "few")]
    led = Q.ledger(spark.createDataFrame(rows, "doc_id long, text string")).cache()
    table = {r["rule"]: (r["n_failed"], r["n_only"], r["n_kept_without"]) for r in Q.ablation(led, "v1").collect()}
    for rule, (failed, only, kept) in table.items():
        bit = Q.mask_of(rule)
        mask = Q.mask_of(*Q.POLICIES["v1"])
        bits = [r.failed_bits & mask for r in led.collect()]
        assert failed == sum(b & bit != 0 for b in bits) and only == sum(b == bit for b in bits)
        assert kept == sum(b & ~bit == 0 for b in bits)


def test_plan_has_no_shuffle_and_no_python(spark):
    df = spark.createDataFrame([(1, "a")], "doc_id long, text string")
    plan = Q.ledger(df)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan
