import random

from pyspark.sql import functions as F

from veil.operators import skew


def test_hot_keys_are_joined_in_place(spark):
    r = random.Random(1)
    rows = [(i, r.choice([7, 7, 7, i, None])) for i in range(4000)]
    left = spark.createDataFrame(rows, "i long, k long")
    right = spark.createDataFrame([(k, f"v{k}") for k in range(0, 4000, 2)] + [(7, "v7")], "k long, v string")
    hot = skew.hot_keys(left.groupBy("k").agg(F.count("*").alias("n")), ["k"], len(rows))
    assert {x.k for x in hot.collect()} == {7, None} and skew.hot_keys(left.groupBy('i').agg(F.count('*').alias('n')), ['i'], len(rows)) is None
    for how in ("inner", "left"):
        want = sorted(map(str, left.join(right, "k", how).collect()))
        assert sorted(map(str, skew.join_hot(left, right, ["k"], hot, how).select("k", "i", "v").collect())) == want


def test_running_sums_equal_one_sort(spark):
    r = random.Random(2)
    rows = [(r.randrange(50), i, r.randrange(9)) for i in range(3000)]
    df = spark.createDataFrame(rows, "k int, i int, x long")
    got = skew.running(df, [F.col("k").desc(), F.col("i")], {"s": F.col("x")}).collect()
    total = 0
    for n, (row, g) in enumerate(zip(sorted(rows, key=lambda t: (-t[0], t[1])), sorted(got, key=lambda g: g["rank"]))):
        assert (g.k, g.i, g.x, g["rank"], g.s) == (*row, n + 1, total)
        total += row[2]
    assert skew.running(df.filter("false"), [F.col("k")]).count() == 0
