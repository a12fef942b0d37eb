"""Queries of the secure comparison and of the remaining definitions."""

from __future__ import annotations

from pyspark.sql import functions as F

from veil.functions import rules as R
from veil.operators.exact import compare
from veil.plans import experiments as X
from veil.plans import measure as M
from veil.plans import protocols as P
from veil.plans import secure as S
from veil.plans import workloads as W
from veil.plans.budget import Budget
from veil.plans.catalogue import _DIG, _W12, query, soundex, w1, w2
from veil.sources.shared import materialize, table


def _pairs(s, d):
    """Every distinct pair of vectors among the candidates."""
    p = W.product(s, d)
    a, b = p.a.select("quarter", "brand", F.col("v").alias("va")).distinct(), p.b.select("quarter", "brand", F.col("v").alias("vb")).distinct()
    return a.join(b, ["quarter", "brand"]).select("va", "vb").distinct().select(F.col("va").alias("a_id"), F.col("vb").alias("b_id"), "va", "vb")


_PAIRS = f"WITH {w2()}, p AS (SELECT DISTINCT a.v AS a_id, b.v AS b_id FROM a JOIN b ON a.bin = b.bin)"


@query("c1_ideal", f"WITH {w2()} SELECT count(*) AS candidates, (SELECT count(*) FROM truth) AS revealed FROM a JOIN b ON a.bin = b.bin")
def c1(s, d):
    p = W.product(s, d)
    x, y = p.a.alias("a"), p.b.alias("b")
    both = x.join(y, (F.col("a.quarter") == F.col("b.quarter")) & (F.col("a.brand") == F.col("b.brand"))).select(S.ideal(p.rule).alias("r"))
    return both.agg(F.count("*").alias("candidates"), F.count("r").alias("revealed"))


@query("c3_hamming_terms", _PAIRS + " SELECT a_id, b_id, CAST(bit_count(xor(a_id, b_id)) AS INT) AS d FROM p")
def c3(s, d):
    return _pairs(s, d).select("a_id", "b_id", S.hamming_terms(F.col("va"), F.col("vb")).cast("int").alias("d"))


@query("c4_blinded_match", _PAIRS + " SELECT a_id, b_id, bit_count(xor(a_id, b_id)) <= 5 AS matched FROM p")
def c4(s, d):
    return S.blinded_match(_pairs(s, d), 5).select("a_id", "b_id", "matched")


@query(
    "c3_squares",
    "SELECT x.s_suppkey AS a_id, y.s_suppkey AS b_id, power(x.s_suppkey % 97 - y.s_suppkey % 97, 2) + power(x.s_nationkey - y.s_nationkey, 2) <= 100 AS matched "
    "FROM supplier x JOIN supplier y USING (s_nationkey)",
)
def c3_squares(s, d):
    """Blinded squared distances of suppliers of one nation, as points of small integers."""
    p = table(s, d, "supplier").select(F.col("s_suppkey").alias("i"), "s_nationkey", (F.col("s_suppkey") % 97).alias("m"))
    point = F.array("m", F.col("s_nationkey").cast("long"))
    c = materialize(p.groupBy("s_nationkey", "m").agg(F.min("i").alias("i")).withColumn("x", point), "points")  # a point is compared once, whoever shares it
    n = int(s.conf.get("spark.sql.shuffle.partitions"))  # few bytes but much work: not to be coalesced
    pairs = c.alias("a").join(c.alias("b"), "s_nationkey").select(F.col("a.i").alias("a_id"), F.col("b.i").alias("b_id"), F.col("a.x").alias("xa"), F.col("b.x").alias("xb"))
    seen = materialize(S.blinded_distance(pairs.repartition(n, "a_id", "b_id"), 10), "blinded")
    member = p.join(c.select("s_nationkey", "m", F.col("i").alias("rep")), ["s_nationkey", "m"]).select("i", "rep")
    x, y = member.select(F.col("rep").alias("a_id"), F.col("i").alias("a")), member.select(F.col("rep").alias("b_id"), F.col("i").alias("b"))
    return seen.join(x, "a_id").join(y, "b_id").select(F.col("a").alias("a_id"), F.col("b").alias("b_id"), "matched")


@query("c2_additive", "SELECT o_orderpriority AS priority, CAST(sum(floor(o_totalprice)) AS BIGINT) AS total, CAST(-3 * count(*) AS BIGINT) AS scaled FROM orders WHERE o_orderpriority IS NOT NULL AND o_totalprice IS NOT NULL GROUP BY 1")
def c2(s, d):
    """Hidden sums of orders' whole prices and scaled hidden counts: every task's partial sums are encrypted, added unseen, then decrypted."""
    import random

    o = table(s, d, "orders").filter("o_orderpriority is not null and o_totalprice is not null")
    part = o.groupBy("o_orderpriority", (F.pmod(F.xxhash64("o_orderkey"), F.lit(16))).alias("holder")).agg(F.sum(F.floor("o_totalprice").cast("long")).alias("x"), F.count("*").alias("n"))
    k, hidden = S.key(), {}
    low = lambda v: v - k.n if v > k.n // 2 else v
    for r in part.collect():  # sixteen holders a priority
        rng = random.Random(f"5|{r.o_orderpriority}|{r.holder}")
        x, n = k.encrypt(r.x, rng), k.encrypt(r.n, rng)
        old = hidden.get(r.o_orderpriority)
        hidden[r.o_orderpriority] = (k.add(old[0], x), k.add(old[1], n)) if old else (x, n)
    rows = [(p, low(k.decrypt(x)), low(k.decrypt(k.scale(n, -3)))) for p, (x, n) in hidden.items()]
    return s.createDataFrame(rows, "priority string, total long, scaled long")


@query("c5_messages", f"WITH {w2()} SELECT 50 * (SELECT count(*) FROM a) + count(*) AS messages FROM a JOIN b ON a.bin = b.bin")
def c5(s, d):
    p = W.product(s, d)
    cost = int(P.plain(p.a, p.b, p.rule, p.blocking).cost.first()["cost"])
    return s.createDataFrame([(M.messages(p.a.count(), cost, 50),)], "messages long")


@query("c6_estimated_seconds", f"WITH {w1()} SELECT CAST(sum(x.n * y.n) AS DOUBLE) AS n, round(sum(x.n * y.n) * 0.077::DOUBLE, 6) AS seconds FROM st JOIN (SELECT bin, count(*) AS n FROM a GROUP BY bin) x ON x.bin = a_bin JOIN (SELECT bin, count(*) AS n FROM b GROUP BY bin) y ON y.bin = b_bin")
def c6(s, d):
    """Estimated wall clock of the comparisons that the grid leaves."""
    p = W.location(s, d)
    n = float(P.plain(p.a, p.b, p.rule, p.blocking).cost.first()["cost"])
    return s.createDataFrame([(n, round(M.estimated_seconds(n), 6))], "n double, seconds double")


@query("w8_unit_time")
def w8(s, d):
    """Measured seconds of a blinded comparison, and the wall clock they mean for all pairs and for padded blocking."""
    p = W.product(s, d)
    unit = S.blinded_match(_pairs(s, d), 5).agg(F.count("*").alias("pairs"), F.avg("seconds").alias("unit_seconds"))
    cost = P.padded(p.a, p.b, p.rule, p.blocking).cost.select(F.col("cost").cast("double").alias("padded"))
    n = p.a.agg(F.count("*").alias("na")).crossJoin(p.b.agg(F.count("*").alias("nb")))
    both = unit.crossJoin(cost).crossJoin(n)
    return both.select("pairs", "unit_seconds", (F.col("padded") * F.col("unit_seconds")).alias("padded_seconds"), (F.col("na") * F.col("nb") * F.col("unit_seconds")).alias("all_pairs_seconds"))


@query("m6_cost_ratio", f"WITH {w1()}, x AS (SELECT bin, count(*) AS n FROM a GROUP BY bin), y AS (SELECT bin, count(*) AS n FROM b GROUP BY bin) SELECT round(sum(x.n * y.n)::DOUBLE / ((SELECT count(*) FROM a) * (SELECT count(*) FROM b)), 9) AS cost_ratio FROM st JOIN x ON x.bin = a_bin JOIN y ON y.bin = b_bin")
def m6(s, d):
    p = W.location(s, d)
    return M.cost_ratio(P.plain(p.a, p.b, p.rule, p.blocking).cost, p.a, p.b)


@query("g8_plain_comparisons", f"WITH {w1()} SELECT count(DISTINCT a_id) * (SELECT count(*) FROM b) + count(DISTINCT b_id) * (SELECT count(*) FROM a) AS plain_comparisons FROM truth")
def g8(s, d):
    p = W.location(s, d)
    return M.plain_comparisons(compare(p.a, p.b, p.rule, p.blocking), p.a.count(), p.b.count())


@query("d12_conversion", "SELECT DISTINCT l_discount AS eps, 2 * l_discount AS linkage_eps, 0.0::DOUBLE AS secure_eps FROM lineitem WHERE l_discount > 0")
def d12(s, d):
    """The discounts of the given lines, taken as budgets of the symmetric guarantee, converted."""
    found = table(s, d, "lineitem").filter("l_discount > 0").select("l_discount").distinct().collect()
    return s.createDataFrame([(r[0], Budget.from_symmetric(r[0]).eps, Budget.cryptographic().eps) for r in found], "eps double, linkage_eps double, secure_eps double")


@query("m7_slope_all_pairs", "SELECT round(regr_slope(log10(n * n), log10(n)), 6) AS slope FROM (VALUES (351.0::DOUBLE), (676), (1310), (5000)) t(n)")
def m7_all(s, d):
    """All-pairs cost grows with the square of the party size, whatever the data."""
    n = s.createDataFrame([(float(v), float(v * v)) for v in (351, 676, 1310, 5000)], "n double, cost double").withColumn("m", F.lit("all_pairs"))
    return M.loglog_slope(n, ["m"]).select("slope")


_NEAR = {"edit": "levenshtein(x, y) <= 2", "digits": _DIG, "phonetic": f"{soundex('x')} = {soundex('y')}", "equal": "x = y"}


@query("r_all_rules", f"WITH {_W12} " + " UNION ALL ".join(f"SELECT '{k}' AS rule, count(*) AS n FROM c JOIN s USING (n) WHERE {v}" for k, v in _NEAR.items()))
def r_all(s, d):
    """Every rule over one pair of parties: accepted pairs per rule."""
    p = W.names(s, d)
    rules = {"edit": R.edit("suffix", 2), "digits": R.digits("suffix", 1), "phonetic": R.phonetic("suffix"), "equal": R.equal("suffix")}
    out = None
    for name, rule in rules.items():
        from veil.operators.exact import match_join

        row = match_join(p.a, p.b, R.all_of(R.equal("nation"), rule)).agg(F.count("*").alias("n")).select(F.lit(name).alias("rule"), "n")
        out = row if out is None else out.unionByName(row)
    return out
