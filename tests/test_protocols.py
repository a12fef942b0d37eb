import random

import pytest
from pyspark.sql import functions as F

from veil.functions import rules as R
from veil.operators import blocking as B
from veil.operators import chase as C
from veil.operators import padding, prune
from veil.operators.exact import compare, match_join, salted_compare
from veil.plans import measure as M
from veil.plans import protocols as P
from veil.plans import workloads as W
from veil.plans.budget import Budget, center, expected_pad

SF = "/root/testdata/sf0.01"
TINY = Budget(50.0, 1e-5)


def party(spark, rows):
    return spark.createDataFrame(rows, "rid long, bin0 long, x double")


def toy(size=4):
    return B.equal_keys("toy", size, F.col("bin0"))


RULE = R.all_of(R.equal("bin0"), R.euclidean(["x"], 1.0))


def pairs(df):
    return sorted((r.a_id, r.b_id) for r in df.select("a_id", "b_id").collect())


def simulate(a, b, match, order, grain, against="all"):
    """The loop itself on lists: entries of each bin in position order, comparisons one after another."""
    out, gone_a, gone_b, cost = set(), set(), set(), 0
    ids_a = {e for bin_ in a.values() for e in bin_ if not str(e).startswith("d")}
    ids_b = {e for bin_ in b.values() for e in bin_ if not str(e).startswith("d")}

    def clean():
        while True:
            xs, ys = {p for p, _ in out}, {q for _, q in out}
            gone_a.update(xs), gone_b.update(ys)
            pool_a = ids_a if against == "all" else ids_a - gone_a
            pool_b = ids_b if against == "all" else ids_b - gone_b
            new = {(p, q) for p in pool_a for q in ys if match(p, q)} | {(p, q) for p in xs for q in pool_b if match(p, q)}
            if new <= out:
                return
            out.update(new)

    for i, j in order:
        batch = []
        for p in list(a[i]):
            for q in list(b[j]):
                if p in gone_a or q in gone_b:
                    continue
                cost += 1
                if match(p, q):
                    if grain == "pair":
                        out.add((p, q))
                        clean()
                    else:
                        batch.append((p, q))
        out.update(batch)
        clean()
    return out, cost


@pytest.mark.parametrize("seed", range(4))
@pytest.mark.parametrize("grain", ["pair", "bin_pair"])
def test_chase_equals_the_sequential_loop(spark, seed, grain):
    r = random.Random(seed)
    k = 4
    grid = B.cyclic_window(k, 2, F.col("bin0"))
    rule = R.euclidean(["x"], 0.6)
    ra = [(i, r.randrange(k), float(r.randrange(9))) for i in range(16)]
    rb = [(100 + i, r.randrange(k), float(r.randrange(9)) + 0.5) for i in range(16)]
    a, b = party(spark, ra), party(spark, rb)
    got = P.padded(a, b, rule, grid, Budget(2.0, 1e-2), seed=seed, order="size", chase=True, grain=grain, lossless=False)
    mu = center(2.0, 1e-2, 2)
    na, nb = P.noisy_bins(a, b, grid, (2.0, 2.0), (mu, mu), seed)
    order = [(x.a_bin, x.b_bin) for x in prune.rank(prune.pair_table(grid, na, nb), "size").orderBy("rank").collect()]

    def bins(df, counts, side):
        out = {i: [] for i in range(k)}
        for e in padding.positions(grid.assign(df), counts, side, seed).orderBy("bin", "pos").collect():
            out[e.bin].append("d" + side + e.entry if e.is_dummy else int(e.entry))
        return out

    xa, xb = {i: v for i, _, v in ra}, {i: v for i, _, v in rb}
    match = lambda p, q: p in xa and q in xb and abs(xa[p] - xb[q]) <= 0.6
    out, cost = simulate(bins(a, na, "a"), bins(b, nb, "b"), match, order, grain)
    assert pairs(got.matches) == sorted(out)
    assert int(got.cost.first()["cost"]) == cost


def test_batches_of_several_bin_pairs_need_all_records():
    a, b = {0: [0], 1: [1]}, {0: [0], 1: [1]}
    match = lambda p, q: (p, q) in {(0, 0), (1, 1), (0, 1)}

    def batch(against):
        out = {(0, 0), (1, 1)}
        xs, ys = {0, 1}, {0, 1}
        pool = xs if against == "all" else set()
        return out | {(p, q) for p in pool for q in ys if match(p, q)}

    assert len(batch("all")) == 3 and len(batch("remaining")) == 2
    assert len(simulate(a, b, match, [(0, 0), (1, 1)], "pair")[0]) == 3


def test_chase_reaches_beyond_the_blocking(spark):
    a, b = party(spark, [(1, 0, 0.0), (2, 1, 0.4)]), party(spark, [(9, 0, 0.2)])
    rule = R.euclidean(["x"], 0.5)
    basic, chased = (P.padded(a, b, rule, toy(), TINY, chase=c, lossless=False) for c in (False, True))
    assert pairs(basic.matches) == [(1, 9)] and pairs(chased.matches) == [(1, 9), (2, 9)]


def test_edge_parties(spark):
    none = party(spark, [])
    some = party(spark, [(1, 0, 0.0), (2, 0, 5.0), (3, None, 0.0), (4, 1, None)])
    for x, y in ((none, none), (none, some), (some, none), (some, some)):
        for chase in (False, True):
            r = P.padded(x, y, RULE, toy(), chase=chase)
            assert pairs(r.matches) == ([(1, 1), (2, 2)] if x is some and y is some else [])
            assert int(r.cost.first()["cost"]) > 0
    assert M.recall(none.select(F.col("rid").alias("a_id"), F.col("rid").alias("b_id")), none.select(F.col("rid").alias("a_id"), F.col("rid").alias("b_id"))).first()["recall"] is None
    with pytest.raises(ValueError):
        P.padded(some.drop("x"), some, RULE, toy())


def test_borders_distance_and_cells(spark):
    rows = [(1, 0.0, 0.0), (2, 40.0, 25.0), (3, 159.99, 99.99), (4, 8.0, 0.0), (5, 8.0000001, 0.0)]
    pts = spark.createDataFrame(rows, "rid long, x double, y double").withColumn("slot", F.lit(0).cast("long"))
    rule = R.all_of(R.equal("slot"), R.euclidean(["x", "y"], 0.2, [40.0, 25.0]))
    from veil.functions.encode import grid

    blk = B.grid_neighbors(1, 4, 4, F.col("slot"), grid(F.col("x"), 40.0, 4), grid(F.col("y"), 25.0, 4))
    assert pairs(compare(pts, pts, rule, blk)) == pairs(match_join(pts, pts, rule))
    assert (1, 4) in pairs(compare(pts, pts, rule, blk)) and (1, 5) not in pairs(compare(pts, pts, rule, blk))


@pytest.fixture(scope="module")
def location(spark):
    p = W.location(spark, SF, 1)
    return W.Problem(p.name, p.a.cache(), p.b.cache(), p.rule, p.blocking, p.attributes, p.gamma)


def test_known_answers(spark, location):
    p = location
    truth = match_join(p.a, p.b, p.rule, p.blocking)
    assert (p.a.count(), truth.count()) == (364, 610)
    assert int(P.plain(p.a, p.b, p.rule, p.blocking).cost.first()["cost"]) == 15_464
    assert M.same_output(truth, match_join(p.a, p.b, p.rule))
    q = W.product(spark, SF)
    assert (q.a.count(), q.b.count(), match_join(q.a, q.b, q.rule).count()) == (30_167, 29_833, 109_212)
    assert P.intersect(q.a, q.b, list(q.attributes)).matches.count() == 3585
    assert int(P.plain(q.a, q.b, q.rule, q.blocking).cost.first()["cost"]) == 1_322_933


def test_dummies_change_the_cost_only(spark, location):
    p = location
    mu = center(1.6, 1e-5, 2)
    na, nb = P.noisy_bins(p.a, p.b, p.blocking, (1.6, 1.6), (mu, mu), 1)
    rows_a, rows_b = padding.pad_rows(p.blocking.assign(p.a), na), padding.pad_rows(p.blocking.assign(p.b), nb)
    counts = [{r.bin: r.n for r in x.groupBy("bin").agg(F.count("*").alias("n")).collect()} for x in (rows_a, rows_b)]
    r = P.padded(p.a, p.b, p.rule, p.blocking)
    by_rows = sum(counts[0].get(s.a_bin, 0) * counts[1].get(s.b_bin, 0) for s in p.blocking.strategy(spark).collect())
    assert int(r.cost.first()["cost"]) == by_rows
    assert M.same_output(r.matches, P.plain(p.a, p.b, p.rule, p.blocking).matches)


def test_expected_cost_is_the_mean_over_seeds_and_below_the_bound(spark, location):
    from veil.plans.experiments import cost_grid

    p = location
    e = expected_pad(center(1.6, 1e-5, 2), 1.6, 2)
    na, nb = P.noisy_bins(p.a, p.b, p.blocking, (1.6, 1.6), (14, 14), 1)
    row = M.expected_cost(na, nb, p.blocking.strategy(spark), e, e).first()
    costs = [r.cost for r in cost_grid(p, 64, (1,), (1.6,), (1e-5,), 50).collect()]
    mean = sum(costs) / 50
    sd = (sum((c - mean) ** 2 for c in costs) / 49) ** 0.5
    assert abs(mean - row.expected_cost) < 5 * sd / 50**0.5
    assert row.expected_cost < M.cost_bound(row.plain_cost, e, 9, 64, 364)


def test_pruning_is_monotone_and_stop_zero_is_everything(spark, location):
    from veil.plans.experiments import tradeoff

    rows = tradeoff(location, [Budget(1.6, 1e-5)]).orderBy(F.col("percent").desc()).collect()
    assert all(x.recall <= y.recall and x.cost <= y.cost for x, y in zip(rows, rows[1:]))
    r = P.padded(location.a, location.b, location.rule, location.blocking)
    assert rows[-1].percent == 0 and rows[-1].recall == 1.0 and rows[-1].cost == int(r.cost.first()["cost"])


def test_chase_costs_no_more_and_finds_no_less(location):
    p = location
    basic = P.padded(p.a, p.b, p.rule, p.blocking)
    full = P.padded(p.a, p.b, p.rule, p.blocking, chase=True, order="size")
    assert int(full.cost.first()["cost"]) <= int(basic.cost.first()["cost"])
    assert M.same_output(basic.matches, full.matches)


def test_bin_pair_grain_saves_nothing_when_bins_meet_once(spark):
    q = W.product(spark, SF, 1)
    basic = P.padded(q.a, q.b, q.rule, q.blocking)
    block = P.padded(q.a, q.b, q.rule, q.blocking, chase=True, grain="bin_pair")
    pair = P.padded(q.a, q.b, q.rule, q.blocking, chase=True)
    costs = [int(r.cost.first()["cost"]) for r in (basic, block, pair)]
    assert costs[0] == costs[1] > costs[2]


def test_suppression_loses_matches_and_warns(location):
    with pytest.warns(UserWarning):
        r = P.suppressed(location.a, location.b, location.rule, location.blocking)
    assert r.matches.count() < 610 and not r.meta["private"]


def test_results_do_not_depend_on_partitioning(spark, location):
    p = location
    one = P.padded(p.a, p.b, p.rule, p.blocking, chase=True)
    other = P.padded(p.a.repartition(7), p.b.repartition(31), p.rule, p.blocking, chase=True)
    assert M.same_output(one.matches, other.matches) and one.cost.first() == other.cost.first()


def test_salted_comparison_is_the_same(location):
    p = location
    assert M.same_output(salted_compare(p.a, p.b, p.rule, p.blocking, 5), compare(p.a, p.b, p.rule, p.blocking))


def test_plans(spark, location):
    p = W.location(spark, SF, 1)
    plan = compare(p.a, p.b, p.rule, p.blocking)._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan and "Python" not in plan
    assert "LessThan(ts," in plan and "user_id" not in plan
    assert C.sides(location.a.select(F.col("rid").alias("a_id"), F.col("rid").alias("b_id")))[0].count() == 364


@pytest.mark.parametrize(
    "rule",
    [R.edit("s", 2), R.edit("s", 0), R.digits("s", 1), R.phonetic("s"), R.hamming("v", 5), R.hamming("v", 0), R.qgram("g", 0.4), R.qgram("g", 1.0), R.euclidean(["x", "y"], 0.7, [2.0, 1.0]), R.euclidean(["x"], 0.0), R.all_of(R.equal("k"), R.edit("s", 1))],
)
def test_rule_indexes_lose_no_match(spark, rule):
    rng = random.Random(3)
    words = ["".join(rng.choice("ab12") for _ in range(rng.randrange(9))) for _ in range(60)]
    rows = [(i, w, rng.getrandbits(50) if i % 2 else rng.choice([7, 8, 15]), [w[j : j + 2] for j in range(len(w) - 1)], rng.choice([-0.4, 0.0, 1.4, 3.0]) + rng.random() // 0.5, rng.uniform(-2, 2), i % 3) for i, w in enumerate(words)]
    rows.append((99, None, None, None, None, None, None))
    p = spark.createDataFrame(rows, "rid long, s string, v long, g array<string>, x double, y double, k int").withColumn("g", F.array_distinct("g"))
    every = p.alias("a").join(p.alias("b"), rule.condition()).select(F.col("a.rid"), F.col("b.rid"))
    assert sorted(map(tuple, match_join(p, p, rule).collect())) == sorted(map(tuple, every.collect()))


def test_a_rule_without_index_is_refused_on_large_parties(spark, monkeypatch):
    from veil.operators import exact

    p = spark.createDataFrame([(1, [0.5]), (2, [0.6])], "rid long, v array<double>")
    assert match_join(p, p, R.vector_distance("v", 0.2)).count() == 4
    monkeypatch.setattr(exact, "MOST_PAIRS", 3)
    with pytest.raises(ValueError):
        match_join(p, p, R.vector_distance("v", 0.2))
