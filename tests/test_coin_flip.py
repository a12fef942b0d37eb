import itertools
import random
from hashlib import md5
from math import exp

from pyspark.sql import functions as F

from veil.plans import audit as A
from veil.plans import coin_flip as R
from veil.plans import experiments as X
from veil.plans import workloads as W

SF = "/root/testdata/sf0.001"


def test_laws():
    p = R.basic_profile(16, 1.6)
    assert abs(R.colocation(p, p, 1) - (p[0] ** 2 + 15 * p[1] ** 2)) < 1e-15
    assert abs(R.colocation(p, p, 1) - 0.099297) < 1e-6
    one = R.colocation(R.certain_profile(10), R.window_profile(10, 3, 1.6), 3)
    assert abs(one - R.recall_at(0.3, 1.6)) < 1e-12 and abs(one - 0.679767) < 1e-6
    assert abs(R.colocation(p, p, 16) - 1) < 1e-12
    assert abs(R.rho_at(R.recall_at(0.37, 0.4), 0.4) - 0.37) < 1e-12


def test_one_sided_optimum_beats_random_profiles():
    r, e = random.Random(1), exp(1.6)
    best = R.colocation(R.certain_profile(10), R.window_profile(10, 3, 1.6), 3)
    for _ in range(300):
        w = [1 + r.random() * (e - 1) for _ in range(10)]
        assert R.colocation(R.certain_profile(10), [x / sum(w) for x in w], 3) <= best + 1e-12


def test_symmetric_choice_is_the_exact_maximum():
    for k, w, eps in itertools.product((6, 10, 16), (1, 3, 6), (0.4, 1.6, 3.0)):
        x, v = R.symmetric_best(k, w, eps)
        scores = {y: R.colocation(R.window_profile(k, y, eps), R.window_profile(k, y, eps), w) for y in range(1, w + 1)}
        assert v == max(scores.values()) and scores[x] == v
    assert R.symmetric_best(10, 3, 3.0)[0] == 1 and R.symmetric_best(10, 6, 1.6)[0] == 1


def test_closed_form_and_slope_agree_where_windows_do_not_wrap():
    for k, w, eps in ((16, 4, 1.6), (20, 6, 0.4), (30, 5, 3.0)):
        for x in range(1, w + 1):
            p = R.window_profile(k, x, eps)
            assert abs(R.symmetric_objective(k, w, eps, x) - R.colocation(p, p, w)) < 1e-12
        h = 1e-6
        diff = (R.symmetric_objective(k, w, eps, 2 + h) - R.symmetric_objective(k, w, eps, 2 - h)) / (2 * h)
        assert abs(diff - R.symmetric_slope(k, w, eps, 2)) < 1e-6


def test_search_is_feasible_and_no_worse():
    pa, pb, v = R.profile_search(8, 3, 1.6, 1.6)
    assert A.local_eps_of(pa) <= 1.6 + 1e-9 and A.local_eps_of(pb) <= 1.6 + 1e-9
    assert abs(sum(pa) - 1) < 1e-9 and v >= R.symmetric_best(8, 3, 1.6)[1] - 1e-12


def test_empirical_recall_is_near_the_law(spark):
    p = W.product(spark, SF)
    home = F.col("quarter") * 16 + F.col("brand") - 1
    q = R.basic_profile(16, 3.0)
    rows = X.flip_law(p, home, 16, (1,), 3.0, lambda w: (q, q), 6).collect()
    mean = sum(r.recall for r in rows) / len(rows)
    assert abs(mean - rows[0].law) < 0.15


def test_a_record_is_hashed_once_and_moves_by_its_draw(spark):
    q = R.window_profile(16, 3, 1.6)
    df = R.assign(spark.range(2000).selectExpr("id AS rid", "id % 16 AS home"), F.col("home"), q, "a", 1)
    assert df._jdf.queryExecution().optimizedPlan().toString().count("md5(") == 1
    bounds = list(itertools.accumulate(q[:-1]))
    draw = lambda rid: int(md5(f"1|a|{rid}|flip".encode()).hexdigest()[:13], 16) / (1 << 52)
    for r in df.collect():
        assert r.flip_bin == (r.home + sum(draw(r.rid) >= b for b in bounds)) % 16
    assert df.columns == ["rid", "home", "flip_bin"]
