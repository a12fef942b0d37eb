import math

import pytest
from pyspark.sql import functions as F

from veil.operators import padding
from veil.plans import budget as N


def test_centres_of_the_grid():
    want = {1e-5: (14, 58, 230), 1e-7: (20, 81, 322), 1e-9: (26, 104, 414)}
    assert {d: tuple(N.center(e, d, 2) for e in (1.6, 0.4, 0.1)) for d in want} == want


@pytest.mark.parametrize("eps,delta", [(1.6, 1e-5), (0.4, 1e-7), (0.1, 1e-5)])
def test_law_sums_to_one_and_keeps_delta(eps, delta):
    mu = N.center(eps, delta, 2)
    xs = range(-20_000, 20_001)
    assert abs(sum(N.pmf(x, mu, eps, 2) for x in xs) - 1) < 1e-12
    assert abs(sum(N.pmf(x, mu, eps, 2) for x in xs if x < 0) - N.p_negative(mu, eps, 2)) < 1e-12
    assert abs(sum(N.pmf(x, mu, eps, 2) * max(x, 0) for x in xs) - N.expected_pad(mu, eps, 2)) < 1e-9
    assert N.failure(mu, eps, 2) <= delta


def test_budgets_compose_and_are_refused_above_the_cap():
    b = N.Budget(1.0, 1e-6).then(N.Budget(0.5, 1e-6))
    assert (b.eps, b.delta) == (1.5, 2e-6) and b.post().eps == 1.5
    ledger = N.Ledger(N.Budget(1.6, 1e-5))
    ledger.spend(N.Budget(1.0, 1e-6))
    with pytest.raises(ValueError):
        ledger.spend(N.Budget(1.0, 1e-6))
    with pytest.warns(UserWarning):
        N.Budget(1.6, 1e-5).check(300_000)
    with pytest.raises(ValueError):
        N.Budget(-1.0)


def test_draws_follow_the_law_and_do_not_depend_on_partitions(spark):
    mu = N.center(1.6, 1e-5, 2)
    eta = padding.draw(mu, 1.6, 2, "1", "a", F.col("id"))
    d = spark.range(20_000).select("id", eta.alias("e"))
    one = {r.id: r.e for r in d.collect()}
    assert one == {r.id: r.e for r in spark.range(20_000).repartition(37).select("id", eta.alias("e")).collect()}
    chi = 0.0
    for x in range(mu - 5, mu + 6):
        want = 20_000 * N.pmf(x, mu, 1.6, 2)
        chi += (sum(v == x for v in one.values()) - want) ** 2 / want
    assert chi < 35
    assert abs(sum(one.values()) / 20_000 - mu) < 0.1


def test_ratio_of_unit_swaps_is_bounded():
    eps, mu = 1.6, 14
    for c1, c2, n1, n2 in ((3, 0, 20, 20), (0, 5, 14, 9), (1, 1, 2, 40)):
        r = sum(math.log(N.pmf(n - c, mu, eps, 2)) for n, c in ((n1, c1), (n2, c2))) - sum(math.log(N.pmf(n - c, mu, eps, 2)) for n, c in ((n1, c1 - 1), (n2, c2 + 1)))
        assert abs(r) <= eps + 1e-12
