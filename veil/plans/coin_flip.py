"""Coin-flip (randomised response) blocking: profiles, laws and the protocol.

A profile gives the probability of moving from the home bin to the bin ``i``
further around the circle. Every profile here keeps the ratio of any two
entries within ``e^eps``.
"""

from __future__ import annotations

import random
from math import exp

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veil.functions.hashing import uniform
from veil.functions.rules import Rule
from veil.operators import padding, prune
from veil.operators.blocking import Blocking, cyclic_window
from veil.operators.classes import classes
from veil.operators.exact import compare, match_join
from veil.plans import protocols as P


def basic_profile(k: int, eps: float) -> list[float]:
    """High probability at home, equal low ones elsewhere."""
    return window_profile(k, 1, eps)


def window_profile(k: int, x: int, eps: float) -> list[float]:
    """High probability on the home bin and the next x-1, low on the rest."""
    e = exp(eps)
    total = k - x + x * e
    return [e / total if i < x else 1 / total for i in range(k)]


def certain_profile(k: int) -> list[float]:
    """No randomisation: the public side."""
    return [1.0] + [0.0] * (k - 1)


def colocation(pa: list[float], pb: list[float], window: int) -> float:
    """Probability that two records of one home bin are compared, by the circular double sum."""
    k = len(pa)
    return sum(pa[i] * pb[(i + j) % k] for i in range(k) for j in range(window))


def symmetric_best(k: int, window: int, eps: float) -> tuple[int, float]:
    """The x in 1..window whose profile, used by both sides, has the highest exact probability."""
    scored = [(colocation(p, p, window), -x) for x in range(1, window + 1) for p in [window_profile(k, x, eps)]]
    best = max(scored)
    return -best[1], best[0]


def symmetric_objective(k: int, window: int, eps: float, x: int) -> float:
    """Closed form of the symmetric probability; valid while windows do not wrap (x + window - 2 < k)."""
    e = exp(eps)
    t = k - x + x * e
    hi, lo = e / t, 1 / t
    both, one = x * (x + 1) / 2, 2 * window * x - x * (x + 1)
    return both * hi * hi + one * hi * lo + (k * window - both - one) * lo * lo


def symmetric_slope(k: int, window: int, eps: float, x: int) -> float:
    """Derivative of the closed form in x, by finite-difference-checked algebra."""
    e = exp(eps)
    return (e - 1) ** 2 * ((2 * k - 4 * window - e + 1) * x + k) / (2 * (k - x + x * e) ** 3)


def recall_at(rho: float, eps: float) -> float:
    """Recall of the one-sided optimum at compression rho = window / k."""
    return rho * exp(eps) / (1 - rho + rho * exp(eps))


def rho_at(recall: float, eps: float) -> float:
    """Compression needed for a recall: the inverse of ``recall_at``."""
    return recall / (recall + exp(eps) * (1 - recall))


def profile_search(k: int, window: int, eps_a: float, eps_b: float, rounds: int = 40, seed: int = 1) -> tuple[list[float], list[float], float]:
    """General profiles by alternating exact linear steps.

    With one side fixed the best answer of the other puts the high probability
    on a set of bins with the largest weights; the best size of the set is found
    by trying all. Alternation from several starts climbs to a local optimum.
    """
    rng = random.Random(seed)

    def answer(weights: list[float], eps: float) -> list[float]:
        order = sorted(range(k), key=lambda i: -weights[i])
        e, best = exp(eps), (-1.0, 1)
        high = 0.0
        total = sum(weights)
        for x in range(1, k + 1):
            high += weights[order[x - 1]]
            best = max(best, ((high * e + total - high) / (k - x + x * e), x))
        x = best[1]
        out = [0.0] * k
        for r, i in enumerate(order):
            out[i] = (e if r < x else 1.0) / (k - x + x * e)
        return out

    top: tuple[float, list[float], list[float]] = (-1.0, [], [])
    starts = [window_profile(k, x, eps_a) for x in range(1, k + 1)] + [answer([rng.random() for _ in range(k)], eps_a) for _ in range(4)]
    for pa in starts:
        last = -1.0
        for _ in range(rounds):
            pb = answer([sum(pa[(i - j) % k] for j in range(window)) for i in range(k)], eps_b)
            pa = answer([sum(pb[(i + j) % k] for j in range(window)) for i in range(k)], eps_a)
            now = colocation(pa, pb, window)
            if now <= last + 1e-15:
                break
            last = now
        top = max(top, (last, pa, pb))
    return top[1], top[2], top[0]


def move(home: Column, profile: list[float], u: Column) -> Column:
    """The bin a record is sent to: its home bin shifted by a step that the uniform ``u`` draws from the profile."""
    total, step = 0.0, F.lit(len(profile) - 1)
    bounds = []
    for p in profile[:-1]:
        total += p
        bounds.append(total)
    for i in range(len(bounds) - 1, -1, -1):
        step = F.when(u < bounds[i], i).otherwise(step)
    return F.pmod(home + step, F.lit(len(profile))).cast("long")


def assign(party: DataFrame, home: Column, profile: list[float], tag: str, seed: int) -> DataFrame:
    """Add ``flip_bin``; the draw depends on seed, party and record only.

    The draw is a column of its own, so that it is hashed once per record and not once per step.
    """
    drawn = party.withColumn("__draw", uniform(str(seed), tag, F.col("rid"), "flip"))
    return drawn.withColumn("flip_bin", move(home, profile, F.col("__draw"))).drop("__draw")


def coin_flip(
    a: DataFrame,
    b: DataFrame,
    rule: Rule,
    home: Column,
    k: int,
    window: int,
    profile_a: list[float],
    profile_b: list[float],
    seed: int = 1,
    prune_at: int = 0,
    chase: bool = False,
    index: Blocking | None = None,
) -> P.LinkResult:
    """Coin-flip blocking with a comparison window; window = k compares every pair.

    ``prune_at`` orders bin pairs by their size and stops at a percentile (bin
    counts of locally randomised records carry no further noise). ``chase``
    grows the output over the match graph, found through ``index`` or the full join.
    """
    fa, fb = assign(a, home, profile_a, "a", seed), assign(b, home, profile_b, "b", seed)
    blocking = cyclic_window(k, window, F.col("flip_bin"))
    by_class = bool(rule.keys) and not chase
    if by_class:  # records of equal attributes differ in their flips only: one row each, with its records by flip bin
        flips = {f"flip{i}": F.count_if(F.col("flip_bin") == i) for i in range(k)}
        ca, cb = (classes(x, [*rule.attributes], flips) for x in (fa, fb))
        spread = lambda c: c.select(F.posexplode(F.array(*[F.col(f) for f in flips])).alias("bin", "n")).groupBy(F.col("bin").cast("long").alias("bin")).agg(F.sum("n").alias("n_real"))
        counts = spread(ca), spread(cb)
    else:
        counts = padding.bin_counts(blocking.assign(fa)), padding.bin_counts(blocking.assign(fb))
    na, nb = (blocking.domain(a.sparkSession).join(n, "bin", "left").select("bin", F.coalesce("n_real", F.lit(0)).alias("n_noisy")) for n in counts)
    pairs = prune.pair_table(blocking, na, nb)
    if prune_at:
        pairs = prune.stop(prune.levels(pairs, prune.thresholds(na, nb)), prune_at)
    scope = None
    if by_class:
        meet = (pairs if prune_at else blocking.strategy(a.sparkSession)).select("a_bin", "b_bin").collect()  # at most k times window
        found = F.lit(0).cast("long")
        for i in range(k):
            others = [F.col(f"b.flip{j}") for x, j in meet if x == i]
            if others:
                found = found + F.col(f"a.flip{i}") * sum(others[1:], others[0])
        scope = P.Scope(ca, cb, found=found)
    view = P._view(pairs)
    live = prune.rank(pairs, "size")
    met = compare(fa, fb, rule, blocking, live)
    if chase:
        out = P.C.chase(match_join(a, b, rule, index), met, ["rank"])
        ids_a, ids_b = (blocking.assign(x).select("rid", "bin") for x in (fa, fb))
        ret = [r.join(i, "rid").select("bin", F.col("first.rank").alias("rank")) for r, i in ((out["ret_a"], ids_a), (out["ret_b"], ids_b))]
        return P.LinkResult(out["output"], view, P.C.cost_by_bin_pair(live, *ret), {"method": "coin_flip", "private": True})
    return P.LinkResult(met.select("a_id", "b_id"), view, P._total(view), {"method": "coin_flip", "private": True}, scope=scope)


def projected_home(vec: Column, dim_in: int, dim_out: int, seed: int) -> Column:
    """Home bin from signs of a random projection; our own extension, without a proof of its own.

    Only the coin flip that follows carries the privacy guarantee.
    """
    rng = random.Random(seed)
    planes = [[rng.gauss(0, 1) for _ in range(dim_in)] for _ in range(dim_out)]
    from veil.functions.encode import sign_bits

    return sign_bits(vec, planes)
