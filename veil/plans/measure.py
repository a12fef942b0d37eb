"""Cost, accuracy and size measures: aggregates over results, views and trial logs."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veil.functions.rules import Rule
from veil.operators import classes, near
from veil.operators.blocking import Blocking


def cost(view: DataFrame) -> DataFrame:
    """Secure comparisons of a view, as exact decimal."""
    return view.agg(F.coalesce(F.sum(F.col("n_candidates").cast("decimal(38,0)")), F.lit(0)).alias("cost"))


def recall(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row ``n_truth, n_found, recall``; null where nothing matches."""
    hit = truth.join(found.select("a_id", "b_id").distinct().withColumn("hit", F.lit(1)), ["a_id", "b_id"], "left")
    out = hit.agg(F.count("*").alias("n_truth"), F.count("hit").alias("n_found"))
    return out.withColumn("recall", F.when(F.col("n_truth") > 0, F.round(F.col("n_found") / F.col("n_truth"), 9)))


def tally(scope, rule: Rule, blocking: Blocking) -> DataFrame | None:
    """One row ``n_truth, n_found, recall`` of a protocol's scope, counted where records meet; None for rules that neither points nor classes serve.

    Ids are unique in a party. No pair is written or shuffled.
    """
    if near.euclidean_part(rule) is not None and scope.found is None:
        met = near.pair_counts(scope.a, scope.b, rule, blocking)
    elif "weight" in scope.a.columns and rule.keys:
        met = classes.pair_counts(scope.a, scope.b, rule, blocking if scope.live is not None else None, scope.found)
    else:
        return None
    n = F.col("n_found")
    if scope.live is not None:
        met = met.join(scope.live.withColumn("live", F.lit(True)), ["a_bin", "b_bin"], "left")
        n = F.when(F.col("live"), n).otherwise(0)
    return share(met.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_truth"), F.coalesce(F.sum(n), F.lit(0)).alias("n_found")))


def share(counts: DataFrame) -> DataFrame:
    """``n_truth, n_found`` with ``recall``; null where nothing matches."""
    return counts.withColumn("recall", F.when(F.col("n_truth") > 0, F.round(F.col("n_found") / F.col("n_truth"), 9)))


def same_scope(x, y, rule: Rule, blocking: Blocking) -> DataFrame:
    """One row ``same, sound``: whether two runs over one pair of parties output the same pairs, and only pairs that the rule accepts.

    A run outputs the accepted pairs of its bin pairs, so the accepted pairs of
    every bin pair are counted once, whether or not a run compares it: the runs
    are the same if no bin pair with such pairs is in one run only, and sound if
    a run's bin pairs hold no more pairs than those the rule accepts.
    """
    met = near.pair_counts(x.a, x.b, rule, blocking)
    for name, s in (("x", x), ("y", y)):
        met = met.join(s.live.withColumn(name, F.lit(True)), ["a_bin", "b_bin"], "left")
    met = met.fillna(False, ["x", "y"])
    apart = F.count_if((F.col("n") > 0) & (F.col("x") != F.col("y")))
    extra = F.count_if(F.col("x") & (F.col("n_found") > F.col("n")))
    return met.agg((apart == 0).alias("same"), (extra == 0).alias("sound"))


def precision(found: DataFrame, truth: DataFrame) -> DataFrame:
    """One row ``n_output, n_false, precision``; 1 for every sound protocol, null without output."""
    bad = found.join(truth, ["a_id", "b_id"], "left_anti").agg(F.count("*").alias("n_false"))
    out = found.agg(F.count("*").alias("n_output")).crossJoin(bad)
    return out.withColumn("precision", F.when(F.col("n_output") > 0, F.round(1 - F.col("n_false") / F.col("n_output"), 9)))


def same_output(x: DataFrame, y: DataFrame) -> bool:
    """Whether two outputs hold the same pairs, with multiplicity."""
    return x.exceptAll(y).isEmpty() and y.exceptAll(x).isEmpty()


def cost_ratio(result_cost: DataFrame, a: DataFrame, b: DataFrame) -> DataFrame:
    """Cost over all pairs."""
    n = a.agg(F.count("*").alias("na")).crossJoin(b.agg(F.count("*").alias("nb")))
    every = F.col("na").cast("decimal(19,0)") * F.col("nb").cast("decimal(19,0)")
    return result_cost.crossJoin(n).select(F.when(every > 0, F.round(F.col("cost").cast("double") / every.cast("double"), 9)).alias("cost_ratio"))


def loglog_slope(log: DataFrame, by: list[str]) -> DataFrame:
    """Slope of log cost over log n per group of a trial log."""
    return log.groupBy(*by).agg(F.round(F.regr_slope(F.log10(F.col("cost").cast("double")), F.log10("n")), 6).alias("slope"))


def summary(log: DataFrame, by: list[str]) -> DataFrame:
    """Mean and spread of cost over seeds."""
    c = F.col("cost").cast("double")
    return log.groupBy(*by).agg(F.count("*").alias("runs"), F.round(F.avg(c), 6).alias("mean_cost"), F.round(F.stddev_samp(c), 6).alias("sd_cost"))


def saving(log: DataFrame, by: list[str], base: str) -> DataFrame:
    """Per group and variant: cost saved against ``base``, absolute and relative."""
    means = log.groupBy(*by, "variant").agg(F.avg(F.col("cost").cast("double")).alias("c"))
    ref = means.filter(F.col("variant") == base).select(*by, F.col("c").alias("b"))
    return means.join(ref, by).select(
        *by, "variant", F.round(F.col("b") - F.col("c"), 6).alias("saved"), F.round((F.col("b") - F.col("c")) / F.col("b"), 9).alias("share")
    )


def expected_cost(counts_a: DataFrame, counts_b: DataFrame, strategy: DataFrame, pad_a: float, pad_b: float) -> DataFrame:
    """Expected padded cost from true counts (declared bins, zeros included) and expected pads."""
    x = counts_a.select(F.col("bin").alias("a_bin"), F.col("n_real").alias("x"))
    y = counts_b.select(F.col("bin").alias("b_bin"), F.col("n_real").alias("y"))
    one = (F.col("x") + F.lit(pad_a)) * (F.col("y") + F.lit(pad_b))
    return strategy.join(x, "a_bin").join(y, "b_bin").agg(F.round(F.sum(one), 6).alias("expected_cost"), F.sum(F.col("x") * F.col("y")).alias("plain_cost"))


def cost_bound(plain: float, pad: float, partners: int, bins: int, n: int) -> float:
    """Upper bound of the expected padded cost."""
    return plain + pad * pad * partners * bins + 2 * pad * partners * n


def bin_profile(padded: DataFrame) -> DataFrame:
    """Dummy share, occupied share, median and largest bin, skew."""
    return padded.agg(
        F.round(F.sum("n_dummy") / F.sum("n_noisy"), 9).alias("dummy_share"),
        F.round(F.count_if(F.col("n_real") > 0) / F.count("*"), 9).alias("occupied"),
        F.round(F.percentile("n_real", F.lit(0.5)), 6).alias("median_bin"),
        F.max("n_real").alias("largest_bin"),
        F.round(F.max("n_real") / F.avg("n_real"), 6).alias("skew"),
    )


def messages(n_a: int, n_pairs: int, d: int) -> int:
    """Ciphertexts exchanged: d per Alice record, one back per pair."""
    return d * n_a + n_pairs


def estimated_seconds(n_comparisons: float, unit: float = 0.077) -> float:
    """Wall clock of the secure part at ``unit`` seconds per comparison."""
    return n_comparisons * unit


def plain_comparisons(reached: DataFrame, n_a: int, n_b: int) -> DataFrame:
    """Clear-text comparisons of the chase: each retired record against all of the other side."""
    a = reached.select("a_id").distinct().agg(F.count("*").alias("ra"))
    b = reached.select("b_id").distinct().agg(F.count("*").alias("rb"))
    return a.crossJoin(b).select((F.col("ra") * n_b + F.col("rb") * n_a).alias("plain_comparisons"))


def timing(run: Callable[[], object]) -> tuple[object, float]:
    """Result and seconds of a call."""
    t = time.perf_counter()
    out = run()
    return out, time.perf_counter() - t
