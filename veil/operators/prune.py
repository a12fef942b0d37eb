"""Size-ordered pruning over the table of bin pairs."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from veil.operators.skew import running

PERCENTS = (90, 80, 70, 60, 50, 40, 30, 20, 10, 0)


def pair_table(blocking, noisy_a: DataFrame, noisy_b: DataFrame) -> DataFrame:
    """``a_bin, b_bin, na, nb``: the strategy with both noisy sizes."""
    pairs = blocking.strategy(noisy_a.sparkSession)
    na = noisy_a.select(F.col("bin").alias("a_bin"), F.col("n_noisy").alias("na"))
    nb = noisy_b.select(F.col("bin").alias("b_bin"), F.col("n_noisy").alias("nb"))
    return pairs.join(na, "a_bin").join(nb, "b_bin").select("a_bin", "b_bin", "na", "nb")


def thresholds(noisy_a: DataFrame, noisy_b: DataFrame, percents: tuple[int, ...] = PERCENTS) -> DataFrame:
    """One row: percentiles of the pooled noisy bin sizes of both parties, descending."""
    pooled = noisy_a.select("n_noisy").unionByName(noisy_b.select("n_noisy"))
    return pooled.agg(F.percentile("n_noisy", F.array(*[F.lit(p / 100) for p in percents])).alias("thresholds"))


def levels(pairs: DataFrame, limits: DataFrame, percents: tuple[int, ...] = PERCENTS) -> DataFrame:
    """Add ``percent``: the first (largest) percentile that both sizes exceed; 0 takes all that is left.

    Groups are nested, so a pair is compared at its own level only.
    """
    least = F.least("na", "nb")
    level: Column = F.lit(0)
    for i in range(len(percents) - 1, -1, -1):
        if percents[i] > 0:
            level = F.when(least > F.element_at("thresholds", i + 1), percents[i]).otherwise(level)
    return pairs.crossJoin(F.broadcast(limits)).withColumn("percent", level.cast("int")).drop("thresholds")


def stop(leveled: DataFrame, percent: int) -> DataFrame:
    """The bin pairs compared when stopping at a percentile; 0 compares all."""
    return leveled.filter(F.col("percent") >= percent)


def rank(pairs: DataFrame, order: str, seed: int = 1) -> DataFrame:
    """Add ``rank`` from 1 in the order ``index``, ``random``, ``size`` or ``decile``; ties by bins.

    One row per bin pair, numbered by ranges of the order: no task sorts the table.
    """
    keys: dict[str, list[Column]] = {
        "index": [],
        "random": [F.md5(F.concat_ws("|", F.lit(f"{seed}|order"), "a_bin", "b_bin"))],
        "size": [F.least("na", "nb").desc(), F.greatest("na", "nb").desc()],
        "decile": [F.col("percent").desc()] if "percent" in pairs.columns else [],
    }
    if order not in keys or order == "decile" and "percent" not in pairs.columns:
        raise ValueError(f"unknown order {order}")
    return running(pairs, [*keys[order], F.col("a_bin"), F.col("b_bin")], label="ranked")


def curve(leveled: DataFrame, found: DataFrame, truth: int | Column, all_pairs: int | Column) -> DataFrame:
    """Cumulative recall and cost per level: ``percent, cost, matches, recall, cost_ratio``.

    ``found`` holds matches with their bin pair.
    """
    hits = found.join(leveled.select("a_bin", "b_bin", "percent"), ["a_bin", "b_bin"]).groupBy("percent").agg(F.count("*").alias("m"))
    cost = leveled.groupBy("percent").agg(F.sum((F.col("na") * F.col("nb")).cast("decimal(38,0)")).alias("c"))
    along = W.orderBy(F.col("percent").desc()).rowsBetween(W.unboundedPreceding, 0)
    run = cost.join(hits, "percent", "left").select(
        "percent", F.sum("c").over(along).alias("cost"), F.sum(F.coalesce("m", F.lit(0))).over(along).alias("matches")
    )
    t = truth if isinstance(truth, Column) else F.lit(truth)
    n = all_pairs if isinstance(all_pairs, Column) else F.lit(all_pairs)
    return run.select(
        "percent",
        F.col("cost").cast("long").alias("cost"),
        F.col("matches").cast("long").alias("matches"),
        F.round(F.col("matches") / t, 9).alias("recall"),
        F.round(F.col("cost").cast("double") / n, 9).alias("cost_ratio"),
    )
