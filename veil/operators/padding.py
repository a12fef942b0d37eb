"""Noise and padding of bin counts.

A draw is ``centre + G1 - G2`` with two geometric variables from hash uniforms,
a pure function of seed, party and bin: a replayed task releases the same pad.
"""

from __future__ import annotations

import warnings

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from veil.functions.hashing import uniform
from veil.operators.blocking import Blocking


def draw(mu: int, eps: float, sensitivity: int, *parts: Column | str) -> Column:
    """Two-sided geometric noise around ``mu`` as long."""
    a = eps / sensitivity

    def geometric(tag: str) -> Column:
        return F.floor(F.log1p(-uniform(*parts, tag)) / F.lit(-a)).cast("long")

    return F.lit(mu).cast("long") + geometric("1") - geometric("2")


def size(party: DataFrame) -> Column:
    """Aggregate: the records of a party, of which a row stands for ``weight`` where it has that column."""
    return F.coalesce(F.sum("weight"), F.lit(0).cast("long")) if "weight" in party.columns else F.count("*")


def bin_counts(binned: DataFrame) -> DataFrame:
    """Records per occupied bin; partial sums before the shuffle."""
    return binned.groupBy("bin").agg(size(binned).alias("n_real"))


def pad_counts(counts: DataFrame, blocking: Blocking, mu: int, eps: float, party: str, seed: int) -> DataFrame:
    """``bin, n_real, n_dummy, n_noisy`` for every declared bin."""
    spark = counts.sparkSession
    eta = draw(mu, eps, blocking.sensitivity(), F.lit(str(seed)), F.lit(party), F.col("bin"))
    full = blocking.domain(spark).join(counts, "bin", "left")
    out = full.select("bin", F.coalesce("n_real", F.lit(0)).cast("long").alias("n_real"), F.greatest(eta, F.lit(0)).cast("long").alias("n_dummy"))
    return out.withColumn("n_noisy", F.col("n_real") + F.col("n_dummy"))


def pad_rows(binned: DataFrame, padded: DataFrame) -> DataFrame:
    """Real rows ``rid, bin`` plus materialised dummies with ids outside the true domain and ``is_dummy``."""
    real = binned.select(F.col("rid").cast("string").alias("entry"), "bin", F.lit(False).alias("is_dummy"))
    made = padded.filter("n_dummy > 0").select("bin", F.explode(F.sequence(F.lit(1).cast("long"), "n_dummy")).alias("d"))
    dummies = made.select(F.concat(F.lit("dummy:"), "bin", F.lit(":"), "d").alias("entry"), "bin", F.lit(True).alias("is_dummy"))
    return real.unionByName(dummies)


def positions(binned: DataFrame, padded: DataFrame, party: str, seed: int) -> DataFrame:
    """``entry, bin, is_dummy, pos``: a seeded order of all entries of each bin, from 1."""
    order = W.partitionBy("bin").orderBy(F.md5(F.concat_ws("|", F.lit(f"{seed}|{party}|pos"), "entry")), "entry")
    return pad_rows(binned, padded).withColumn("pos", F.row_number().over(order).cast("long"))


def placed(binned: DataFrame, padded: DataFrame, party: str, seed: int) -> DataFrame:
    """``binned`` with ``pos``, the place that ``positions`` gives a record among all entries of its bin; one shuffle, no join."""
    made = padded.filter("n_dummy > 0").select("bin", F.explode(F.sequence(F.lit(1).cast("long"), "n_dummy")).alias("d"))
    dummies = made.select("bin", F.concat(F.lit("dummy:"), "bin", F.lit(":"), "d").alias("dummy"))
    every = binned.unionByName(dummies, allowMissingColumns=True)
    entry = F.coalesce("dummy", F.col("rid").cast("string"))
    order = W.partitionBy("bin").orderBy(F.md5(F.concat_ws("|", F.lit(f"{seed}|{party}|pos"), entry)), entry)
    return every.withColumn("pos", F.row_number().over(order).cast("long")).filter("dummy is null").drop("dummy")


def mark_kept(binned: DataFrame, blocking: Blocking, eps: float, party: str, seed: int) -> DataFrame:
    """Adds ``kept``: whether signed noise around zero leaves the record in its bin."""
    order = W.partitionBy("bin").orderBy(F.md5(F.concat_ws("|", F.lit(f"{seed}|{party}|drop"), F.col("rid").cast("string"))), "rid")
    size = F.count("*").over(W.partitionBy("bin"))
    eta = draw(0, eps, blocking.sensitivity(), F.lit(str(seed)), F.lit(party), F.col("bin"))
    ranked = binned.withColumns({"__r": F.row_number().over(order), "__n": size, "__e": eta})
    return ranked.withColumn("kept", F.col("__r") <= F.col("__n") + F.least(F.col("__e"), F.lit(0))).drop("__r", "__n", "__e")


def suppress(binned: DataFrame, blocking: Blocking, eps: float, party: str, seed: int) -> DataFrame:
    """Signed noise around zero that drops records where it is negative: kept rows of ``binned``.

    A negative control: dropping real records breaks the privacy guarantee.
    """
    warnings.warn("suppressing records does not protect non-matching records", stacklevel=2)
    return mark_kept(binned, blocking, eps, party, seed).filter("kept").drop("kept")


def suppressed_counts(kept: DataFrame, blocking: Blocking, eps: float, party: str, seed: int) -> DataFrame:
    """Noisy counts of the suppressing variant: kept records plus positive noise."""
    return pad_counts(bin_counts(kept), blocking, 0, eps, party, seed)
