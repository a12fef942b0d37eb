"""Classes of equal records: one row stands for all records of a party that no rule or bin can tell apart.

A class has the columns that rule and blocking read, ``rid`` (its smallest id)
and ``weight`` (its records). Counts over pairs of records are sums over pairs
of classes, so copies are never expanded into pairs.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veil.functions.rules import Rule
from veil.operators.blocking import Blocking
from veil.sources.shared import materialize


def classes(party: DataFrame, columns: list[str], more: dict[str, Column] | None = None) -> DataFrame:
    """The classes of a party by ``columns``, with further aggregates; written once, as all counts read it."""
    by = list(dict.fromkeys(columns))
    return materialize(party.groupBy(*by).agg(F.min("rid").alias("rid"), F.count("*").alias("weight"), *[c.alias(n) for n, c in (more or {}).items()]), "classes")


def pair_counts(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking | None, found: Column | None = None) -> DataFrame:
    """``a_bin, b_bin, n, n_found`` per bin pair: pairs of records that the rule accepts, and those among them that ``found`` counts.

    ``found`` is a number of pairs of records over aliases ``a`` and ``b``; left out, all are found.
    The rule has an equality part. The blocking gives every record one bin and need not hold every match; without one all pairs are in bin 0.
    """
    at = lambda c, name: (blocking.assign(c) if blocking else c.withColumn("bin", F.lit(0))).withColumnRenamed("bin", name)
    x, y = at(a, "a_bin").alias("a"), at(b, "b_bin").alias("b")
    n = F.col("a.weight") * F.col("b.weight")
    met = x.join(y, rule.condition())
    return met.groupBy("a_bin", "b_bin").agg(F.sum(n).alias("n"), F.sum(n if found is None else found).alias("n_found"))
