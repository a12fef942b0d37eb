"""The match-join itself and the comparison of candidates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veil.functions.rules import Rule
from veil.operators.blocking import Blocking


def _sides(a: DataFrame, b: DataFrame, rule: Rule, *extra: str) -> tuple[DataFrame, DataFrame]:
    """Only ids, rule attributes and join columns take part in the shuffle."""
    cols = ["rid", *dict.fromkeys([*rule.attributes, *extra])]
    return a.select(*cols).alias("a"), b.select(*cols).alias("b")


#: Pairs up to which a rule without any index is compared in full.
MOST_PAIRS = 100_000_000


def match_join(a: DataFrame, b: DataFrame, rule: Rule, index: Blocking | None = None) -> DataFrame:
    """All pairs ``a_id, b_id`` that the rule accepts.

    ``index`` names a blocking that loses no match; without one, the rule's own
    index gives join keys. A rule with neither compares every pair, and raises
    beyond ``MOST_PAIRS`` pairs.
    """
    if index is not None:
        return compare(a, b, rule, index)
    x, y = _sides(a, b, rule)
    keys = rule.lossless_index()
    if keys is None:
        if a.count() * b.count() > MOST_PAIRS:
            raise ValueError("the rule has no index and the parties are too large to compare every pair; give a blocking")
        return x.join(y, rule.condition()).select(F.col("a.rid").alias("a_id"), F.col("b.rid").alias("b_id"))
    i = x.select(F.col("rid").alias("a_id"), F.explode(keys[0]).alias("meet"))
    j = y.select(F.col("rid").alias("b_id"), F.explode(keys[1]).alias("meet"))
    met = i.join(j, "meet").select("a_id", "b_id").distinct()  # a pair that shares many keys is checked once
    near = met.join(x, F.col("a_id") == F.col("a.rid")).join(y, F.col("b_id") == F.col("b.rid")).filter(rule.condition())
    return near.select("a_id", "b_id").distinct()


def compare(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking, live: DataFrame | None = None) -> DataFrame:
    """Matches among the candidates of a blocking: ``a_id, b_id`` and, with ``live``, ``a_bin, b_bin, rank``.

    Alice's records are copied to the partner bins, then joined on the bin.
    ``live`` restricts the bin pairs and carries their rank; it is joined before
    the records meet, so pruned bin pairs never reach the comparison.
    """
    cols = list(dict.fromkeys(["rid", *rule.attributes]))
    left = blocking.assign(a.select(*a.columns)).select(*cols, F.col("bin").alias("a_bin"))
    right = blocking.assign(b.select(*b.columns)).select(*cols, F.col("bin").alias("b_bin"))
    left = left.withColumn("b_bin", F.explode(blocking.partners(F.col("a_bin"))))
    if live is not None:
        left = left.join(live.select("a_bin", "b_bin", "rank"), ["a_bin", "b_bin"])
    x, y = left.alias("a"), right.alias("b")
    joined = x.join(y, (F.col("a.b_bin") == F.col("b.b_bin")) & rule.condition())
    out = [F.col("a.rid").alias("a_id"), F.col("b.rid").alias("b_id")]
    if live is not None:
        return joined.select(*out, F.col("a.a_bin").alias("a_bin"), F.col("a.b_bin").alias("b_bin"), F.col("a.rank").alias("rank"))
    pairs = joined.select(*out)
    return pairs.distinct() if blocking.max_bins > 1 else pairs


def salted_compare(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking, slices: int) -> DataFrame:
    """``compare`` with every bin of A cut in slices by record hash and B's bin copied to each slice.

    For bins that hold a large share of a party: the m x m work of one bin is
    spread over ``slices`` tasks, at the price of ``slices`` copies of B.
    """
    cols = list(dict.fromkeys(["rid", *rule.attributes]))
    left = blocking.assign(a).select(*cols, F.col("bin").alias("a_bin"), F.pmod(F.xxhash64("rid"), F.lit(slices)).alias("slice"))
    left = left.withColumn("b_bin", F.explode(blocking.partners(F.col("a_bin"))))
    right = blocking.assign(b).select(*cols, F.col("bin").alias("b_bin"))
    right = right.withColumn("slice", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(slices - 1).cast("long"))))
    x, y = left.alias("a"), right.alias("b")
    on = (F.col("a.b_bin") == F.col("b.b_bin")) & (F.col("a.slice") == F.col("b.slice")) & rule.condition()
    pairs = x.join(y, on).select(F.col("a.rid").alias("a_id"), F.col("b.rid").alias("b_id"))
    return pairs.distinct() if blocking.max_bins > 1 else pairs
