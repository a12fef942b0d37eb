"""Privacy definitions on small universes, and closed-form checks."""

from __future__ import annotations

from math import exp, log

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from veil.functions.rules import Rule
from veil.operators.exact import match_join
from veil.operators.blocking import Blocking


def universe(spark: SparkSession, values: list[int]) -> DataFrame:
    """All subsets of a few values: ``db_id`` (bit mask) and ``members`` (sorted array)."""
    if len(values) > 16:
        raise ValueError("a universe of all subsets is for toy domains")
    v = F.array(*[F.lit(x).cast("long") for x in sorted(values)])
    keep = F.filter(v, lambda x, i: F.call_function("shiftright", F.col("id"), i).bitwiseAND(F.lit(1)) == 1)
    return spark.range(1 << len(values)).select(F.col("id").alias("db_id"), keep.alias("members"))


def with_output(dbs: DataFrame, alice: list[int]) -> DataFrame:
    """Add ``output``: what the equality match with Alice's values reveals."""
    return dbs.withColumn("output", F.array_intersect("members", F.array(*[F.lit(x).cast("long") for x in sorted(alice)])))


def _pairs(dbs: DataFrame) -> DataFrame:
    x, y = dbs.alias("x"), dbs.alias("y")
    cols = [F.col(f"{s}.{c}").alias(f"{s}_{c}") for s in "xy" for c in ("db_id", "members", "output")]
    p = x.join(y, F.col("x.db_id") < F.col("y.db_id")).select(*cols)
    diff = F.array_union(F.array_except("x_members", "y_members"), F.array_except("y_members", "x_members"))
    return p.withColumn("diff", F.array_sort(diff))


def dp_graph(dbs: DataFrame) -> DataFrame:
    """Edges between databases that differ in one record."""
    return _pairs(dbs).filter(F.size("diff") == 1).select("x_db_id", "y_db_id")


def path_distance(dbs: DataFrame) -> DataFrame:
    """Distance in the graph of single changes: the size of the symmetric difference, for all pairs."""
    return _pairs(dbs).select("x_db_id", "y_db_id", F.size("diff").alias("distance"))


def equal_output_graph(dbs: DataFrame) -> DataFrame:
    """Edges between databases of equal output."""
    return _pairs(dbs).filter(F.col("x_output") == F.col("y_output")).select("x_db_id", "y_db_id")


def output_classes(dbs: DataFrame) -> DataFrame:
    """Databases per output."""
    return dbs.groupBy("output").agg(F.count("*").alias("n"))


def constrained_neighbors(dbs: DataFrame, fixed_size: bool = True) -> DataFrame:
    """Edges of equal output whose symmetric difference holds no smaller one of equal output.

    With ``fixed_size`` the number of records is part of the output, as in a
    protocol that reveals it; then a minimal edge swaps one non-matching record.
    """
    p = _pairs(dbs).filter(F.col("x_output") == F.col("y_output"))
    if fixed_size:
        p = p.filter(F.size("x_members") == F.size("y_members"))
    e = p.select("x_db_id", "y_db_id", "diff")
    both = e.unionByName(e.select(F.col("y_db_id").alias("x_db_id"), F.col("x_db_id").alias("y_db_id"), "diff"))
    other = both.select(F.col("x_db_id").alias("o"), F.col("diff").alias("d"))
    smaller = (F.col("x_db_id") == F.col("o")) & (F.size("d") < F.size("diff")) & (F.size(F.array_except("d", "diff")) == 0)
    return e.join(other, smaller, "left_anti").select("x_db_id", "y_db_id")


def is_linkage_neighbor(a: DataFrame, b: DataFrame, b2: DataFrame, rule: Rule, index: Blocking | None = None) -> bool:
    """Whether two versions of Bob differ by the swap of one non-matching record."""
    gone, new = b.join(b2, "rid", "left_anti"), b2.join(b, "rid", "left_anti")
    if (gone.count(), new.count()) != (1, 1):
        return False
    return match_join(a, gone, rule, index).isEmpty() and match_join(a, new, rule, index).isEmpty()


def local_ratio(prob: DataFrame) -> DataFrame:
    """Largest log ratio of a bin's probability between two inputs: ``prob`` has ``input, bin, p``."""
    per = prob.groupBy("bin").agg(F.log(F.max("p") / F.min("p")).alias("r"))
    return per.agg(F.round(F.max("r"), 9).alias("local_eps"))


def log_ratio(bins: DataFrame, bins2: DataFrame, noisy: DataFrame, eps: float, sensitivity: int, mu: int) -> DataFrame:
    """Log likelihood ratio of noisy counts under two databases: sum over bins of the difference of distances."""
    a = eps / sensitivity
    j = noisy.join(bins.select("bin", F.col("n_real").alias("n1")), "bin").join(bins2.select("bin", F.col("n_real").alias("n2")), "bin")
    one = F.abs(F.col("n_noisy") - F.col("n2") - mu) - F.abs(F.col("n_noisy") - F.col("n1") - mu)
    return j.agg(F.round(F.lit(a) * F.sum(one), 9).alias("log_ratio"))


def suppression_witness(eps: float, sensitivity: int, m: int) -> tuple[float, float]:
    """How far the suppressing variant breaks the guarantee, and the bound below which it is claimed to.

    A non-matching record is swapped from a bin of its own into a bin of ``m``
    matching ones. Observed are the counts 1 and m with all matches surviving.
    Without the swap both draws are 0; with it one draw is 1 and the other -1,
    and the dropped record must be the new one, one of m+1. Returns the delta
    needed for that event and the bound ``p^sensitivity / (2 e^eps)``.
    """
    a = eps / sensitivity
    p = (exp(a) - 1) / (exp(a) + 1)
    needed = p * p - exp(eps) * p * p * exp(-2 * a) / (m + 1)
    return max(0.0, needed), p**sensitivity / (2 * exp(eps))


def local_eps_of(profile: list[float]) -> float:
    """Privacy of a coin-flip profile."""
    return log(max(profile) / min(profile)) if min(profile) > 0 else float("inf")
