"""Blocking over a declared bin domain and bin-pair strategies.

A bin is a long in ``0 .. size-1``. The domain is generated, never read off the
data, so empty bins are padded like any other.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Blocking:
    """``bins`` gives a record's bins (array of long), ``partners`` the bins of B that a bin of A meets."""

    name: str
    size: int
    bins: Callable[[], Column]
    partners: Callable[[Column], Column]
    max_bins: int = 1
    max_partners: int = 1

    def domain(self, spark: SparkSession) -> DataFrame:
        """Every bin, empty ones included."""
        return spark.range(self.size).select(F.col("id").alias("bin"))

    def sensitivity(self) -> int:
        """Largest change of bin counts when one record is swapped for another."""
        return 2 * self.max_bins

    def assign(self, party: DataFrame) -> DataFrame:
        """One row per record and bin; records without a bin go nowhere. Narrow: no shuffle."""
        return party.withColumn("bin", F.explode(self.bins()))

    def strategy(self, spark: SparkSession) -> DataFrame:
        """The bin pairs ``a_bin, b_bin``."""
        return self.domain(spark).select(F.col("bin").alias("a_bin"), F.explode(self.partners(F.col("bin"))).alias("b_bin"))

    def check_efficiency(self, spark: SparkSession, n: int) -> DataFrame:
        """Preconditions of subquadratic cost: bins below n squared, bounded partners."""
        per = self.strategy(spark).groupBy("a_bin").agg(F.count("*").alias("c"))
        return per.agg(F.max("c").alias("max_partners"), F.count("*").alias("bins")).withColumn(
            "subquadratic", (F.col("bins") < F.lit(float(n) * n)) & (F.col("max_partners") <= self.max_partners)
        )


def _own(b: Column) -> Column:
    return F.array(b)


def equal_keys(name: str, size: int, key: Column) -> Blocking:
    """One bin per key; corresponding bins meet."""
    return Blocking(name, size, lambda: F.array(key), _own)


def grid_neighbors(times: int, nx: int, ny: int, time: Column, cx: Column, cy: Column) -> Blocking:
    """Time slots times a grid; a cell meets itself and its neighbours, clipped at the border."""

    def partners(b: Column) -> Column:
        x, y, t = F.floor(b / ny) % nx, b % ny, F.floor(b / (nx * ny))
        steps = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i in (-1, 0, 1) for j in (-1, 0, 1)])
        inside = F.filter(
            steps, lambda s: (x + s["i"] >= 0) & (x + s["i"] < nx) & (y + s["j"] >= 0) & (y + s["j"] < ny)
        )
        return F.transform(inside, lambda s: ((t * nx + x + s["i"]) * ny + y + s["j"]).cast("long"))

    return Blocking("grid", times * nx * ny, lambda: F.array(((time * nx + cx) * ny + cy).cast("long")), partners, 1, 9)


def sorted_window(size: int, key: Column, low: float, high: float, w: int = 1) -> Blocking:
    """Sorted neighbourhood over a declared key range in equal steps: a bin meets those up to ``w`` away."""
    place = F.greatest(F.lit(0), F.least(F.lit(size - 1), F.floor((key - low) / ((high - low) / size)))).cast("long")

    def partners(b: Column) -> Column:
        return F.sequence(F.greatest(F.lit(0).cast("long"), b - w), F.least(F.lit(size - 1).cast("long"), b + w))

    return Blocking("sorted", size, lambda: F.array(place), partners, 1, 2 * w + 1)


def cyclic_window(size: int, window: int, home: Column) -> Blocking:
    """A bin meets the ``window`` bins from its own on, around the circle."""

    def partners(b: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.lit(window - 1)), lambda j: F.pmod(b + j, F.lit(size)).cast("long"))

    return Blocking("window", size, lambda: F.array(home), partners, 1, window)


def multi(name: str, size: int, keys: list[Column]) -> Blocking:
    """Each record in several bins; a pair counts once in the output, as often in the cost as it meets."""
    return Blocking(name, size, lambda: F.array_distinct(F.array(*keys)), _own, len(keys))


def meeting_pairs(a: DataFrame, b: DataFrame, blocking: Blocking) -> DataFrame:
    """One row ``pairs``: distinct pairs of records with a common bin, for strategies where a bin meets itself only.

    By inclusion and exclusion over the sets of bins that records share: a
    record has at most 2 ** max_bins - 1 sets, which are counted, never paired.
    """

    def sets(party: DataFrame, name: str) -> DataFrame:
        bins = F.array_sort(F.filter(F.array_distinct(blocking.bins()), lambda x: x.isNotNull()))
        steps = F.sequence(F.lit(1), F.call_function("shiftleft", F.lit(1), F.size("bins")) - 1)
        some = lambda m: F.filter(F.col("bins"), lambda x, i: F.call_function("shiftright", m, i).bitwiseAND(F.lit(1)) == 1)
        rows = party.select(bins.alias("bins")).filter(F.size("bins") > 0)
        return rows.select(F.explode(F.transform(steps, some)).alias("set")).groupBy("set").agg(F.count("*").alias(name))

    n = F.col("na").cast("decimal(19,0)") * F.col("nb").cast("decimal(19,0)")
    sign = F.when(F.size("set") % 2 == 1, n).otherwise(-n)
    return sets(a, "na").join(sets(b, "nb"), "set").agg(F.coalesce(F.sum(sign).cast("long"), F.lit(0).cast("long")).alias("pairs"))
