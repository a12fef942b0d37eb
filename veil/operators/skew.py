"""Joins with hot keys and running sums without a single sorting task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from veil.sources.shared import materialize

#: A key is hot above one part in HOT of all rows, so there are fewer than HOT hot keys, whatever the data; never below LEAST rows.
HOT, LEAST = 1000, 64


def is_hot(n: Column, total: int) -> Column:
    """Whether a key with ``n`` of ``total`` rows is hot."""
    return n > max(LEAST, total // HOT)


def hot_keys(counts: DataFrame, on: list[str], total: int, n: str = "n") -> DataFrame | None:
    """The keys of ``counts`` with more than one part in HOT of ``total`` rows: a local table of fewer than HOT keys, or none."""
    found = counts.filter(is_hot(F.col(n), total)).select(*on)
    rows = found.collect()
    return counts.sparkSession.createDataFrame(rows, found.schema) if rows else None


def join_hot(left: DataFrame, right: DataFrame, on: list[str], hot: DataFrame | None, how: str = "inner") -> DataFrame:
    """Equi-join of ``left`` with a ``right`` of unique keys, where ``hot`` keys of ``left`` stay in place.

    ``hot`` has fewer than HOT distinct keys, so the rows of ``right`` that
    belong to them are broadcast; the other keys are shuffled. ``left`` and
    ``right`` should be written tables, as both are read twice. ``how`` is
    ``inner`` or ``left``; null keys match nothing.
    """
    if hot is None:
        return left.join(right, on, how)
    marked = left.join(F.broadcast(hot.withColumn("__hot", F.lit(True))), on, "left")
    few = right.join(F.broadcast(hot), on, "left_semi")
    cold = marked.filter("__hot is null").drop("__hot").join(right, on, how)
    return cold.unionByName(marked.filter("__hot").drop("__hot").join(F.broadcast(few), on, how))


def running(df: DataFrame, order: list[Column], sums: dict[str, Column] | None = None, label: str = "running") -> DataFrame:
    """Adds ``rank`` (long, from 1) and exclusive running sums in a total order.

    Rows are dealt to ranges of the order and written; each range is numbered
    and summed in its own task, and the totals of the ranges before it, one row
    per range, are added. Without ties in ``order`` the result does not depend
    on where the ranges are cut.
    """
    spark = df.sparkSession
    sums = sums or {}
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    dealt = df.withColumns({f"__{k}": c for k, c in sums.items()}) if sums else df
    dealt = materialize(dealt.repartitionByRange(n, *order).withColumn("__p", F.spark_partition_id()), label)
    inside = W.partitionBy("__p").orderBy(*order)
    before = inside.rowsBetween(W.unboundedPreceding, -1)
    zero = F.lit(0)
    rows = dealt.withColumns({"rank": F.row_number().over(inside).cast("long"), **{k: F.coalesce(F.sum(f"__{k}").over(before), zero) for k in sums}})
    totals = dealt.groupBy("__p").agg(F.count("*").alias("__n"), *[F.sum(f"__{k}").alias(f"__{k}") for k in sums])
    along = W.orderBy("__p").rowsBetween(W.unboundedPreceding, -1)  # one row per range
    first = totals.select("__p", *[F.coalesce(F.sum(f"__{k}").over(along), zero).alias(f"__first_{k}") for k in ("n", *sums)])
    out = rows.join(F.broadcast(first), "__p")
    return out.withColumns({k: F.col(k) + F.col(f"__first_{f}") for k, f in (("rank", "n"), *((k, k) for k in sums))}).select(*df.columns, "rank", *sums)
