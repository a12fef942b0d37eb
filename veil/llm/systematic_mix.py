"""Mixing sources to target weights by systematic sampling (native).

Within each source, documents are put in order of size; each document's
expected number of copies is prefix-summed, one random offset per source is
added, and a copy is emitted for every integer boundary that the running sum
crosses. Ordering by size makes every stratum of sizes sampled in proportion,
so the words taken come near the target and not only the number of documents.

The prefix sum runs over all sources at once in four levels: rows are summed
inside buckets (source, size, hash range), the buckets of a size along its hash
ranges, the sizes along each size class, and the classes, a small table, along
each source; the rows add the starts of all. No task holds a source, only a bucket; there are at least 64
hash ranges, more for more rows, so a bucket stays bounded even when one
source or one size holds a third of the table. The order is (size, digest, id)
at every number of ranges, so the result does not depend on it. Targets need a
common level over sources ordered by name and by cap; both orders are numbered
by ranges, so very many sources are no single task either. Sums are integers in
units of 1e-8 copies, so reruns and retries agree exactly.

Defined results: texts of any length count as a whole; null texts have size 0 and take nothing; the null source
comes last; sources whose documents are all empty have target 0; repeated
rows are separate documents with equal order keys (which of them is emitted
does not change the multiset); extra columns pass through unless they have one
of the names this operator computes; an empty table mixes to an empty table.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from veil.llm.words import word_count
from veil.operators.skew import running
from veil.sources.shared import materialize

UNIT = 100_000_000
MAX_COPIES = 3
LEAST_CLASSES, ROWS_PER_CLASS = 64, 1_000_000
COMPUTED = ("size", "source_size", "target", "copies", "taken")


def targets(sizes: DataFrame, max_copies: int = MAX_COPIES) -> DataFrame:
    """Add ``target`` (double) to ``source, source_size``: weights 1, 2, 3 repeating, capped and reshared.

    Resharing the excess until no target is above its cap ends in one common
    level ``v``: a source gets ``min(cap, v * weight)`` and all shares add up.
    Sources are sorted by cap per weight; the level is the one at which the
    first uncapped source stays below its cap. One row per source.
    """
    by_name = running(sizes, [F.col("source").asc_nulls_last()], label="mix-names")
    s = by_name.withColumn("weight", ((F.col("rank") - 1) % 3 + 1).cast("long")).drop("rank")
    s = s.withColumn("cap", max_copies * F.col("source_size"))
    whole = s.agg(F.sum("source_size").alias("all_size"), F.sum("weight").alias("all_weight"))
    by_cap = [F.col("cap") / F.col("weight"), F.col("source").asc_nulls_last()]
    s = running(s, by_cap, {"cap_before": F.col("cap"), "weight_before": F.col("weight")}, "mix-caps").crossJoin(F.broadcast(whole))
    s = s.withColumn("level", (F.col("all_size") - F.col("cap_before")) / (F.col("all_weight") - F.col("weight_before")))
    first = F.min(F.when(F.col("level") * F.col("weight") <= F.col("cap"), F.struct("rank", "level")))["level"]
    s = s.crossJoin(F.broadcast(s.agg(first.alias("final"))))
    capped = F.coalesce(F.least(F.col("cap").cast("double"), F.col("final") * F.col("weight")), F.col("cap").cast("double"))
    return s.select("source", "source_size", capped.alias("target"))


def uniform(*parts: Column) -> Column:
    """Hash uniform in [0, 1) of 52 bits."""
    hexed = F.substr(F.md5(F.concat_ws("|", *parts)), F.lit(1), F.lit(13))
    return F.conv(hexed, 16, 10).cast("long") / F.lit(float(1 << 52))


def emit_copies(docs: DataFrame, expected: Column, group: str, size: str, key: str, seed: str, n_rows: int) -> DataFrame:
    """Add ``copies`` (long): integer boundaries crossed by each row's expected copies within its group."""
    classes = max(LEAST_CLASSES, math.ceil(n_rows / ROWS_PER_CLASS))
    tie = F.md5(F.concat_ws("|", F.lit(seed), F.col(key).cast("string")))
    octave = F.length(F.bin(F.col(size)))
    rows = docs.withColumns(
        {
            "__u": F.floor(expected * UNIT).cast("long"),
            "__g": F.coalesce(F.concat(F.lit("s"), F.col(group)), F.lit("n")),
            "__o": octave,
            "__m": F.call_function("shiftright", F.col(size), F.greatest(octave - 4, F.lit(0))),
            "__t": tie,
        }
    ).withColumns({"__c": F.floor(F.conv(F.substr("__t", F.lit(1), F.lit(8)), 16, 10).cast("long") * classes / (1 << 32)).cast("int"), "__n": F.col(size)})
    level = ["__g", "__o", "__m"]
    one, bucket = [*level, "__n"], [*level, "__n", "__c"]
    totals = rows.groupBy(*bucket).agg(F.sum("__u").alias("__b"))

    def before(parts: list[str], *order: str) -> Column:
        along = W.partitionBy(*parts).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
        return F.coalesce(F.sum("__b").over(along), F.lit(0))

    sizes = totals.groupBy(*one).agg(F.sum("__b").alias("__b"))
    levels = sizes.groupBy(*level).agg(F.sum("__b").alias("__b")).select(*level, before(["__g"], "__o", "__m").alias("__first"))
    sizes = sizes.select(*one, before(level, "__n").alias("__next"))
    starts = totals.select(*bucket, before(one, "__c").alias("__start")).join(sizes, one).join(levels, level)
    starts = starts.select(*bucket, (F.col("__first") + F.col("__next") + F.col("__start")).alias("__start"))
    inside = W.partitionBy(*bucket).orderBy("__t", key).rowsBetween(W.unboundedPreceding, 0)
    run = rows.withColumn("__run", F.sum("__u").over(inside)).join(starts, bucket)
    offset = F.floor(uniform(F.lit(seed), F.col("__g")) * UNIT).cast("long")
    end = F.col("__run") + F.col("__start") + offset
    start = end - F.col("__u")
    copies = F.expr("__end div {0} - __begin div {0}".format(UNIT))
    out = run.withColumns({"__end": end, "__begin": start}).withColumn("copies", copies)
    return out.drop(*bucket, "__u", "__t", "__b", "__start", "__run", "__end", "__begin")


def sized(docs: DataFrame, text: str = "text") -> DataFrame:
    """Add ``size`` (words, long)."""
    return docs.drop(*COMPUTED).withColumn("size", word_count(F.col(text)))


def mix(docs: DataFrame, seed: str = "mix", group: str = "source", key: str = "doc_id") -> DataFrame:
    """Every row of a sized table with ``source_size, target, copies, taken``.

    The table is written once in the shared folder: sizes are counted in one
    scan, and the sums per source, per bucket and along a bucket read the file.
    """
    rows = materialize(docs, "mix-sized")
    sizes = rows.groupBy(F.col(group).alias("source")).agg(F.sum("size").alias("source_size"))
    goal = targets(sizes).withColumnRenamed("source", "__s")
    joined = rows.join(goal, F.col(group).eqNullSafe(F.col("__s")), "left").drop("__s")
    expected = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(0.0)
    out = emit_copies(joined, expected, group, "size", key, seed, rows.count())
    return out.withColumn("taken", F.col("copies") * F.col("size"))


def sample(docs: DataFrame, **options) -> DataFrame:
    """The mix itself: each document once per copy, with the columns it came with."""
    named = {c: f"__in_{c}" for c in docs.columns if c in COMPUTED}  # their names are free while mixing
    mixed = mix(sized(docs.withColumnsRenamed(named)), **options)
    copies = F.explode(F.sequence(F.lit(1).cast("long"), F.col("copies"))).alias("__k")
    out = mixed.filter(F.col("copies") > 0).select(*mixed.columns, copies)
    return out.select(*[F.col(named.get(c, c)).alias(c) for c in docs.columns])
