"""Chase-and-remove: grow the output from found matches and retire matched records.

The sequential loop has a closed form. Take the bipartite graph of all true
matches. The output is every match in a component that holds at least one
candidate match, and a record retires when the first candidate match of its
component is compared. So: join, components, minimum, counts.

Two grains of the check: after every bin pair, or after every comparison. For
the latter every record and dummy has a position in its bin, comparisons are
ordered by (bin-pair rank, Alice position, Bob position), and the cost is
counted per row of comparisons; pairs are never enumerated.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from veil.operators.components import connected_components
from veil.sources.shared import materialize


def sides(matches: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The records of each party in an output."""
    return matches.select(F.col("a_id").alias("rid")).distinct(), matches.select(F.col("b_id").alias("rid")).distinct()


def components(edges: DataFrame) -> DataFrame:
    """``a_id, b_id, component`` of the match graph; parties' ids are kept apart by tags."""
    a, b = F.concat(F.lit("a"), "a_id"), F.concat(F.lit("b"), "b_id")
    tagged = edges.select("a_id", "b_id", a.alias("a"), b.alias("b"))
    labels = connected_components(tagged.select("a", "b"))
    return tagged.join(labels, tagged["a"] == labels["node"]).select("a_id", "b_id", "component")


def retirement(edges: DataFrame, seeds: DataFrame, when: list[str]) -> tuple[DataFrame, DataFrame]:
    """Output edges and, per component, the first candidate match.

    ``edges`` has ``a_id, b_id, component``; ``seeds`` the candidate matches
    with the columns ``when`` that order them. Returns the edges of the reached
    components and ``component, first`` with the smallest ``when`` as a struct.
    """
    placed = seeds.join(edges, ["a_id", "b_id"])
    first = placed.groupBy("component").agg(F.min(F.struct(*when)).alias("first"))
    return edges.join(first, "component"), first


def retired_records(reached: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Per party the records of the output with the time of their component."""
    a = reached.groupBy(F.col("a_id").alias("rid")).agg(F.min("first").alias("first"))
    b = reached.groupBy(F.col("b_id").alias("rid")).agg(F.min("first").alias("first"))
    return a, b


def cost_by_bin_pair(pairs: DataFrame, ret_a: DataFrame, ret_b: DataFrame) -> DataFrame:
    """Comparisons left when the check follows every bin pair: one row ``cost``.

    ``pairs``: ``a_bin, b_bin, na, nb, rank``; ``ret_*``: ``bin, rank`` per
    retired record. Live entries are the noisy size less those retired before.
    """

    def gone(side: str, ret: DataFrame) -> DataFrame:
        p = pairs.select(F.col(f"{side}_bin").alias("bin"), "rank").alias("p")
        r = ret.alias("r")
        return p.join(r, (F.col("p.bin") == F.col("r.bin")) & (F.col("r.rank") < F.col("p.rank"))).groupBy(F.col("p.rank").alias("rank")).agg(
            F.count("*").alias(f"gone_{side}")
        )

    live = pairs.join(gone("a", ret_a), "rank", "left").join(gone("b", ret_b), "rank", "left").fillna(0, ["gone_a", "gone_b"])
    one = (F.col("na") - F.col("gone_a")) * (F.col("nb") - F.col("gone_b"))
    return live.agg(F.sum(one.cast("decimal(38,0)")).alias("cost"))


def cost_by_comparison(pairs: DataFrame, ret_a: DataFrame, ret_b: DataFrame, firsts: DataFrame) -> DataFrame:
    """Comparisons left when the check follows every comparison: one row ``cost``.

    ``ret_*``: ``bin, pos, t, p, q`` of each retired record: its own bin and
    position and the place of its component's first match. ``firsts``: the
    places ``t, p, q`` of the components.

    Per bin pair: live rows times live columns at its start, less what retires
    inside it (a running sum over positions), and rows in which a component is
    found are counted to the found position only.
    """
    pr = pairs.select(F.col("rank").alias("k"), "a_bin", "b_bin", "na", "nb")
    a = pr.join(ret_a.withColumnRenamed("bin", "a_bin"), "a_bin").filter("t <= k")
    b = pr.join(ret_b.withColumnRenamed("bin", "b_bin"), "b_bin").filter("t <= k")
    dead_rows = a.filter("t < k or p < pos").select("k", F.col("pos").alias("at"), (F.col("t") < F.col("k")).alias("before"))
    count_a = dead_rows.groupBy("k").agg(F.count("*").alias("dead_a"))
    count_b = b.groupBy("k").agg(F.count_if(F.col("t") < F.col("k")).alias("gone_b"))
    inside_b = b.filter("t = k").select("k", F.col("p").alias("at"))
    # Columns that retire at row p are missing from the live rows after p.
    found_in = F.broadcast(ret_b.select(F.col("t").alias("k")).distinct())  # at most one row per bin pair; elsewhere no column retires inside
    events = dead_rows.join(found_in, "k", "left_semi").select("k", "at", F.lit(0).alias("kind")).unionByName(inside_b.select("k", "at", F.lit(1).alias("kind")))
    before = W.partitionBy("k").orderBy("at", "kind").rowsBetween(W.unboundedPreceding, -1)
    seen = events.withColumn("retired", F.coalesce(F.sum("kind").over(before), F.lit(0)))
    lost_dead = seen.filter("kind = 0").groupBy("k").agg(F.sum("retired").alias("overlap"))
    lost = inside_b.join(pr.select("k", "na"), "k").groupBy("k").agg(F.sum(F.col("na") - F.col("at")).alias("lost"))
    base = pr.join(count_a, "k", "left").join(count_b, "k", "left").join(lost, "k", "left").join(lost_dead, "k", "left")
    base = base.fillna(0, ["dead_a", "gone_b", "lost", "overlap"])
    per_pair = (F.col("na") - F.col("dead_a")) * (F.col("nb") - F.col("gone_b")) - F.col("lost") + F.col("overlap")
    total = base.agg(F.sum(per_pair.cast("decimal(38,0)")).alias("c"))
    # Rows in which a component is found stop at the found position q.
    found = firsts.withColumnRenamed("t", "k").join(pr, "k")
    row = _retired_before(found, b)
    change = (F.col("q") - F.col("gone_q")) - (F.col("nb") - F.col("gone"))
    fix = row.agg(F.coalesce(F.sum(change.cast("decimal(38,0)")), F.lit(0)).alias("d"))
    return total.crossJoin(fix).select((F.coalesce("c", F.lit(0)) + F.col("d")).alias("cost"))


def _retired_before(found: DataFrame, retired: DataFrame) -> DataFrame:
    """Adds to each ``k, p, q, nb`` the columns of its bin pair retired before row p: ``gone``, and ``gone_q`` up to column q.

    Counting under two bounds without pairing rows and columns: a column stands
    in one node of every level of a binary tree over positions, the columns up
    to q are the union of at most one node per level, and inside a node a
    running count in the order of time answers all rows.
    """

    def shifted(x, level):
        return F.call_function("shiftright", x, level)

    depth = F.length(F.bin("nb"))
    place, level = F.col("pos") - 1, F.col("level")
    when = F.when(F.col("t") < F.col("k"), 0).otherwise(F.col("p"))
    columns = retired.join(F.broadcast(found.select("k").distinct()), "k", "left_semi").select("k", "pos", when.alias("time"), F.explode(F.sequence(F.lit(-1), depth - 1)).alias("level"))
    columns = columns.select("k", "level", F.when(level < 0, 0).otherwise(shifted(place, F.greatest(level, F.lit(0)))).alias("node"), "time", F.lit(1).alias("kind"))
    own = F.filter(F.sequence(F.lit(0), depth - 1), lambda i: shifted(F.col("q"), i) % 2 == 1)
    asked = found.select("k", "p", "q", "nb", F.explode(F.concat(F.array(F.lit(-1)), own)).alias("level"))
    asked = asked.withColumns({"node": F.when(level < 0, 0).otherwise(shifted(F.col("q"), F.greatest(level, F.lit(0))) - 1), "time": F.col("p"), "kind": F.lit(0)})
    along = W.partitionBy("k", "level", "node").orderBy("time", "kind").rowsBetween(W.unboundedPreceding, -1)
    both = asked.unionByName(columns, allowMissingColumns=True)
    counted = both.withColumn("before", F.coalesce(F.sum("kind").over(along), F.lit(0))).filter("kind = 0")
    return counted.groupBy("k", "p", "q", "nb").agg(
        F.sum(F.when(level < 0, F.col("before"))).alias("gone"), F.coalesce(F.sum(F.when(level >= 0, F.col("before"))), F.lit(0)).alias("gone_q")
    )


def chase(matches: DataFrame, seeds: DataFrame, when: list[str]) -> dict[str, DataFrame]:
    """Output and retirement from all true matches and the ordered candidate matches.

    Keys of the result: ``output`` (a_id, b_id), ``ret_a``, ``ret_b`` (rid,
    first), ``firsts`` (component, first). Written once, as several counts read it.
    """
    edges = materialize(components(matches), "chase-edges")
    reached, first = retirement(edges, seeds, when)
    reached = materialize(reached, "chase-reached")
    a, b = retired_records(reached)
    return {"output": reached.select("a_id", "b_id"), "ret_a": a, "ret_b": b, "firsts": first}
