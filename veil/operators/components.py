"""Connected components of an edge table, by hooking of nodes, pointer jumping and contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veil.operators.skew import hot_keys, is_hot, join_hot
from veil.sources.shared import drop_written, materialize

MAX_ROUNDS = 64


def connected_components(edges: DataFrame, max_rounds: int = MAX_ROUNDS) -> DataFrame:
    """``node, component`` for every node of ``a, b`` (both of one orderable type).

    The component is its smallest node. Each contraction hooks every node with
    a smaller neighbour to the smallest one, follows the hooks to their roots
    by jumping, and replaces both ends of every edge by their roots: edges
    within a tree vanish and equal ones fall together, so later contractions
    read only what still joins different trees. The hooks of all contractions
    are chained at the end. Tables are written to the shared folder and deleted
    when nothing reads them any more. Minima are taken before each shuffle;
    hubs and large trees are joined in place. Raises if ``max_rounds`` jumps in
    all do not suffice; self-loops and repeats are allowed.
    """
    ends = edges.select(F.least("a", "b").alias("lo"), F.greatest("a", "b").alias("hi")).distinct()
    ends = materialize(ends, "cc-edges")
    alone = materialize(ends.filter("lo = hi").select(F.col("lo").alias("node")), "cc-loops")
    pairs, chain, rounds = ends, [], 0
    while n_pairs := pairs.filter("lo < hi").count():
        open_pairs = pairs.filter("lo < hi")
        hooks = materialize(open_pairs.groupBy(F.col("hi").alias("node")).agg(F.min("lo").alias("up")), f"cc-hooks-{len(chain)}")
        n_hooks = hooks.count()
        crowded, moved = _census(hooks.withColumn("moved", F.lit(True)), n_hooks)
        while moved:
            rounds += 1
            if rounds > max_rounds:
                raise RuntimeError(f"components did not settle in {max_rounds} rounds")
            jumped = _follow(hooks, hooks, crowded, f"cc-jumped-{rounds}")
            crowded, moved = _census(jumped, n_hooks)
            drop_written(hooks)
            hooks = jumped
        hooks_of = hooks.select("node", "up")
        hubs = hot_keys(open_pairs.select(F.explode(F.array("lo", "hi")).alias("node")).groupBy("node").agg(F.count("*").alias("n")), ["node"], n_pairs)
        low, high = (hubs and hubs.withColumnRenamed("node", x) for x in ("lo", "hi"))
        half = join_hot(open_pairs, hooks_of.select(F.col("node").alias("hi"), F.col("up").alias("h")), ["hi"], high).select("lo", "h")
        whole = join_hot(half, hooks_of.select(F.col("node").alias("lo"), F.col("up").alias("l")), ["lo"], low, "left").select(F.coalesce("l", "lo").alias("l"), "h")
        merged = whole.filter("l <> h").select(F.least("l", "h").alias("lo"), F.greatest("l", "h").alias("hi")).distinct()
        merged = materialize(merged, f"cc-merged-{len(chain)}")
        drop_written(pairs)
        pairs = merged
        chain.append(hooks)
    drop_written(pairs)
    if not chain:
        return alone.select("node", F.col("node").alias("component"))
    total = chain[-1]
    for hooks in reversed(chain[:-1]):
        crowded, _ = _census(hooks, hooks.count())
        longer = _follow(hooks, total, crowded, "cc-chained")
        old, total = total, materialize(longer.unionByName(total), "cc-total")
        drop_written(hooks, longer, old)
    roots = total.select(F.col("up").alias("node")).unionByName(alone).distinct().join(total, "node", "left_anti")
    labels = materialize(total.select("node", F.col("up").alias("component")).unionByName(roots.select("node", F.col("node").alias("component"))), "cc")
    drop_written(total, alone)
    return labels


def merge_components(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """The components of a graph with the components ``labels`` after ``edges`` between different nodes joined it.

    ``labels`` and ``edges`` are written tables. Only edges between different
    components are worked on.
    """
    ends = edges.select(F.explode(F.array("a", "b")).alias("node")).groupBy("node").agg(F.count("*").alias("n"))
    hubs = hot_keys(ends, ["node"], edges.count())
    known = edges
    for x in ("a", "b"):
        of = labels.select(F.col("node").alias(x), F.col("component").alias(f"{x}_in"))
        known = join_hot(known, of, [x], hubs and hubs.withColumnRenamed("node", x), "left")
    between = known.select(F.coalesce("a_in", "a").alias("a"), F.coalesce("b_in", "b").alias("b")).filter("a <> b")
    delta = connected_components(between)
    large = hot_keys(labels.groupBy("component").agg(F.count("*").alias("n")), ["component"], labels.count())
    moved = join_hot(labels, delta.select(F.col("node").alias("component"), F.col("component").alias("to")), ["component"], large, "left")
    moved = moved.select("node", F.coalesce("to", "component").alias("component"))
    return materialize(moved.unionByName(delta.join(labels, "node", "left_anti")), "cc-grown")


def _follow(hooks: DataFrame, further: DataFrame, crowded: DataFrame | None, label: str) -> DataFrame:
    """``hooks`` one step longer along ``further``, and whether each ``moved``."""
    step = further.select(F.col("node").alias("up"), F.col("up").alias("end"))
    joined = join_hot(hooks.select("node", "up"), step, ["up"], crowded, "left")
    return materialize(joined.select("node", F.coalesce("end", "up").alias("up"), F.col("end").isNotNull().alias("moved")), label)


def _census(hooks: DataFrame, n_hooks: int) -> tuple[DataFrame | None, bool]:
    """The hot targets of hooks, fewer than a thousand, and whether any hook moved, in one job."""
    targets = hooks.groupBy("up").agg(F.count("*").alias("n"), F.max("moved").alias("moved"))
    hot = F.collect_list(F.when(is_hot(F.col("n"), n_hooks), F.struct("up"))).alias("hot")
    row = targets.agg(F.max("moved").alias("moved"), hot).first()
    found = hooks.sparkSession.createDataFrame(row["hot"], targets.select("up").schema) if row["hot"] else None
    return found, bool(row["moved"])
