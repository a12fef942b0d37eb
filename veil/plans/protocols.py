"""Linkage protocols and the baselines they are compared with.

Both parties are simulated in one application; the ideal secure comparison is a
column expression. What the privacy definitions speak about is ``view``, the
table of candidate counts, together with the matches.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veil.functions.rules import Rule
from veil.operators import chase as C
from veil.operators import near, padding, prune
from veil.operators.blocking import Blocking
from veil.operators.exact import compare, match_join
from veil.plans.budget import Budget, center, center_negligible
from veil.sources.shared import materialize

DEFAULT = Budget(1.6, 1e-5)


@dataclass(frozen=True)
class Scope:
    """Which accepted pairs a protocol outputs, so that they can be counted where they meet.

    Pairs of the parties ``a`` and ``b`` whose bin pair is in ``live`` (None:
    any), whose records both have ``kept`` where the parties carry it, and as
    many for a pair of classes as ``found`` says (None: all).
    """

    a: DataFrame
    b: DataFrame
    live: DataFrame | None = None
    found: Column | None = None


@dataclass(frozen=True)
class LinkResult:
    """``matches`` (a_id, b_id), ``view`` (a_bin, b_bin, n_candidates), ``cost`` (one row), ``meta``; ``truth`` where all matches are known, ``scope`` where the output can be counted without its pairs, ``counts`` (n_truth, n_found) where it has been."""

    matches: DataFrame
    view: DataFrame
    cost: DataFrame
    meta: dict
    truth: DataFrame | None = None
    scope: Scope | None = None
    counts: DataFrame | None = None

    def with_meta(self, **more: object) -> LinkResult:
        return replace(self, meta={**self.meta, **more})


def _view(pairs: DataFrame) -> DataFrame:
    return pairs.select("a_bin", "b_bin", (F.col("na") * F.col("nb")).cast("decimal(38,0)").alias("n_candidates"))


def _scope(a: DataFrame, b: DataFrame, blocking: Blocking, view: DataFrame) -> Scope | None:
    """The pairs of the bin pairs of a view; none where a record has several bins."""
    return Scope(a, b, view.select("a_bin", "b_bin")) if blocking.max_bins == 1 else None


def _total(view: DataFrame) -> DataFrame:
    return view.agg(F.coalesce(F.sum("n_candidates"), F.lit(0)).cast("decimal(38,0)").alias("cost"))


def check_party(party: DataFrame, rule: Rule) -> DataFrame:
    """Refuse a party without ``rid`` or a rule attribute."""
    missing = [c for c in ("rid", *rule.attributes) if c not in party.columns]
    if missing:
        raise ValueError(f"a party lacks the columns {missing}")
    return party


def plain(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking) -> LinkResult:
    """Blocking without privacy."""
    na = padding.bin_counts(blocking.assign(a)).withColumnRenamed("n_real", "n_noisy")
    nb = padding.bin_counts(blocking.assign(b)).withColumnRenamed("n_real", "n_noisy")
    pairs = prune.pair_table(blocking, na, nb)
    view = _view(pairs)
    return LinkResult(compare(a, b, rule, blocking), view, _total(view), {"method": "plain", "private": False}, scope=_scope(a, b, blocking, view))


def noisy_bins(a: DataFrame, b: DataFrame, blocking: Blocking, eps: tuple[float, float], mu: tuple[int, int], seed: int) -> tuple[DataFrame, DataFrame]:
    """Padded counts of both parties, each with its own noise."""
    na = padding.pad_counts(padding.bin_counts(blocking.assign(a)), blocking, mu[0], eps[0], "a", seed)
    nb = padding.pad_counts(padding.bin_counts(blocking.assign(b)), blocking, mu[1], eps[1], "b", seed)
    return na, nb


def padded(
    a: DataFrame,
    b: DataFrame,
    rule: Rule,
    blocking: Blocking,
    budget_a: Budget = DEFAULT,
    budget_b: Budget | None = None,
    seed: int = 1,
    *,
    order: str = "index",
    stop_at: int = 0,
    chase: bool = False,
    grain: str = "pair",
    negligible_for: int | None = None,
    lossless: bool = True,
) -> LinkResult:
    """Padded blocking, optionally size-ordered, stopped early, and with chase-and-remove.

    ``stop_at`` is the percentile at which comparison stops (0: never).
    ``grain`` is ``pair`` (check after every comparison) or ``bin_pair``.
    ``negligible_for`` takes the centre for a vanishing delta at that many records.
    ``lossless`` says that the blocking holds every match of the rule, so its
    candidates are the match graph; else the graph comes from the full join.
    """
    check_party(a, rule), check_party(b, rule)
    budget_b = budget_b or budget_a
    d = blocking.sensitivity()
    mus = tuple(
        center_negligible(negligible_for, x.eps, d) if negligible_for else center(x.eps, x.delta, d) for x in (budget_a, budget_b)
    )
    na, nb = noisy_bins(a, b, blocking, (budget_a.eps, budget_b.eps), mus, seed)
    every = pairs = prune.pair_table(blocking, na, nb)
    if stop_at or order == "decile":
        pairs = prune.stop(prune.levels(pairs, prune.thresholds(na, nb)), stop_at)
    view = _view(pairs)
    meta = {"method": "padded", "private": True, "budget": (budget_a, budget_b), "centre": mus, "order": order, "stop_at": stop_at, "chase": chase}
    if not chase:
        if not stop_at:
            return LinkResult(compare(a, b, rule, blocking), view, _total(view), meta, scope=_scope(a, b, blocking, view))
        live = pairs.withColumn("rank", F.lit(0).cast("long"))
        found = compare(a, b, rule, blocking, live).select("a_id", "b_id")
        return LinkResult(found.distinct() if blocking.max_bins > 1 else found, view, _total(view), meta, scope=_scope(a, b, blocking, view))
    ranked = materialize(prune.rank(pairs, order, seed), "pairs")
    if grain == "pair" and _meets_in_blocks(rule, blocking):
        return _chased_points(a, b, rule, blocking, (na, nb), ranked, view, seed, {**meta, "grain": grain}, lossless)
    if lossless and blocking.max_bins == 1:  # one comparison gives the match graph and, where a bin pair is live, the seeds
        live = every.join(ranked.select("a_bin", "b_bin", "rank"), ["a_bin", "b_bin"], "left") if stop_at else ranked
        compared = materialize(compare(a, b, rule, blocking, live), "compared")
        seeds, graph = compared.filter("rank is not null"), compared.select("a_id", "b_id")
    else:
        seeds = materialize(compare(a, b, rule, blocking, ranked), "seeds")
        graph = materialize(match_join(a, b, rule, blocking if lossless else None), "graph")
    if grain == "bin_pair":
        out = C.chase(graph, seeds, ["rank"])
        ids_a, ids_b = (blocking.assign(x).select("rid", "bin") for x in (a, b))
        ret = [r.join(i, "rid").select("bin", F.col("first.rank").alias("rank")) for r, i in ((out["ret_a"], ids_a), (out["ret_b"], ids_b))]
        cost = C.cost_by_bin_pair(ranked, *ret)
    elif grain == "pair":
        pa, pb = (
            materialize(padding.positions(blocking.assign(x), n, s, seed).filter("not is_dummy").select("entry", "bin", "pos"), "positions")
            for x, n, s in ((a, na, "a"), (b, nb, "b"))
        )
        at_a = pa.select(F.col("entry").alias("ea"), F.col("bin").alias("a_bin"), F.col("pos").alias("p"))
        at_b = pb.select(F.col("entry").alias("eb"), F.col("bin").alias("b_bin"), F.col("pos").alias("q"))
        placed = seeds.withColumns({"ea": F.col("a_id").cast("string"), "eb": F.col("b_id").cast("string"), "t": F.col("rank")})
        placed = placed.join(at_a, ["ea", "a_bin"]).join(at_b, ["eb", "b_bin"]).select("a_id", "b_id", "t", "p", "q")
        out = C.chase(graph, placed, ["t", "p", "q"])
        ret = [
            r.select(F.col("rid").cast("string").alias("entry"), "first.*").join(at, "entry").select("bin", "pos", "t", "p", "q")
            for r, at in ((out["ret_a"], pa), (out["ret_b"], pb))
        ]
        cost = C.cost_by_comparison(ranked, *ret, out["firsts"].select("first.*"))
    else:
        raise ValueError(f"unknown grain {grain}")
    return LinkResult(out["output"], view, cost.select(F.col("cost").cast("decimal(38,0)").alias("cost")), {**meta, "grain": grain}, graph)


#: Bin pairs up to which their ranks are sent to the tasks.
MOST_RANKS = 1_000_000


def _meets_in_blocks(rule: Rule, blocking: Blocking) -> bool:
    """Whether points of one key and one bin each can be chased without their pairs; bin pairs are declared, so bounded."""
    return bool(rule.keys) and near.euclidean_part(rule) is not None and blocking.max_bins == 1 and blocking.size * blocking.max_partners <= MOST_RANKS


def _chased_points(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking, noisy: tuple[DataFrame, DataFrame], ranked: DataFrame, view: DataFrame, seed: int, meta: dict, lossless: bool) -> LinkResult:
    """Chase-and-remove where points meet: one row per matching record is written, the match graph never is.

    A component's matches are those of its records of A, so the output is
    counted by them, and listed by a semi-join only if somebody reads it.
    """
    ranks = {(r.a_bin, r.b_bin): r["rank"] for r in ranked.select("a_bin", "b_bin", "rank").collect()}
    cols = list(dict.fromkeys(["rid", *rule.attributes, "bin"]))
    at = [padding.placed(blocking.assign(x).select(*cols), n, s, seed).drop("bin") for x, n, s in ((a, noisy[0], "a"), (b, noisy[1], "b"))]
    met = materialize(near.chased(*at, rule, blocking, ranks), "chased")
    reached = met.filter("t is not null")
    ret = [reached.filter(F.col("side") == i).select("bin", "pos", "t", "p", "q") for i in (0, 1)]
    cost = C.cost_by_comparison(ranked, *ret, reached.filter("first").select("t", "p", "q"))
    n = F.col("matches")
    counts = met.agg(F.coalesce(F.sum(n), F.lit(0)).alias("n_truth"), F.coalesce(F.sum(F.when(F.col("t").isNotNull(), n)), F.lit(0)).alias("n_found"))
    truth = match_join(a, b, rule, blocking if lossless else None)
    out = truth.join(reached.filter("side = 0").select(F.col("rid").alias("a_id")), "a_id", "left_semi")
    return LinkResult(out.select("a_id", "b_id"), view, cost.select(F.col("cost").cast("decimal(38,0)").alias("cost")), meta, truth, counts=counts)


def suppressed(a: DataFrame, b: DataFrame, rule: Rule, blocking: Blocking, budget: Budget = DEFAULT, seed: int = 1) -> LinkResult:
    """Signed noise that drops records: the negative control, not private."""
    marked = [padding.mark_kept(blocking.assign(x), blocking, budget.eps, s, seed) for x, s in ((a, "a"), (b, "b"))]
    kept = [padding.suppress(blocking.assign(x), blocking, budget.eps, s, seed) for x, s in ((a, "a"), (b, "b"))]
    na, nb = (padding.suppressed_counts(k, blocking, budget.eps, s, seed) for k, s in zip(kept, "ab"))
    view = _view(prune.pair_table(blocking, na, nb))
    cols = list(dict.fromkeys(["rid", *rule.attributes]))
    x = kept[0].select(*cols, F.explode(blocking.partners(F.col("bin"))).alias("meet")).alias("a")
    y = kept[1].select(*cols, F.col("bin").alias("meet")).alias("b")
    found = x.join(y, (F.col("a.meet") == F.col("b.meet")) & rule.condition())
    found = found.select(F.col("a.rid").alias("a_id"), F.col("b.rid").alias("b_id")).distinct()
    return LinkResult(found, view, _total(view), {"method": "suppressed", "private": False, "end_to_end": False}, scope=Scope(*[m.drop("bin") for m in marked], view.select("a_bin", "b_bin")))


def all_pairs(a: DataFrame, b: DataFrame, rule: Rule, index: Blocking | None = None) -> LinkResult:
    """Secure comparison of every pair: cost by counts, matches by the match-join."""
    n = a.agg(padding.size(a).alias("na")).crossJoin(b.agg(padding.size(b).alias("nb")))
    view = n.select(F.lit(0).alias("a_bin"), F.lit(0).alias("b_bin"), (F.col("na").cast("decimal(19,0)") * F.col("nb").cast("decimal(19,0)")).alias("n_candidates"))
    return LinkResult(match_join(a, b, rule, index), view, _total(view), {"method": "all_pairs", "private": True}, scope=Scope(a, b))


def intersection_cost(n, gamma: float):
    """gamma * n * ln ln n for a column ``n``; below three records no round is needed."""
    return F.when(n >= 3, F.lit(float(gamma)) * n * F.log(F.log(n.cast("double")))).otherwise(0.0)


def intersect(a: DataFrame, b: DataFrame, attributes: list[str]) -> LinkResult:
    """Equality intersection on encoded attributes."""
    x, y = a.select("rid", *attributes).alias("a"), b.select("rid", *attributes).alias("b")
    on = F.col(f"a.{attributes[0]}") == F.col(f"b.{attributes[0]}")
    for c in attributes[1:]:
        on = on & (F.col(f"a.{c}") == F.col(f"b.{c}"))
    found = x.join(y, on).select(F.col("a.rid").alias("a_id"), F.col("b.rid").alias("b_id"))
    scope = None
    if "weight" in a.columns and "weight" in b.columns:  # of classes, those whose attributes are equal
        scope = Scope(a, b, found=F.when(on, F.col("a.weight") * F.col("b.weight")).otherwise(0))
    return LinkResult(found, None, _intersection(a, b, 1.0), {"method": "intersect", "private": True}, scope=scope)


def _intersection(a: DataFrame, b: DataFrame, gamma: float) -> DataFrame:
    n = a.agg(padding.size(a).alias("na")).crossJoin(b.agg(padding.size(b).alias("nb")))
    return n.select(F.round(intersection_cost(F.greatest("na", "nb"), gamma), 6).alias("cost"))


def expanded_intersect(a: DataFrame, b: DataFrame, rule: Rule, gamma: float, index: Blocking | None = None) -> LinkResult:
    """One side expanded by its match ball, then intersected: cost by formula, matches by the match-join."""
    return LinkResult(match_join(a, b, rule, index), None, _intersection(a, b, gamma), {"method": "expanded_intersect", "private": True, "gamma": gamma}, scope=Scope(a, b))


def expand_and_intersect(a: DataFrame, b: DataFrame, col: str, ball: list[int], keys: list[str]) -> LinkResult:
    """The expansion carried out for a small ball of bit masks: explode, then equi-join."""
    x = a.select("rid", *keys, F.explode(F.transform(F.array(*[F.lit(m).cast("long") for m in ball]), lambda m: F.col(col).bitwiseXOR(m))).alias("v")).alias("a")
    y = b.select("rid", *keys, F.col(col).alias("v")).alias("b")
    on = F.col("a.v") == F.col("b.v")
    for c in keys:
        on = on & (F.col(f"a.{c}") == F.col(f"b.{c}"))
    found = x.join(y, on).select(F.col("a.rid").alias("a_id"), F.col("b.rid").alias("b_id"))
    return LinkResult(found, None, _intersection(a, b, float(len(ball))), {"method": "expanded_intersect", "private": True})
