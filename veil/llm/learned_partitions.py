"""Approximate nearest neighbours by learned partitions.

Fit, on a bounded sample: the exact neighbour graph of the sample is cut into
balanced parts, keeping neighbours together, and a small network learns to name
a vector's part. Larger tables get a second level: each part is cut again, from
a bounded sample of its own, by a network of its own. Index: every vector goes
to its most probable part. Search: a query goes to its most probable parts and
is compared with all their vectors in double precision. How many parts it takes
is calibrated on held-out vectors for a recall target. A query that found too
few vectors is compared with all.

Scale: the number of parts follows the rows, at least eight and at most
``MOST_PARTS`` squared; the networks are of bounded size and travel with the
tasks. A task compares one block of index rows with one block of queries, both
of bounded size: large parts are cut in several blocks, small ones share one,
and the queries of a block are dealt to as many tasks as their number asks.
Each task returns its best few, which are merged per query.

Defined results: vectors that are null, zero, of another length than most, or
hold null or non-finite components take no part, nor do rows with a null id;
rows that repeat an id with another vector all take part, as queries and as
candidates, and each such query has a list of its own; rows equal in id and
vector count once; a query's own id is never its neighbour; equal scores are
ordered by id; with fewer than ``k`` candidates all are returned; an empty
table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from veil.sources.shared import in_arrow, materialize, ship

#: Bounds of the fit: sample rows, held-out rows, parts of a level, neighbours, hidden units.
FIT_ROWS, HELD_ROWS, MOST_PARTS, NEIGHBOURS, HIDDEN = 8192, 512, 64, 10, 128
LEAST_PARTS, PART_ROWS = 8, 512
RECALL_TARGET = 0.97
#: Rows of a block of the index, and of a block of queries.
BLOCK_ROWS, QUERY_ROWS = 20_000, 20_000
QUERY_BLOCK = 512


@dataclass(frozen=True)
class Net:
    """A network with one hidden layer that names the part of a vector."""

    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: np.ndarray

    def log_odds(self, unit: np.ndarray) -> np.ndarray:
        """Logarithm of the probability of each part."""
        z = np.maximum(unit @ self.w1 + self.b1, 0) @ self.w2 + self.b2
        z = z - z.max(1, keepdims=True)
        return z - np.log(np.exp(z).sum(1, keepdims=True))

    def pack(self) -> bytes:
        return b"".join(np.asarray(x, np.float64).tobytes() for x in (self.w1, self.b1, self.w2, self.b2))

    @staticmethod
    def unpack(data: bytes, d: int, parts: int) -> Net:
        shapes = ((d, HIDDEN), (HIDDEN,), (HIDDEN, parts), (parts,))
        cuts = np.cumsum([int(np.prod(x)) for x in shapes])[:-1]
        return Net(*[x.reshape(shape) for x, shape in zip(np.split(np.frombuffer(data), cuts), shapes)])


@dataclass(frozen=True)
class Model:
    """One or two levels of networks; ``probes`` parts are searched for a query."""

    top: Net
    subs: tuple[Net, ...] = ()
    probes: int = 1

    @property
    def parts(self) -> int:
        return len(self.top.b2) * (len(self.subs[0].b2) if self.subs else 1)

    def scores(self, x: np.ndarray) -> np.ndarray:
        unit = x / np.sqrt((x.astype(np.float64) ** 2).sum(1, keepdims=True))
        top = self.top.log_odds(unit)
        if not self.subs:
            return top
        return np.concatenate([top[:, p : p + 1] + net.log_odds(unit) for p, net in enumerate(self.subs)], axis=1)

    def rank(self, x: np.ndarray, n: int) -> np.ndarray:
        """The n most probable parts of each vector, best first."""
        return np.argsort(-self.scores(x), axis=1, kind="stable")[:, :n]


def usable(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """``vec_id, v`` of the vectors that take part."""
    v = F.col(vec_col).cast("array<double>")
    ok = ~F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists(v, lambda x: x != 0)
    good = vectors.select(F.col(id_col).alias("vec_id"), F.col(vec_col).alias("v")).filter(F.col("vec_id").isNotNull() & F.coalesce(ok, F.lit(False)))
    size = good.groupBy(F.size("v").alias("d")).agg(F.count("*").alias("n")).agg(F.max_by("d", F.struct("n", -F.col("d"))).alias("d"))
    dim = size.first()["d"]
    return good.filter(F.size("v") == (dim or 0))


def neighbour_graph(x: np.ndarray, k: int) -> np.ndarray:
    """Indexes of the k nearest other rows by inner product of unit vectors, in blocks."""
    out = np.zeros((len(x), k), np.int64)
    for lo in range(0, len(x), 1024):
        s = x[lo : lo + 1024] @ x.T
        s[np.arange(len(s)), np.arange(lo, lo + len(s))] = -np.inf
        out[lo : lo + 1024] = np.argpartition(-s, k - 1, axis=1)[:, :k]
    return out


def _fill(gain: np.ndarray, room: int) -> np.ndarray:
    """Give every row a part, highest gains first, no part above its room."""
    n, parts = gain.shape
    left, out = np.full(parts, room), np.full(n, -1)
    order = np.argsort(-gain, axis=1, kind="stable")
    for r in range(parts):
        rows = np.flatnonzero(out < 0)
        if not len(rows):
            break
        want = order[rows, r]
        for p in np.unique(want):
            mine = rows[want == p]
            best = mine[np.argsort(-gain[mine, p], kind="stable")[: left[p]]]
            out[best] = p
            left[p] -= len(best)
    return out


def balanced_cut(x: np.ndarray, graph: np.ndarray, parts: int, rng: np.random.Generator, rounds: int = 12) -> np.ndarray:
    """Balanced parts of the neighbour graph: seeded by balanced centres, refined by neighbours' votes."""
    n = len(x)
    room = int(np.ceil(1.05 * n / parts))
    centres = x[rng.choice(n, parts, replace=False)]
    part = _fill(x @ centres.T, room)
    for _ in range(rounds):
        centres = np.stack([x[part == p].mean(0) if (part == p).any() else x[rng.integers(n)] for p in range(parts)])
        part = _fill(x @ centres.T, room)
    for _ in range(rounds):
        votes = np.zeros((n, parts))
        np.add.at(votes, (np.repeat(np.arange(n), graph.shape[1]), part[graph].ravel()), 1.0)
        np.add.at(votes, (graph.ravel(), np.repeat(part, graph.shape[1])), 1.0)
        votes[np.arange(n), part] += 0.5
        part = _fill(votes + 1e-3 * (x @ centres.T), room)
    return part


def train(x: np.ndarray, part: np.ndarray, parts: int, rng: np.random.Generator, epochs: int = 40) -> Net:
    """Softmax network by mini-batch gradient descent with momentum averages."""
    d = x.shape[1]
    p = [rng.normal(0, d**-0.5, (d, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, (HIDDEN, parts)), np.zeros(parts)]
    m, v, t = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p], 0
    for _ in range(epochs):
        for idx in np.array_split(rng.permutation(len(x)), max(1, len(x) // 256)):
            a, y = x[idx], part[idx]
            h = np.maximum(a @ p[0] + p[1], 0)
            z = h @ p[2] + p[3]
            e = np.exp(z - z.max(1, keepdims=True))
            e /= e.sum(1, keepdims=True)
            e[np.arange(len(y)), y] -= 1
            e /= len(y)
            back = (e @ p[2].T) * (h > 0)
            t += 1
            for i, g in enumerate((a.T @ back + 1e-4 * p[0], back.sum(0), h.T @ e + 1e-4 * p[2], e.sum(0))):
                m[i] = 0.9 * m[i] + 0.1 * g
                v[i] = 0.999 * v[i] + 0.001 * g * g
                p[i] = p[i] - 3e-3 * (m[i] / (1 - 0.9**t)) / (np.sqrt(v[i] / (1 - 0.999**t)) + 1e-8)
    return Net(*p)


def learn(x: np.ndarray, parts: int, seed: int) -> Net:
    """Cut the neighbour graph of unit vectors and learn the parts, with even shares."""
    rng = np.random.default_rng(seed)
    if len(x) < parts or len(x) < 3:  # nothing to learn from: any fixed network will do
        d = x.shape[1]
        return Net(rng.normal(0, d**-0.5, (d, HIDDEN)), np.zeros(HIDDEN), rng.normal(0, HIDDEN**-0.5, (HIDDEN, parts)), np.zeros(parts))
    part = balanced_cut(x, neighbour_graph(x, min(NEIGHBOURS, len(x) - 1)), parts, rng)
    net = train(x, part, parts, rng)
    b2 = net.b2
    for _ in range(20):  # even out the shares of the parts
        net = Net(net.w1, net.b1, net.w2, b2)
        share = np.bincount(np.argmax(net.log_odds(x), 1), minlength=parts) / len(x)
        b2 = b2 - 0.3 * np.log((share + 1e-3) * parts)
    return Net(net.w1, net.b1, net.w2, b2)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.sqrt((x**2).sum(1, keepdims=True))


def _learn_rows(parts: int, seed: int):
    def run(key: tuple, rows: pa.Table) -> pa.Table:
        x = _unit(_matrix(rows.column("v").combine_chunks()).astype(np.float64))
        net = learn(x, parts, seed + key[0].as_py())
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "net": pa.array([net.pack()], pa.binary())})

    return run


def _second_level(vectors: DataFrame, top: Net, parts: int, seed: int) -> tuple[Net, ...]:
    """A network for each part of the first level, learned on executors from at most about FIT_ROWS vectors of it."""
    first = len(top.b2)
    homes = route(vectors, Model(top), 1).select("v", F.col("parts")[0].alias("part"))
    sizes = homes.groupBy("part").agg(F.count("*").alias("n"))
    share = sizes.select("part", F.least(F.lit(1.0), FIT_ROWS / F.col("n")).alias("share"))  # one row per part
    pick = F.pmod(F.xxhash64("v", F.lit(seed)), F.lit(1 << 20)) < F.col("share") * (1 << 20)
    sample = homes.join(F.broadcast(share), "part").filter(pick).select("part", "v")
    nets = sample.groupBy("part").applyInArrow(_learn_rows(parts, seed), "part int, net binary").collect()  # one row per part
    d = top.w1.shape[0]
    known = {r["part"]: Net.unpack(bytes(r["net"]), d, parts) for r in nets}
    return tuple(known.get(p) or learn(np.zeros((0, d)), parts, seed) for p in range(first))


def levels(n_rows: int) -> tuple[int, int]:
    """Parts of the first and of the second level (1: no second level)."""
    parts = max(LEAST_PARTS, n_rows // PART_ROWS)
    if parts <= MOST_PARTS:
        return parts, 1
    return MOST_PARTS, min(MOST_PARTS, -(-parts // MOST_PARTS))


def fit(vectors: DataFrame, n_rows: int, k: int, seed: int = 1) -> Model:
    """Fit on at most FIT_ROWS vectors and calibrate on at most HELD_ROWS others, both by hash order."""
    order = F.xxhash64("vec_id", "v", F.lit(seed))
    picked = vectors.orderBy(order, "vec_id").limit(FIT_ROWS + HELD_ROWS).select("v").collect()
    raw = np.array([r["v"] for r in picked], np.float64)
    held = min(HELD_ROWS, len(raw) // 8)
    first, second = levels(n_rows)
    top = learn(_unit(raw[held:]), first, seed)
    model = Model(top, _second_level(vectors, top, second, seed) if second > 1 else ())
    if held == 0:
        return Model(model.top, model.subs, model.parts)
    q, x = raw[:held], raw[held:]
    home = model.rank(x, 1)[:, 0]
    near = np.argsort(-(q @ x.T), axis=1, kind="stable")[:, :k]
    place = np.argsort(model.rank(q, model.parts), axis=1)  # rank of each part for each query
    reached = np.sort(np.take_along_axis(place, home[near], 1).ravel())
    probes = int(reached[min(len(reached) - 1, int(np.ceil(RECALL_TARGET * len(reached))) - 1)]) + 1
    return Model(model.top, model.subs, probes)


def _matrix(col: pa.Array) -> np.ndarray:
    flat = col.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(col), -1) if len(col) else flat.reshape(0, 0)


def _route_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema, model: Model, probes: int) -> Iterator[pa.RecordBatch]:
    for b in batches:
        if b.num_rows:
            parts = model.rank(_matrix(b.column("v")).astype(np.float64), probes).astype(np.int32)
            columns = [*b.columns, pa.array(list(parts), schema.field("parts").type)]
            yield pa.RecordBatch.from_arrays(columns, names=[*b.schema.names, "parts"])


def route(vectors: DataFrame, model: Model, probes: int) -> DataFrame:
    """Add ``parts``, the most probable parts of each vector ``v``."""
    kept = ", ".join(f"{n} {t}" for n, t in vectors.dtypes)
    return in_arrow(vectors, _route_rows, f"{kept}, parts array<int>", model, probes)


def _best(q_ids: np.ndarray, q: np.ndarray, ids: np.ndarray, x: np.ndarray, k: int) -> Iterator[tuple]:
    """The k best of a block for each query, by exact score, then id: place of the query, ids, scores.

    A product of matrices selects with a margin; the scores of what it selects
    are summed again row by row, so equal vectors get equal scores. Rows of the
    query's own id are left out before the choice.
    """
    for lo in range(0, len(q), QUERY_BLOCK):
        s = q[lo : lo + QUERY_BLOCK] @ x.T
        s[q_ids[lo : lo + QUERY_BLOCK, None] == ids[None, :]] = -np.inf
        floor = np.partition(s, len(ids) - k, axis=1)[:, len(ids) - k] if len(ids) > k else np.full(len(s), -np.inf)
        for i, row in enumerate(s):
            near = np.flatnonzero((row >= floor[i] - 1e-9 * (1 + abs(floor[i]))) & (row > -np.inf) if np.isfinite(floor[i]) else row > -np.inf)
            exact = (x[near] * q[lo + i]).sum(1)
            top = np.lexsort((ids[near], -exact))[:k]
            yield lo + i, ids[near][top], exact[top]


FOUND = "query_id long, query_key long, vec_id long, score double"


def _block_rows(k: int):
    def run(key: tuple, queries: pa.Table, rows: pa.Table) -> pa.Table:
        best: dict[tuple[int, int], list[tuple[np.ndarray, np.ndarray]]] = {}
        if queries.num_rows and rows.num_rows:
            q_all, x_all = (_matrix(t.column("v").combine_chunks()).astype(np.float64) for t in (queries, rows))
            q_ids, ids = (t.column("vec_id").to_numpy() for t in (queries, rows))
            q_keys = queries.column("query_key").to_numpy()
            q_part, part = (t.column("part").to_numpy() for t in (queries, rows))
            for p in np.unique(part):
                mine, own = np.flatnonzero(q_part == p), np.flatnonzero(part == p)
                for at, near, score in _best(q_ids[mine], q_all[mine], ids[own], x_all[own], k):
                    best.setdefault((q_ids[mine[at]], q_keys[mine[at]]), []).append((near, score))
        out: list[list] = [[np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0, np.int64)], [np.zeros(0)]]
        for (qid, qkey), found in best.items():
            near, score = (np.concatenate(c) for c in zip(*found))
            top = np.lexsort((near, -score))[:k]
            for column, values in zip(out, (np.full(len(top), qid), np.full(len(top), qkey), near[top], score[top])):
                column.append(values)
        return pa.table(dict(zip(("query_id", "query_key", "vec_id", "score"), map(np.concatenate, out))))

    return run


def _blocks(spark: SparkSession, rows: dict[int, int], asked: dict[int, int]) -> DataFrame:
    """``part, first, slices, turns`` of each part, from its numbers of index rows and of routed queries.

    Small parts share a block; large ones are cut in slices of BLOCK_ROWS on
    average. The queries of a block are dealt to turns of QUERY_ROWS on average.
    """
    out, shared, block, held = [], [], 0, 0

    def close() -> None:
        nonlocal block, held
        turns = max(1, -(-sum(asked.get(p, 0) for p in shared) // QUERY_ROWS))
        out.extend((p, block, 1, turns) for p in shared)
        block, held = block + bool(shared), 0
        shared.clear()

    for part, n in sorted(rows.items()):  # at most MOST_PARTS squared
        slices = -(-n // BLOCK_ROWS)
        if slices > 1 or held + n > BLOCK_ROWS:
            close()
        if slices > 1:
            out.append((part, block, slices, max(1, -(-asked.get(part, 0) // QUERY_ROWS))))
            block += slices
        else:
            shared.append(part)
            held += n
    close()
    return spark.createDataFrame(out, "part int, first int, slices int, turns int")


def _by_part(df: DataFrame) -> dict[int, int]:
    return {r["part"]: r["n"] for r in df.groupBy("part").agg(F.count("*").alias("n")).collect()}  # one row per part


def _compare(routed: DataFrame, homes: DataFrame, sizes: dict[int, int], k: int) -> DataFrame:
    """Best k per query over its parts: ``query_id, query_key, vec_id, score, rank``."""
    blocks = F.broadcast(_blocks(homes.sparkSession, sizes, _by_part(routed)))  # one row per part

    def upto(n: str):
        return F.explode(F.sequence(F.lit(0), F.col(n) - 1))

    slot = (F.pmod(F.xxhash64("vec_id", "v"), F.col("slices")) + F.col("first")).cast("int")
    index = homes.join(blocks, "part").select("vec_id", "v", "part", slot.alias("block"), upto("turns").alias("turn"))
    turn = F.pmod(F.col("query_key"), F.col("turns")).cast("int")
    queries = routed.join(blocks, "part").select("vec_id", "query_key", "v", "part", "first", turn.alias("turn"), upto("slices").alias("slice"))
    queries = queries.select("vec_id", "query_key", "v", "part", (F.col("first") + F.col("slice")).alias("block"), "turn")
    met = queries.groupBy("block", "turn").cogroup(index.groupBy("block", "turn"))
    found = met.applyInArrow(_block_rows(k), FOUND)
    order = W.partitionBy("query_id", "query_key").orderBy(F.col("score").desc(), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def search(vectors: DataFrame, is_query, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding", model: Model | None = None, probes: int | None = None) -> DataFrame:
    """``query_id, rank, vec_id, score`` of the k nearest found for each query.

    ``is_query`` is a condition over ``vec_id``. ``probes`` overrides the
    calibrated number of parts; all parts make the search exact.
    """
    ship(vectors.sparkSession)
    good = usable(vectors, id_col, vec_col).dropDuplicates(["vec_id", "v"])
    good = materialize(good.withColumn("query_key", F.xxhash64("vec_id", "v")), "ann-vectors")
    n_rows = good.count()
    if n_rows == 0:
        empty: SparkSession = vectors.sparkSession
        return empty.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    model = model or fit(good.select("vec_id", "v"), n_rows, k)
    homes = materialize(route(good.select("vec_id", "v"), model, 1).select("vec_id", "v", F.element_at("parts", 1).alias("part")), "ann-index")
    sizes = _by_part(homes)
    asked = good.filter(is_query)
    columns = ["vec_id", "query_key", "v", F.explode("parts").alias("part")]
    routed = materialize(route(asked, model, min(model.parts, probes or model.probes)).select(*columns), "ann-queries")
    found = materialize(_compare(routed, homes, sizes, k), "ann-found")
    got = found.groupBy("query_id", "query_key").agg(F.count("*").alias("n"))
    own = homes.join(asked.select("vec_id").distinct(), "vec_id").groupBy("vec_id").agg(F.count("*").alias("own"))
    lists = asked.join(own, "vec_id").join(got.withColumnRenamed("query_id", "vec_id"), ["vec_id", "query_key"], "left")
    short = lists.filter(F.coalesce("n", F.lit(0)) < F.least(F.lit(k), n_rows - F.col("own"))).select("vec_id", "v", "query_key")
    short = materialize(short, "ann-short")
    if not short.isEmpty():
        rest = materialize(route(short, model, model.parts).select(*columns), "ann-rest")
        again = materialize(_compare(rest, homes, sizes, k), "ann-again")
        found = found.join(again.select("query_id", "query_key").distinct(), ["query_id", "query_key"], "left_anti").unionByName(again)
    return found.select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def recall(vectors: DataFrame, is_query, k: int = 20, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """One row ``n_wanted, n_found``: how many of the exact k nearest of each query the search finds.

    The exact lists come from the same blocks with every part searched.
    """
    found = search(vectors, is_query, k, id_col, vec_col).select("query_id", "rank", "vec_id")
    exact = search(vectors, is_query, k, id_col, vec_col, probes=MOST_PARTS * MOST_PARTS).select("query_id", "vec_id").distinct()
    hit = exact.join(found.select("query_id", "vec_id", F.lit(1).alias("hit")).distinct(), ["query_id", "vec_id"], "left")
    return hit.agg(F.count("*").alias("n_wanted"), F.count("hit").alias("n_found"))
