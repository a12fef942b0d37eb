"""Links between similar sets, counted without listing pairs or carrying sets along with candidates.

Records with one key and one set form a class. Classes with too many members of
their own can have no link; they leave first, and what they alone shared with
others counts no more. Of the rest two classes are a candidate if they share one
of their rarest members (their prefixes, in one common order) at places that
leave room for enough others, and if sketches of their sets do not rule them out.
Candidates are joined into groups, and inside a group every two sets are compared
exactly. Sets are shuffled only for grouped classes; what leaves a task are counts.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from veil.functions.grams import mix
from veil.operators.components import connected_components
from veil.sources.shared import discard, drop_written, in_arrow, materialize, ship, small_batches

#: Classes in a block; larger groups are compared by pairs of blocks.
BLOCK = 256
#: Columns of the member matrix handled at once.
COLUMNS = 8192
#: Members collected in a task before their buckets are handed on.
MOST_MEMBERS = 2_000_000
#: Bounds of the number of buckets (powers of two), and the counts from which a bucket's members come later in the order.
BITS, LEVELS = (20, 28), (2, 4, 32)
#: Classes that share a prefix member are paired up to this number; more are chained by size.
LIST = 64
#: Entries of prefixes paired in one task, and hits held there before they are made distinct.
ENTRIES, HITS = 200_000, 2_000_000
#: Largest sketch of a set (power of two, in bits).
SKETCH = 13


def _flat(members: pa.Array, salt: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All members of a batch, hashed with their record's salt, and the sizes of the sets."""
    n = members.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = members.flatten().to_numpy(zero_copy_only=False).astype(np.int64, copy=False).view(np.uint64)
    return mix(flat ^ np.repeat(salt.to_numpy(zero_copy_only=False).view(np.uint64), n)), n


def _bucket(h: np.ndarray, bits: int) -> np.ndarray:
    return (h >> np.uint64(64 - bits)).astype(np.int64)


def _bits(most: int) -> int:
    return min(max(int(most).bit_length(), BITS[0]), BITS[1])


def _batch(columns, schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(v, f.type) for v, f in zip(columns, schema)], schema=schema)


def _classes(batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """``rid, side, id, able, n`` of ``rid, side, salt, keyed, g``."""
    for b in batches:
        flat, n = _flat(b.column("g"), b.column("salt"))
        total = np.zeros(len(flat) + 1, np.uint64)
        np.cumsum(mix(flat + np.uint64(1)), out=total[1:])
        ends = np.cumsum(n)
        salt = b.column("salt").to_numpy(zero_copy_only=False).view(np.uint64)
        own = mix(mix(total[ends] - total[ends - n] + mix(salt)) + n.astype(np.uint64)).view(np.int64)
        able = b.column("keyed").to_numpy(zero_copy_only=False) & (n > 0)
        yield pa.RecordBatch.from_arrays([b.column("rid"), b.column("side"), pa.array(own), pa.array(able), pa.array(n, pa.int32())], schema=schema)


def _buckets(batches: Iterator[pa.RecordBatch], schema: pa.Schema, bits: int) -> Iterator[pa.RecordBatch]:
    """``part, low, again, times``: buckets of a task's members by the high bits, those met more than once with their counts."""

    def hand_on(kept: list[np.ndarray]) -> Iterator[pa.RecordBatch]:
        u, n = np.unique(np.concatenate(kept), return_counts=True)
        low, part = (u & 0xFFFF).astype(np.uint16), u >> 16
        parts, at = np.unique(part, return_index=True)
        rows = [], [], [], []
        for p, i, j in zip(parts, at, np.r_[at[1:], len(u)]):
            more = n[i:j] > 1
            for out, v in zip(rows, (int(p), low[i:j].tobytes(), low[i:j][more].tobytes(), np.minimum(n[i:j][more], 255).astype(np.uint8).tobytes())):
                out.append(v)
        yield _batch(rows, schema)

    kept, size = [], 0
    for b in batches:
        h, _ = _flat(b.column("g"), b.column("salt"))
        if len(h):
            kept.append(_bucket(h, bits))
            size += len(h)
        if size >= MOST_MEMBERS:
            yield from hand_on(kept)
            kept, size = [], 0
    if kept:
        yield from hand_on(kept)


def _bitmaps(levels: tuple[int, ...]):
    def bitmaps(t: pa.Table) -> pa.Table:
        """A bitmap per level of the buckets of a part that are met so often."""
        n = np.zeros(1 << 16, np.int64)
        for low, again, times in zip(*(t.column(c).to_pylist() for c in ("low", "again", "times"))):
            n[np.frombuffer(low, np.uint16)] += 1
            n[np.frombuffer(again, np.uint16)] += np.frombuffer(times, np.uint8).astype(np.int64) - 1
        maps = [np.packbits(n >= least, bitorder="little").tobytes() for least in levels]
        return pa.table([t.column("part").slice(0, 1), pa.array([maps], pa.list_(pa.binary()))], ["part", "maps"])

    return bitmaps


def _count(sets: DataFrame, bits: int, levels: tuple[int, ...]):
    """A broadcast of ``bits`` and a bitmap per level of the buckets that members of ``salt, g`` fall into; 32 MB each at most."""
    spark = sets.sparkSession
    with small_batches(spark):
        seen = in_arrow(sets, _buckets, "part int, low binary, again binary, times binary", bits)
        rows = seen.groupBy("part").applyInArrow(_bitmaps(levels), "part int, maps array<binary>").toLocalIterator()
        maps = np.zeros((len(levels), 1 << (bits - 3)), np.uint8)
        for r in rows:
            for m, own in zip(maps, r.maps):
                m[r.part << 13 : (r.part + 1) << 13] = np.frombuffer(own, np.uint8)
    return spark.sparkContext.broadcast((bits, maps))


def _met(bits: np.ndarray, bucket: np.ndarray) -> np.ndarray:
    return (bits[bucket >> 3] >> (bucket & 7).astype(np.uint8)) & 1


def _only(batches: Iterator[pa.RecordBatch], schema: pa.Schema, some) -> Iterator[pa.RecordBatch]:
    """The rows with one of the ids; a few others may stay."""
    bits, (known,) = some.value
    for b in batches:
        rid = b.column("rid").to_numpy(zero_copy_only=False).astype(np.int64).view(np.uint64)
        b = b.filter(pa.array(_met(known, _bucket(mix(rid), bits)) == 1))
        if b.num_rows:
            yield b


def prefix(n: int, least: float) -> int:
    """Members of a set of ``n`` of which a similar set shares one, in any common order."""
    return n - int(np.ceil(least * n - 1e-9)) + 1


def _linkable(batches: Iterator[pa.RecordBatch], schema: pa.Schema, maps, least: float) -> Iterator[pa.RecordBatch]:
    """``rid, n`` of the sets with fewer members of their own than their prefix has."""
    bits, (shared, *_) = maps.value
    for b in batches:
        flat, n = _flat(b.column("g"), b.column("salt"))
        own = np.r_[0, np.cumsum(_met(shared, _bucket(flat, bits)) == 0)]
        ends = np.cumsum(n)
        most = n - np.ceil(least * n - 1e-9).astype(np.int64) + 1
        left = own[ends] - own[ends - n] < most
        yield _batch((b.column("rid").to_numpy(zero_copy_only=False)[left], n[left]), schema)


def sketch(h: np.ndarray) -> bytes:
    """A bitmap of the hashes of a set, of as many bits as it has members or more, up to a bound."""
    bits = min(max(int(len(h)).bit_length(), 6), SKETCH)
    m = np.zeros(1 << bits, bool)
    m[(h & np.uint64((1 << bits) - 1)).astype(np.int64)] = True
    return np.packbits(m, bitorder="little").tobytes()


def may_link(n_a: int, n_b: int, s_a: bytes, s_b: bytes, least: float) -> bool:
    """Whether sketches leave room for enough common members: a bit of one side only is a member that the other has not."""
    a, b = np.frombuffer(s_a, np.uint8), np.frombuffer(s_b, np.uint8)
    while len(a) != len(b):  # the larger one is folded
        x = max(a, b, key=len)
        x = x[: len(x) // 2] | x[len(x) // 2 :]
        a, b = (x, b) if len(a) > len(b) else (a, x)
    of = lambda x: int(np.bitwise_count(x).sum())
    return min(n_a - of(a & ~b), n_b - of(b & ~a)) >= least / (1 + least) * (n_a + n_b) - 1e-6


def _prefixes(batches: Iterator[pa.RecordBatch], schema: pa.Schema, maps, least: float) -> Iterator[pa.RecordBatch]:
    """``h, rid, n, pos, sketch``: the members of a set's prefix that may stand in another set, and once a set its sketch."""
    bits, levels = maps.value
    for b in batches:
        flat, sizes = _flat(b.column("g"), b.column("salt"))
        bucket = _bucket(flat, bits)
        level = sum(_met(m, bucket) for m in levels)
        ends = np.cumsum(sizes)
        out, ids, sketches = ([], [], [], []), [], []
        for i, start, end in zip(b.column("rid").to_numpy(), ends - sizes, ends):
            n = int(end - start)
            lv, most = level[start:end], prefix(n, least)
            alone = int(np.count_nonzero(lv == 0))
            if alone >= most:
                continue
            order = np.lexsort((flat[start:end], lv))[alone:most]
            for v, x in zip(out, (flat[start:end][order].view(np.int64), np.full(len(order), i), np.full(len(order), n, np.int32), np.arange(alone, most, dtype=np.int32))):
                v.append(x)
            ids.append((i, n))
            sketches.append(sketch(flat[start:end]))
        if ids:
            h, i, n, pos = map(np.concatenate, out)
            yield _batch((h, i, n, pos, [None] * len(h)), schema)
            none = [None] * len(ids)
            yield _batch((none, [x for x, _ in ids], [x for _, x in ids], none, sketches), schema)


def _pairs(least: float, most: int):
    def distinct(held: list[np.ndarray]) -> np.ndarray:
        x = np.concatenate(held, axis=1)
        x = x[:, np.lexsort(x)]
        return x[:, np.r_[True, (x[:, 1:] != x[:, :-1]).any(axis=0)]] if x.shape[1] else x

    def pairs(t: pa.Table) -> pa.Table:
        """``a, b, sure``: classes that share a member and have room for enough others; those of a long list chained by size, as sure."""
        h, i, n, pos = (t.column(c).to_numpy() for c in ("h", "rid", "n", "pos"))
        order = np.lexsort((i, n, h))
        h, i, n, pos = h[order], i[order], n[order], pos[order]
        once = np.r_[True, (h[1:] != h[:-1]) | (i[1:] != i[:-1])]
        h, i, n, pos = h[once], i[once], n[once].astype(np.int64), pos[once].astype(np.int64)
        first = np.flatnonzero(np.r_[True, h[1:] != h[:-1]])
        size = np.diff(np.r_[first, len(h)])
        end = np.repeat(first + size, size)
        long = np.repeat(size > most, size)
        held, hits = [np.zeros((3, 0), np.int64)], 0
        for step in range(1, max(min(most, int(size.max())), 2)):
            x = np.flatnonzero((np.arange(len(h)) + step < end) & (~long if step > 1 else True))
            if not len(x):
                break
            y = x + step
            fit = n[x] >= least * n[y] - 1e-9
            room = np.minimum(n[x] - pos[x], n[y] - pos[y]) >= least / (1 + least) * (n[x] + n[y]) - 1e-6
            fit &= long[x] | room
            x, y = x[fit], y[fit]
            held.append(np.stack([np.minimum(i[x], i[y]), np.maximum(i[x], i[y]), long[x].astype(np.int64)]))
            hits += len(x)
            if hits > HITS:
                held = [distinct(held)]
                hits = 0
        a, b, sure = distinct(held)
        return pa.table([pa.array(a), pa.array(b), pa.array(sure == 1)], ["a", "b", "sure"])

    return pairs


def _plausible(batches: Iterator[pa.RecordBatch], schema: pa.Schema, least: float) -> Iterator[pa.RecordBatch]:
    for b in batches:
        rows = zip(*(b.column(c).to_pylist() for c in ("n_a", "n_b", "s_a", "s_b")))
        b = b.select(["a", "b"]).filter(pa.array([may_link(*r, least) for r in rows], pa.bool_()))
        if b.num_rows:
            yield pa.RecordBatch.from_arrays(b.columns, schema=schema)


def _sets(batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """``rid, h`` of ``rid, salt, g``."""
    for b in batches:
        flat, n = _flat(b.column("g"), b.column("salt"))
        h = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(n)], pa.int32()), pa.array(flat.view(np.int64))).cast(schema.field(1).type)
        yield pa.RecordBatch.from_arrays([b.column("rid"), h], schema=schema)


def overlaps(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all intersections of sets of distinct members."""
    flat, owner = np.concatenate(sets), np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, column, times = np.unique(flat, return_inverse=True, return_counts=True)
    used = times[column] > 1  # the others are in one set only
    number = np.cumsum(times > 1) - 1
    column, owner = number[column[used]], owner[used]
    order = np.argsort(column, kind="stable")
    column, owner = column[order], owner[order]
    out = np.zeros((len(sets), len(sets)), np.int64)
    width = int(column[-1]) + 1 if len(column) else 0
    for c in range(0, width, COLUMNS):
        i, j = np.searchsorted(column, [c, c + COLUMNS])
        m = np.zeros((len(sets), min(COLUMNS, width - c)), np.float32)
        m[owner[i:j], column[i:j] - c] = 1
        out += np.rint(m @ m.T).astype(np.int64)
    return out


def _compare(least: float):
    def compare(t: pa.Table) -> pa.Table:
        """Records of either side in the classes that are similar to a class, of those that this pair of blocks has."""
        ids, block, x, y = (t.column(c).to_numpy() for c in ("id", "block", "x", "y"))
        n_a, n_b = (t.column(c).to_numpy() for c in ("n_a", "n_b"))
        sets = [s.values.to_numpy(zero_copy_only=False) for s in t.column("h")]
        size, both = np.array([len(s) for s in sets]), overlaps(sets)
        link = (both >= 1) & (both >= least * (size[:, None] + size[None, :] - both))
        if x[0] != y[0]:
            link &= block[:, None] != block[None, :]
        np.fill_diagonal(link, False)
        rows = np.flatnonzero(link.any(axis=1))
        return pa.table([pa.array(v, pa.int64()) for v in (ids[rows], link[rows] @ n_a, link[rows] @ n_b)], ["id", "to_a", "to_b"])

    return compare


def link_counts(d: DataFrame, key: str, members: Column, least: float) -> DataFrame:
    """``rid, class_id, n_links`` per record: the smallest id with its key and set, and its similar records of the other side.

    ``d`` has ``rid`` (long), ``side`` (0 or 1, else of no side), ``key`` and what
    ``members`` reads, an expression of a record's array of distinct hashes. It is
    computed anew where sets are needed, which is cheaper than to keep them. Records are similar that have one key and whose sets have
    a Jaccard similarity of at least ``least`` (above 0); without a key or without
    members nothing is. Members are told apart by 64-bit hashes, and so are classes.
    """
    spark = d.sparkSession
    ship(spark)
    keyed = F.col(key).isNotNull()
    salt = F.xxhash64(F.col(key).isNull(), key).alias("salt")
    known = in_arrow(d.select("rid", F.col("side").cast("long").alias("side"), salt, keyed.alias("keyed"), members.alias("g")), _classes, "rid long, side long, id long, able boolean, n int")
    known = materialize(known, "similar-members")
    per = known.groupBy("id").agg(F.min("rid").alias("class_id"), F.count_if(F.col("side") == 0).alias("n_a"), F.count_if(F.col("side") == 1).alias("n_b"), F.first("able").alias("able"), F.first("n").alias("n"))
    per = materialize(per, "similar-classes")

    def some(ids: DataFrame, count: int):
        return _count(ids.select(F.lit(0).cast("long").alias("salt"), F.array("rid").alias("g")), _bits(16 * count), (1,))

    def sets(ids, *columns: str) -> DataFrame:
        rows = in_arrow(d.filter(keyed), _only, d.schema.toDDL(), ids)
        return rows.select(*columns, salt, members.alias("g"))

    # Classes that cannot be similar to any other leave, once more while the buckets of the others are crowded.
    left, n_left = per.filter("able").select(F.col("class_id").alias("rid"), "n"), None
    while True:
        n_sets, total = left.agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
        ids = some(left, n_sets)
        if n_left is not None and (4 * total < 1 << BITS[1] or total > 0.8 * n_left):
            break
        n_left = total
        maps = _count(sets(ids), _bits(4 * total), LEVELS[:1])
        old, left = left, materialize(in_arrow(sets(ids, "rid"), _linkable, "rid long, n int", maps, least), "similar-left")
        maps.destroy()
        ids.destroy()
        drop_written(*[t for t in (old,) if hasattr(t, "written_at")])
    maps = _count(sets(ids), _bits(2 * total), LEVELS)
    keys = in_arrow(sets(ids, "rid"), _prefixes, "h long, rid long, n int, pos int, sketch binary", maps, least)
    keys = materialize(keys, "similar-keys")
    maps.destroy()
    ids.destroy()
    discard(left)

    entries = keys.filter("h IS NOT NULL").drop("sketch")
    parts = entries.count() // ENTRIES + 1
    pairs = entries.withColumn("part", F.pmod("h", F.lit(parts))).groupBy("part").applyInArrow(_pairs(least, LIST), "a long, b long, sure boolean")
    pairs = materialize(pairs.groupBy("a", "b").agg(F.max("sure").alias("sure")), "similar-pairs")
    sketches = keys.filter("sketch IS NOT NULL").dropDuplicates(["rid"])
    of = lambda x: sketches.select(F.col("rid").alias(x), F.col("n").alias(f"n_{x}"), F.col("sketch").alias(f"s_{x}"))
    plausible = in_arrow(pairs.filter("NOT sure").join(of("a"), "a").join(of("b"), "b"), _plausible, "a long, b long", least)
    groups = connected_components(plausible.unionByName(pairs.filter("sure").select("a", "b")))
    drop_written(pairs)
    discard(keys)

    inside = W.partitionBy("component")
    placed = groups.join(per, groups["node"] == per["class_id"]).select(F.col("class_id").alias("rid"), "component", "n", "n_a", "n_b")
    placed = placed.withColumn("block", ((F.row_number().over(inside.orderBy("n", "rid")) - 1) / BLOCK).cast("int"))
    placed = materialize(placed, "similar-placed")
    # Blocks go up in size; two of them meet unless all their sizes are too far apart.
    spans = placed.groupBy("component", "block").agg(F.min("n").alias("low"), F.max("n").alias("high"))
    others = spans.select("component", F.col("block").alias("other"), F.col("low").alias("other_low"), F.col("high").alias("other_high"))
    near = (F.col("other_high") >= F.lit(least) * F.col("low") - 1e-9) & (F.col("high") >= F.lit(least) * F.col("other_low") - 1e-9)
    meet = spans.join(others, "component").filter(near).select("component", "block", F.least("block", "other").alias("x"), F.greatest("block", "other").alias("y"))
    seats = placed.join(meet, ["component", "block"]).select("rid", "component", "block", "x", "y", "n_a", "n_b")
    ids = some(placed, placed.count())
    own = in_arrow(sets(ids, "rid"), _sets, "rid long, h array<long>").join(seats, "rid").withColumnRenamed("rid", "id")
    found = own.groupBy("component", "x", "y").applyInArrow(_compare(least), "id long, to_a long, to_b long")
    found = materialize(found.groupBy("id").agg(F.sum("to_a").alias("to_a"), F.sum("to_b").alias("to_b")), "similar-links")
    ids.destroy()
    drop_written(*[t for t in (groups,) if hasattr(t, "written_at")])
    discard(placed)
    out = known.select("rid", "side", "id").join(per.drop("n"), "id").join(found.withColumnRenamed("id", "class_id"), "class_id", "left")
    to = F.when(F.col("side") == 0, F.col("n_b") + F.coalesce("to_b", F.lit(0))).when(F.col("side") == 1, F.col("n_a") + F.coalesce("to_a", F.lit(0)))
    return out.select("rid", "class_id", F.coalesce(F.when(F.col("able"), to), F.lit(0)).alias("n_links"))
