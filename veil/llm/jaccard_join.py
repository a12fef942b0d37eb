"""N-gram Jaccard join with grouped prefixes, exact for sets of word shingles.

1. Sets. Words are hashed, five consecutive words give a shingle, and the
   distinct shingles of a text are its set. Equal sets become one node.
2. Census. Shingle hashes are shuffled in packed form by hash range; each range
   counts in how many sets a shingle occurs. Shingles of one set only can never
   match, so only shared ones return to their sets, with their frequency.
3. Prefixes. In the order of frequency (rare first) a set of n shingles can
   reach the threshold only with sets that share one of its first
   n - ceil(0.75 n) + 1 shingles. Sets with equal size and equal shared prefix
   form a group.
4. Group pairs. Groups that share a prefix shingle are paired under a size
   filter and a position filter (and, in full comparison, a filter on the number
   of shared prefix shingles). Short lists give all pairs. In long lists each
   group is first paired with a few hubs only: links found there join groups to
   components, and pairs within one component need no comparison, as they
   cannot change the result.
5. Verification. Group pairs are expanded to members, whose overlap is counted
   exactly. What the hubs did not join is compared in full at the end, so no
   link between different components is lost.
6. Components of the links, with the smallest document id as their name.
7. Link counts (``jaccard_links``). Two linked sets are in one component, so
   each component's sets are dealt by hash into blocks, and every pair of blocks
   counts the exact overlaps of all its pairs of sets; links are weighted by the
   rows that have a set. The work is the number of pairs inside components.

Scale: the number of ranges follows the bytes of text, so a task holds one range
of bounded size; of a shingle that very many sets have, postings are passed on
as soon as it is known to be that frequent, and all such shingles share the last
place in the order of frequency, ties by hash. Hot keys (a component, a list of
one shingle, a set with many copies) are joined in place: only their few rows of
the other side, fewer than a thousand, are broadcast. Nothing is collected.

Shingles and sets are identified by 64-bit hashes, kept whole. Two of n different
sets share a hash with a chance of about n * n / 2**65: 3 % at a billion sets; such
a pair would count as one set. A shared hash of two shingles moves an overlap by one.

Defined results: null, empty and blank texts have an empty set, link with
nothing and are their own component; texts of fewer than five words have one
shingle, their whole sequence; repeated rows share their set; null ids take
part and a component of null ids only has a null name; an empty table gives an
empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veil.llm.word_hash import BLOCK, mix, segments, word_hashes
from veil.operators.components import connected_components, merge_components
from veil.operators.skew import hot_keys, join_hot
from veil.sources.shared import discard, drop_written, in_arrow, materialize

WORDS = 5
#: Threshold as a fraction.
NUM, DEN = 3, 4
_C = [np.uint64(pow(0xD6E8FEB86659FD93, k + 1, 1 << 64) | 1) for k in range(WORDS)]
SHORT_LIST = 16
HUBS = 3
HUB_ROUNDS = 2
#: Bytes of text per range of shingle hashes.
RANGE_BYTES = 8 << 20
#: Postings of a range after which frequent shingles are looked for, and postings that make a shingle frequent.
LOOK_AFTER, FREQUENT = 4_000_000, 1_000_000
LAST = np.uint32(0xFFFFFFFF)


def shingle_set(words: np.ndarray) -> np.ndarray:
    """Distinct shingle hashes, sorted; fewer than five words make one shingle."""
    n = len(words)
    if n == 0:
        return words
    if n < WORDS:
        return mix(sum((words[k : k + 1] * _C[k] for k in range(n)), np.zeros(1, np.uint64)) + np.uint64(n))
    k = n - WORDS + 1
    return np.unique(mix(sum((words[j : j + k] * _C[j] for j in range(WORDS)), np.zeros(k, np.uint64))))


def sets_of(texts: list[bytes]) -> list[np.ndarray]:
    """The shingle sets of a block of texts."""
    out: list[np.ndarray | None] = [None] * len(texts)
    small = []
    for i, t in enumerate(texts):
        if len(t) > BLOCK:
            out[i] = shingle_set(np.concatenate([h for h, _, _ in segments(t)] or [np.zeros(0, np.uint64)]))
        else:
            small.append(i)
    at = 0
    while at < len(small):
        take, held = [], 0
        while at < len(small) and (not take or held + len(texts[small[at]]) <= BLOCK):
            take.append(small[at])
            held += len(texts[small[at]]) + 1
            at += 1
        h, starts, _ = word_hashes(b" ".join(texts[i] for i in take))
        offsets = np.cumsum([0] + [len(texts[i]) + 1 for i in take])
        cut = np.searchsorted(starts, offsets)
        for j, i in enumerate(take):
            out[i] = shingle_set(h[cut[j] : cut[j + 1]])
    return out


POSTED = "part int, blob binary, docs array<long>, marks array<long>, refs array<long>, sizes array<long>"
FOUND = "bucket int, blob binary, docs array<long>, marks array<long>, refs array<long>, sizes array<long>"


def _posting_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema, parts: int) -> Iterator[pa.RecordBatch]:
    """Packed shingles of a block of texts, one row per hash range, and one row with the block's documents."""
    for b in batches:
        ids, marks, texts = b.column("doc_id").to_pylist(), b.column("mark").to_pylist(), b.column("text").cast(pa.binary())
        at = 0
        while at < len(ids):
            block, held = [], 0
            while at < len(ids) and (not block or held < BLOCK):
                block.append((ids[at], marks[at], texts[at].as_py() or b""))
                held += len(block[-1][2])
                at += 1
            sets = sets_of([t for _, _, t in block])
            refs = [int(np.int64(np.uint64(xxhash.xxh3_64_intdigest(s.tobytes())))) if len(s) else None for s in sets]
            rows: list[tuple] = [(at % parts, None, [i for i, _, _ in block], [m for _, m, _ in block], refs, [len(s) for s in sets])]
            distinct = {r: s for r, s in zip(refs, sets) if r is not None}
            if distinct:
                rows += _packed(distinct, parts)
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows), schema)], schema=schema)


def _packed(sets: dict[int, np.ndarray], parts: int) -> Iterator[tuple]:
    """Per range: number of sets, their ids, sizes and counts, and the shingles as eight bytes each."""
    refs = np.array(list(sets), np.int64)
    sizes = np.array([len(s) for s in sets.values()], np.uint32)
    h = np.concatenate(list(sets.values()))
    owner = np.repeat(np.arange(len(refs), dtype=np.int64), [len(s) for s in sets.values()])
    part = ((h >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)
    order = np.argsort(part * len(refs) + owner, kind="stable")
    part, owner, h = part[order], owner[order], h[order]
    bounds = np.flatnonzero(np.diff(part)) + 1
    for lo, hi in zip(np.concatenate([[0], bounds]), np.concatenate([bounds, [len(part)]])):
        o = owner[lo:hi]
        first = np.concatenate([[0], np.flatnonzero(np.diff(o)) + 1])
        counts = np.diff(np.concatenate([first, [hi - lo]])).astype(np.uint32)
        blob = np.uint32(len(first)).tobytes() + refs[o[first]].tobytes() + sizes[o[first]].tobytes() + counts.tobytes() + h[lo:hi].tobytes()
        yield int(part[lo]), blob, None, None, None, None


class _Range:
    """Postings of one range of hashes: shingle, set and size of the set, repeats removed."""

    def __init__(self) -> None:
        self.k, self.ref, self.size = np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(0, np.uint32)
        self.new: list[tuple[np.ndarray, ...]] = []
        self.frequent = np.zeros(0, np.uint64)
        self.waiting = 0

    def add(self, blob: bytes) -> None:
        n = int(np.frombuffer(blob, np.uint32, 1)[0])
        counts = np.frombuffer(blob, np.uint32, n, 4 + 12 * n)
        refs, sizes = np.repeat(np.frombuffer(blob, np.int64, n, 4), counts), np.repeat(np.frombuffer(blob, np.uint32, n, 4 + 8 * n), counts)
        self.new.append((np.frombuffer(blob, np.uint64, -1, 4 + 16 * n), refs, sizes))
        self.waiting += len(refs)

    def merge(self) -> np.ndarray:
        """Take in what was added, sorted and without repeats; returns how often each posting's shingle occurs."""
        k, ref, size = map(np.concatenate, zip((self.k, self.ref, self.size), *self.new))
        self.new, self.waiting = [], 0
        order = np.lexsort((ref, k))
        k, ref, size = k[order], ref[order], size[order]
        keep = np.ones(len(k), bool)
        keep[1:] = (k[1:] != k[:-1]) | (ref[1:] != ref[:-1])
        self.k, self.ref, self.size = k[keep], ref[keep], size[keep]
        starts = np.flatnonzero(np.concatenate([[True], self.k[1:] != self.k[:-1]])) if len(self.k) else np.zeros(0, np.int64)
        counts = np.diff(np.append(starts, len(self.k)))
        return np.repeat(counts, counts)

    def _take(self, mine: np.ndarray, freq: np.ndarray) -> tuple[np.ndarray, ...]:
        out = self.k[mine], self.ref[mine], self.size[mine], freq[mine].astype(np.uint32)
        self.k, self.ref, self.size = self.k[~mine], self.ref[~mine], self.size[~mine]
        return out

    def pass_on(self) -> tuple[np.ndarray, ...]:
        """Postings of shingles known to be frequent, which leave the memory."""
        freq = self.merge()
        self.frequent = np.union1d(self.frequent, self.k[freq >= FREQUENT])
        return self._take(np.isin(self.k, self.frequent), np.full(len(self.k), LAST))

    def shared(self) -> tuple[np.ndarray, ...]:
        """At the end: the other postings of shingles that several sets have."""
        freq = self.merge()
        return self._take(freq > 1, freq)


def _by_bucket(postings: tuple[np.ndarray, ...], parts: int, schema: pa.Schema) -> pa.RecordBatch:
    """Postings packed by buckets of sets."""
    k, ref, size, freq = postings
    bucket = (ref.view(np.uint64) % np.uint64(parts)).astype(np.int64)
    order = np.argsort(bucket, kind="stable")
    cuts = np.concatenate([[0], np.flatnonzero(np.diff(bucket[order])) + 1, [len(order)]])
    rows = []
    for lo, hi in zip(cuts[:-1], cuts[1:]):
        if hi > lo:
            i = order[lo:hi]
            rows.append((int(bucket[i[0]]), k[i].tobytes() + ref[i].tobytes() + size[i].tobytes() + freq[i].tobytes(), None, None, None, None))
    return _batch(rows, schema)


def _shared_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema, parts: int) -> Iterator[pa.RecordBatch]:
    """The documents as they come, and the shingles of the task's range that several sets have, packed by buckets of sets."""
    ranges: dict[int, _Range] = {}  # one per task, as ranges are dealt by their number
    for b in batches:
        whole = np.flatnonzero(b.column("blob").is_null().to_numpy(zero_copy_only=False))
        if len(whole):
            kept = b.take(pa.array(whole))
            yield pa.RecordBatch.from_arrays([c.cast(f.type) for c, f in zip(kept.columns, schema)], schema=schema)
        for part, blob in zip(b.column("part").to_pylist(), b.column("blob")):
            if blob.is_valid:
                r = ranges.setdefault(part, _Range())
                r.add(blob.as_py())
                if r.waiting >= LOOK_AFTER:
                    yield _by_bucket(r.pass_on(), parts, schema)
    for part in sorted(ranges):
        r = ranges.pop(part)
        if len(r.frequent):
            yield _by_bucket(r.pass_on(), parts, schema)
        yield _by_bucket(r.shared(), parts, schema)


SETS = "ref long, n long, before long, gid long, keys array<long>, items array<long>"


def _prefix_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """Sets that have shared shingles in their prefix: those keys and all shared shingles.

    A task holds one bucket of sets, as packed numbers only.
    """
    blobs: dict[int, list[bytes]] = {}
    for b in batches:
        for bucket, blob in zip(b.column("bucket").to_pylist(), b.column("blob").to_pylist()):
            blobs.setdefault(bucket, []).append(blob)
    for bucket in sorted(blobs):
        cols: list[list[np.ndarray]] = [[], [], [], []]
        for blob in blobs.pop(bucket):
            m = len(blob) // 24
            for c, (kind, at) in zip(cols, ((np.int64, 0), (np.int64, 8 * m), (np.uint32, 16 * m), (np.uint32, 20 * m))):
                c.append(np.frombuffer(blob, kind, m, at))
        k, ref, size, freq = map(np.concatenate, cols)
        order = np.lexsort((k, freq, ref))
        k, ref, size = k[order], ref[order], size[order]
        once = np.ones(len(k), bool)  # postings passed on early may repeat
        once[1:] = (k[1:] != k[:-1]) | (ref[1:] != ref[:-1])
        k, ref, size = k[once], ref[once], size[once]
        cuts = np.concatenate([[0], np.flatnonzero(np.diff(ref)) + 1, [len(ref)]])
        rows, held = [], 0
        for lo, hi in zip(cuts[:-1], cuts[1:]):
            n = int(size[lo])
            before = n - int(hi - lo)
            room = n - (NUM * n + DEN - 1) // DEN + 1 - before
            if room <= 0:
                continue
            keys = k[lo : min(hi, lo + room)]
            gid = xxhash.xxh3_64_intdigest(np.int64(n).tobytes() + keys.tobytes())
            rows.append((int(ref[lo]), n, before, int(np.int64(np.uint64(gid))), keys, np.sort(k[lo:hi])))
            held += hi - lo
            if held > 500_000:
                yield _batch(rows, schema)
                rows, held = [], 0
        yield _batch(rows, schema)


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    cols = list(zip(*rows)) if rows else [[] for _ in schema]
    return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(cols, schema)], schema=schema)


def _enough(a: str, b: str, pos_a: str | None = None, pos_b: str | None = None):
    """Size filter and, with positions, position filter: 7 * overlap >= 3 * (n_a + n_b) must be possible."""
    na, nb = F.col(f"{a}.n"), F.col(f"{b}.n")
    most = F.least(na, nb)
    if pos_a:
        most = F.least(na - F.col(pos_a), nb - F.col(pos_b))
    return (NUM + DEN) * most >= NUM * (na + nb)


def _enough_keys(a: str, b: str):
    """Meet at the first common prefix key only, and share as many prefix keys as a link must.

    A link shares at least ``need`` shingles, so a set of n lacks at most
    n - need of its prefix in the other set. For the set whose prefix ends
    first in the common order, the rest lies in the other's prefix; the smaller
    of both bounds holds for either. A pair whose first common key is not of
    this list was met in a short list or is in one component.
    """
    na, nb = F.col(f"{a}.n"), F.col(f"{b}.n")
    need = F.ceil((na + nb) * NUM / (NUM + DEN))

    def bound(n):
        return n - F.ceil(n * NUM / DEN) + 1 - (n - need)

    common = F.array_intersect(f"{a}.keys", f"{b}.keys")
    return (F.size(common) >= F.least(bound(na), bound(nb))) & (F.element_at(common, 1) == F.col(f"{a}.h"))


def _verified(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs ``a, b`` of sets whose similarity reaches the threshold."""
    one = sets.select(F.col("ref").alias("a"), F.col("n").alias("na"), F.col("items").alias("ia"))
    two = sets.select(F.col("ref").alias("b"), F.col("n").alias("nb"), F.col("items").alias("ib"))
    overlap = F.size(F.array_intersect("ia", "ib"))
    return pairs.join(one, "a").join(two, "b").filter((NUM + DEN) * overlap >= NUM * (F.col("na") + F.col("nb"))).select("a", "b")


def _ordered(a, b):
    return F.least(a, b).alias("a"), F.greatest(a, b).alias("b")


#: Postings of a long list that meet a minority's sets in one task.
SLICE = 4096


def components(sets: DataFrame) -> DataFrame:
    """``node, component`` of every set that links with another one.

    Components of the links found first grow with the links that later steps
    find between them; links within a component are not looked for.
    """
    groups = materialize(
        sets.groupBy("gid").agg(
            F.min("ref").alias("leader"),
            F.first("n").alias("n"),
            F.first("before").alias("before"),
            F.first("keys").alias("keys"),
            F.count("*").alias("members"),
        ),
        "join-groups",
    )
    large = hot_keys(groups, ["gid"], sets.count(), "members")
    entries = groups.select("gid", "leader", "n", "before", F.posexplode("keys").alias("k", "h"))
    entries = materialize(entries.select("gid", "leader", "n", (F.col("before") + F.col("k")).alias("pos"), "h"), "join-entries")
    lengths = materialize(entries.groupBy("h").agg(F.count("*").alias("len")).filter("len > 1"), "join-lengths")
    common = hot_keys(lengths, ["h"], entries.count(), "len")
    lists = materialize(join_hot(entries, lengths, ["h"], common), "join-lists")
    drop_written(entries, lengths)
    e1, e2 = lists.filter(F.col("len") <= SHORT_LIST).alias("x"), lists.filter(F.col("len") <= SHORT_LIST).alias("y")
    near = (F.col("x.h") == F.col("y.h")) & (F.col("x.gid") < F.col("y.gid")) & _enough("x", "y", "x.pos", "y.pos")
    short = e1.join(e2, near).select(F.col("x.gid").alias("g1"), F.col("y.gid").alias("g2"), F.col("x.leader").alias("a"), F.col("y.leader").alias("b"))
    short = materialize(short.distinct(), "join-short")
    long_lists = lists.filter(F.col("len") > SHORT_LIST)
    owned = sets.select("gid", F.col("ref").alias("leader"))
    in_lists = materialize(long_lists.groupBy("gid").agg(F.collect_list(F.struct("n", "pos", "h", "len")).alias("in")), "join-in-lists")
    whole = join_hot(owned, in_lists, ["gid"], large).select("gid", "leader", F.inline("in"))
    whole = materialize(whole, "join-long")  # each member of a group stands for itself
    several = groups.filter("members > 1").select("gid", "leader")
    inside = join_hot(sets.select("gid", "ref"), several, ["gid"], large).filter("ref <> leader")
    inside = inside.select(*_ordered(F.col("ref"), F.col("leader")))
    first = short.select(*_ordered(F.col("a"), F.col("b"))).unionByName(inside).unionByName(_hub_pairs(long_lists, 0))
    first = materialize(first.distinct(), "join-first")
    found = materialize(_verified(first, sets), "join-links-0")

    open_lists = not long_lists.isEmpty()
    labels = connected_components(found)
    drop_written(found)
    for k in range(1, HUB_ROUNDS + 1):
        if not open_lists:
            break
        apart = materialize(_apart(whole, labels), f"join-apart-{k}")
        if apart.isEmpty():
            open_lists = False
            break
        if k < HUB_ROUNDS:
            more = materialize(_verified(_hub_pairs(apart, k).distinct(), sets), f"join-links-{k}")
            labels = merge_components(labels, more)
            drop_written(more)
    if open_lists:
        keyed = apart.join(sets.select(F.col("ref").alias("leader"), "keys"), "leader")
        slices = F.ceil(F.col("len") / SLICE).cast("int")
        x = keyed.filter("minor").withColumn("slice", F.explode(F.sequence(F.lit(0), slices - 1))).alias("x")
        y = keyed.withColumn("slice", F.pmod(F.xxhash64("leader"), slices).cast("int")).alias("y")
        across = (F.col("x.h") == F.col("y.h")) & (F.col("x.slice") == F.col("y.slice")) & (F.col("x.label") != F.col("y.label"))
        once = ~F.col("y.minor") | (F.col("x.leader") < F.col("y.leader"))
        rest = x.join(y, across & once & _enough("x", "y", "x.pos", "y.pos") & _enough_keys("x", "y"))
        rest = rest.select(*_ordered(F.col("x.leader"), F.col("y.leader")))
    left = _between_groups(short.select("g1", "g2"), groups, sets, labels, large)
    left = left.unionByName(rest) if open_lists else left
    left = materialize(left.distinct().join(first, ["a", "b"], "left_anti"), "join-rest")
    drop_written(lists, short, in_lists, whole, first)
    if left.isEmpty():
        return labels
    return merge_components(labels, materialize(_verified(left, sets), "join-links"))


def _between_groups(pairs: DataFrame, groups: DataFrame, sets: DataFrame, labels: DataFrame, large: DataFrame) -> DataFrame:
    """Pairs of sets of paired groups, or of one group, that lie in different components.

    Groups that lie in one and the same component are left out before members meet.
    """
    members = sets.select("gid", "ref").join(labels.withColumnRenamed("node", "ref"), "ref", "left")
    members = materialize(members.select("gid", "ref", F.coalesce("component", "ref").alias("c")), "join-group-members")
    spread = materialize(members.groupBy("gid").agg(F.min("c").alias("lo"), F.max("c").alias("hi")), "join-spread")
    own = groups.filter("members > 1").select(F.col("gid").alias("g1"), F.col("gid").alias("g2"))
    s1, s2 = (spread.select(F.col("gid").alias(f"g{i}"), F.col("lo").alias(f"lo{i}"), F.col("hi").alias(f"hi{i}")) for i in (1, 2))
    one = (F.col("lo1") == F.col("hi1")) & (F.col("lo2") == F.col("hi2")) & (F.col("lo1") == F.col("lo2"))
    split = materialize(pairs.unionByName(own).join(s1, "g1").join(s2, "g2").filter(~one).select("g1", "g2"), "join-split")
    named = materialize(split.select(F.explode(F.array("g1", "g2")).alias("gid")).distinct(), "join-named")
    met = materialize(join_hot(members, named, ["gid"], large), "join-met")
    m1 = met.select(F.col("gid").alias("g1"), F.col("ref").alias("r1"), F.col("c").alias("c1"))
    m2 = met.select(F.col("gid").alias("g2"), F.col("ref").alias("r2"), F.col("c").alias("c2"))
    left = split.join(m1, "g1").join(m2, "g2").filter("c1 <> c2")
    return left.select(*_ordered(F.col("r1"), F.col("r2")))


def _hub_pairs(lists: DataFrame, salt: int) -> DataFrame:
    """Each set of a long list with a few hubs of the list, chosen by hash."""
    hub = F.struct("leader", "n", "pos")
    picks = F.array(*[F.min_by(hub, F.xxhash64("leader", F.lit(HUBS * salt + i))) for i in range(HUBS)]).alias("hubs")
    hubs = materialize(lists.groupBy("h").agg(picks, F.count("*").alias("listed")), "join-hubs")
    common = hot_keys(hubs, ["h"], lists.count(), "listed")
    met = join_hot(lists, hubs.select("h", "hubs"), ["h"], common).select("leader", "n", "pos", F.explode("hubs").alias("y"))
    x = met.select(F.struct("leader", "n", "pos").alias("x"), "y")
    x = x.filter((F.col("x.leader") != F.col("y.leader")) & _enough("x", "y", "x.pos", "y.pos"))
    return x.select(*_ordered(F.col("x.leader"), F.col("y.leader")))


def _apart(lists: DataFrame, labels: DataFrame) -> DataFrame:
    """The lists whose sets are in several components, with each set's label and whether it is a minority."""
    labelled = lists.join(labels.select(F.col("node").alias("leader"), "component"), "leader", "left")
    labelled = materialize(labelled.withColumn("label", F.coalesce("component", "leader")), "join-labels")
    sizes = labelled.groupBy("h", "label").agg(F.count("*").alias("m"))
    split = sizes.groupBy("h").agg(F.count("*").alias("parts"), F.sum("m").alias("listed"), F.max_by("label", F.struct("m", "label")).alias("major"))
    split = materialize(split.filter("parts > 1"), "join-parted")
    common = hot_keys(split, ["h"], labelled.count(), "listed")
    joined = join_hot(labelled, split.select("h", "major"), ["h"], common)
    return joined.select("h", "gid", "leader", "n", "pos", "len", "label", (F.col("label") != F.col("major")).alias("minor"))


#: Bounds of a block of sets of one component: sets, and their shared shingles.
BLOCK_SETS, BLOCK_ITEMS = 512, 1_000_000


def _overlap_rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """Links of each set within one pair of blocks; rows come sorted by component and pair of blocks."""
    held: list[tuple] = []
    pair = None
    for b in batches:
        items = b.column("items")
        offsets, flat = items.offsets.to_numpy(), items.values.to_numpy()
        named = zip(b.column("component").to_pylist(), b.column("lo").to_pylist(), b.column("hi").to_pylist())
        rest = zip(*(b.column(c).to_pylist() for c in ("block", "ref", "n", "copies")))
        for i, (now, (block, ref, n, copies)) in enumerate(zip(named, rest)):
            if held and now != pair:
                yield from _counted(held, pair, schema)
                held = []
            pair = now
            held.append((block, ref, n, copies, flat[offsets[i] : offsets[i + 1]].copy()))
    if held:
        yield from _counted(held, pair, schema)


def _counted(held: list[tuple], pair: tuple, schema: pa.Schema) -> Iterator[pa.RecordBatch]:
    """Exact overlaps of every two sets of a pair of blocks, or of one block with itself."""
    one = [x for x in held if x[0] == pair[1]]
    two = one if pair[1] == pair[2] else [x for x in held if x[0] == pair[2]]
    if not one or not two:
        return
    n1, n2 = (np.array([x[2] for x in side], np.int64) for side in (one, two))
    c1, c2 = (np.array([x[3] for x in side], np.int64) for side in (one, two))
    flat = np.concatenate([x[4] for x in two])
    starts = np.concatenate([[0], np.cumsum([len(x[4]) for x in two])[:-1]])
    names, at = np.unique(flat, return_inverse=True)
    mark = np.zeros(len(names) + 1, np.int32)
    links1, links2 = np.zeros(len(one), np.int64), np.zeros(len(two), np.int64)
    for i, x in enumerate(one):
        place = np.searchsorted(names, x[4])
        place = np.where(names[np.minimum(place, len(names) - 1)] == x[4], place, len(names))
        mark[place] = 1
        mark[len(names)] = 0
        ok = (NUM + DEN) * np.add.reduceat(mark[at], starts, dtype=np.int64) >= NUM * (n1[i] + n2)
        mark[place] = 0
        if two is one:
            ok[i] = False
        links1[i] = c2[ok].sum()
        links2[ok] += c1[i]
    rows = [(x[1], int(k)) for x, k in zip(one, links1) if k]
    if two is not one:
        rows += [(x[1], int(k)) for x, k in zip(two, links2) if k]
    yield _batch(rows, schema)


def _link_counts(sets: DataFrame, labels: DataFrame, copies: DataFrame) -> DataFrame:
    """``ref, others``: rows of other sets that a set links with, for every set of a component."""
    narrow = sets.select("ref", F.size("items").alias("m")).join(labels.withColumnRenamed("node", "ref"), "ref").join(copies, "ref")
    narrow = materialize(narrow, "join-narrow")
    blocks = F.greatest(F.ceil(F.count("*") / BLOCK_SETS), F.ceil(F.sum("m") / BLOCK_ITEMS)).cast("int").alias("blocks")
    counts = narrow.groupBy("component").agg(blocks, F.count("*").alias("of")).filter("of > 1")
    dealt = narrow.join(counts, "component").withColumn("block", F.pmod(F.xxhash64("ref"), "blocks").cast("int"))
    dealt = sets.select("ref", "n", "items").join(dealt.drop("m", "of"), "ref")
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    met = dealt.select("component", "block", "ref", "n", "copies", "items", other)
    met = met.withColumns({"lo": F.least("block", "other"), "hi": F.greatest("block", "other")}).drop("other")
    deal = ["component", "lo", "hi"]
    met = met.repartition(*deal).sortWithinPartitions(*deal)
    parts = in_arrow(met, _overlap_rows, "ref long, links long")
    return parts.groupBy("ref").agg(F.sum("links").alias("others"))


def _labelled(docs: DataFrame, text: str, key: str, mark: Column, count: bool = False) -> DataFrame:
    """``doc_id, mark, n, ref, label`` for every row; sets that link carry their component's label.

    ``count`` adds ``n_links``, the other rows that the row links with.
    """
    spark = docs.sparkSession
    narrow = docs.select(F.col(key).alias("doc_id"), mark.alias("mark"), F.col(text).alias("text"))
    held = narrow.agg(F.sum(F.octet_length("text").cast("long")).alias("n")).first()["n"] or 0
    parts = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")), -(-held // RANGE_BYTES))
    posted = in_arrow(narrow, _posting_rows, POSTED, parts)
    found = materialize(in_arrow(posted.repartitionById(parts, "part"), _shared_rows, FOUND, parts), "join-found")
    rows = found.filter("blob is null").select(F.explode(F.arrays_zip("docs", "marks", "refs", "sizes")).alias("r"))
    rows = rows.select(F.col("r.docs").alias("doc_id"), F.col("r.marks").alias("mark"), F.col("r.refs").alias("ref"), F.col("r.sizes").alias("n"))
    rows = materialize(rows, "join-members")
    packed = found.filter("blob is not null").select("bucket", "blob").repartitionById(parts, "bucket")
    sets = materialize(in_arrow(packed, _prefix_rows, SETS), "join-sets")
    discard(found)
    nodes = components(sets).withColumnRenamed("node", "ref")
    solid = rows.filter("ref is not null")
    copies = materialize(solid.groupBy("ref").agg(F.count("*").alias("copies")), "join-copies")
    if count:
        others = _link_counts(sets, nodes.withColumnRenamed("ref", "node"), copies)
        n_links = (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).cast("long")
        nodes = copies.join(nodes, "ref", "left").join(others, "ref", "left").select("ref", "component", n_links.alias("n_links"))
        nodes = materialize(nodes, "join-nodes")
    many = hot_keys(copies, ["ref"], rows.count(), "copies")
    named = join_hot(solid, nodes, ["ref"], many, "left").withColumn("label", F.coalesce("component", "ref"))
    labelled = materialize(named.unionByName(rows.filter("ref is null"), allowMissingColumns=True), "join-labelled")
    discard(sets)
    return labelled


def _named(labelled: DataFrame, key: str, *more: Column) -> DataFrame:
    """Rows with the smallest document id of their component."""
    solid = labelled.filter("label is not null")
    names = materialize(solid.groupBy("label").agg(F.min("doc_id").alias("name"), F.count("*").alias("of")), "join-names")
    large = hot_keys(names, ["label"], labelled.count(), "of")
    named = join_hot(solid, names.select("label", F.col("name").alias("component_id")), ["label"], large)
    empty = labelled.filter("label is null").withColumn("component_id", F.col("doc_id"))
    return named.unionByName(empty.select(*named.columns)).select(F.col("doc_id").alias(key), F.col("n").alias("n_shingles"), *more, "component_id")


def jaccard_components(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``doc_id, n_shingles, component_id`` for every row."""
    return _named(_labelled(docs, text, key, F.lit(0).cast("long")), key)


def jaccard_links(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """``doc_id, n_shingles, n_links, component_id`` for every row.

    ``n_links`` is the exact number of other rows that reach the threshold
    with the row, exact copies among them; rows without words have none.
    """
    labelled = _labelled(docs, text, key, F.lit(0).cast("long"), True)
    return _named(labelled, key, F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"))


def _row_mark(docs: DataFrame) -> Column:
    """Hash of a whole row; nulls are told apart by place, and maps, which have no hash, are hashed as text."""
    whole = [F.to_json(F.struct(f.name)) if "map<" in f.dataType.simpleString() else F.col(f.name) for f in docs.schema]
    return F.xxhash64(*whole, *[F.col(f.name).isNull() for f in docs.schema])


def keep_representatives(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row of each component stays: the one with the smallest id, nulls last; rows without words all stay.

    Rows are told apart by id and hash of the whole row, not by id alone: rows
    of one id, or of none, whose texts are not linked are in different
    components and stay. Of rows of one component and id the smallest hash
    stays, and of rows equal in every column one.
    """
    mark = _row_mark(docs)
    labelled = _labelled(docs, text, key, mark)
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "mark")).alias("r")
    solid = labelled.filter("label is not null").groupBy("label").agg(first).select("r.doc_id", "r.mark", F.lit(False).alias("__empty"))
    empty = labelled.filter("label is null").select("doc_id", "mark", F.lit(True).alias("__empty")).distinct()
    keep = solid.unionByName(empty).withColumnsRenamed({"doc_id": "__k", "mark": "__m"})
    marked = docs.withColumn("__mark", mark)
    joined = marked.join(keep, F.col(key).eqNullSafe(F.col("__k")) & (F.col("__mark") == F.col("__m")))
    one = joined.filter(~F.col("__empty")).dropDuplicates([key, "__mark"])
    return one.unionByName(joined.filter("__empty")).select(*docs.columns)
