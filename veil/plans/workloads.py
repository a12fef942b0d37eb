"""Experiment workloads on the given tables: parties, rule and blocking of each."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from veil.functions import encode as E
from veil.functions import rules as R
from veil.functions.grams import run_hashes
from veil.functions.hashing import hash_int, uniform
from veil.operators import blocking as B
from veil.operators.classes import classes
from veil.operators.near import euclidean_part
from veil.sources.shared import materialize, table

BOX_X, BOX_Y, CELLS, SLOTS = 160.0, 100.0, 4, 4
SIZE_X, SIZE_Y, THETA = 40.0, 25.0, 0.2
FIRST_DAY = "2024-01-01"
BRANDS, BITS, HAMMING = 25, 50, 5
#: Declared domains: days from FIRST_DAY on, and quarters from FIRST_QUARTER on; what lies outside goes to the edge bins.
DAYS, FIRST_QUARTER, QUARTERS = 30, 1995 * 4, 28


@dataclass(frozen=True)
class Problem:
    """One linkage problem; ``attributes`` are the encodings that equality intersection compares."""

    name: str
    a: DataFrame
    b: DataFrame
    rule: R.Rule
    blocking: B.Blocking
    attributes: tuple[str, ...] = ()
    gamma: float = 1.0


def _inside(slot: Column, n: int) -> Column:
    return F.greatest(F.lit(0), F.least(F.lit(n - 1), slot)).cast("long")


def location(spark: SparkSession, sf_dir: str, t: int | None = None) -> Problem:
    """All points against perturbed copies, or those before day ``t``; same day and slot, scaled distance at most 0.2.

    The filter on a raw column reaches the Parquet scan. Distances are scaled by
    the cell size; a cell meets its neighbours, and points outside the declared
    box or days are in its edge cells, so the blocking loses no match.
    """
    ev = table(spark, sf_dir, "events").select("event_id", "ts", "value", "props")
    if t is not None:
        ev = ev.filter(F.col("ts") < F.date_add(F.lit(FIRST_DAY).cast("date"), t).cast("timestamp_ntz"))
    day = F.datediff(F.to_date("ts"), F.lit(FIRST_DAY).cast("date"))
    k = F.get_json_object("props", "$.k").cast("double")
    base = ev.select(
        F.col("event_id").alias("rid"),
        F.col("value").alias("x"),
        (k + uniform("k", F.col("event_id"))).alias("y"),
        (day * SLOTS + F.floor(F.hour("ts") / 6)).cast("long").alias("slot"),
    )
    moved = base.select(
        "rid",
        E.shift(F.col("x"), uniform("bx", F.col("rid")), THETA * SIZE_X).alias("x"),
        E.shift(F.col("y"), uniform("by", F.col("rid")), THETA * SIZE_Y).alias("y"),
        "slot",
    )
    rule = R.all_of(R.equal("slot"), R.euclidean(["x", "y"], THETA, [SIZE_X, SIZE_Y]))
    times = SLOTS * (DAYS if t is None else t)
    grid = B.grid_neighbors(times, CELLS, CELLS, _inside(F.col("slot"), times), E.grid(F.col("x"), SIZE_X, CELLS), E.grid(F.col("y"), SIZE_Y, CELLS))
    cut = lambda df: df.withColumns({"tx": E.truncate(F.col("x")), "ty": E.truncate(F.col("y"))})
    return Problem("location", cut(base), cut(moved), rule, grid, ("slot", "tx", "ty"), 1e6 * 3.141592653589793)


def line_digest() -> Column:
    """Digest of the columns of a line that are unique together."""
    return F.md5(F.concat_ws("|", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"))


def line_key() -> Column:
    """Surrogate id of a line: 60 bits of its digest."""
    return F.conv(F.substr(line_digest(), F.lit(1), F.lit(15)), 16, 10).cast("long")


def product(spark: SparkSession, sf_dir: str, t: int | None = None, skewed: bool = False) -> Problem:
    """Product names sold, in all or in ``t`` quarters, two sellers' groups; same quarter and brand, Hamming at most 5 of 50 bits.

    ``skewed`` keeps a line with probability one over its brand's number.
    """
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_shipdate")
    pa = table(spark, sf_dir, "part").select("p_partkey", "p_name", "p_brand")
    quarter = (F.year("l_shipdate") * 4 + F.quarter("l_shipdate") - 1 - FIRST_QUARTER).cast("long")
    brand = F.regexp_extract("p_brand", "[0-9]+", 0).cast("long")
    pa = pa.withColumn("pv", E.bloom(F.col("p_name")))  # once per part, not per line
    rows = li.join(pa, F.col("l_partkey") == F.col("p_partkey")).withColumns({"quarter": quarter, "brand": brand, "rid": line_key()})
    if t is not None:
        rows = rows.filter(F.col("quarter") < t)
    if skewed:
        rows = rows.filter(uniform("z", line_digest()) < 1 / F.col("brand"))
    line = [F.col("l_orderkey"), F.col("l_linenumber")]
    lost = F.when(uniform("t", *line) < 0.9, E.drop_character(F.col("p_name"), uniform("c", *line))).otherwise(F.col("p_name"))

    def party(parity: int, name: Column) -> DataFrame:
        mine = rows.filter(F.col("l_suppkey") % 2 == parity).withColumn("name", name)
        v = F.col("pv") if parity == 0 else F.when(F.col("name") == F.col("p_name"), F.col("pv")).otherwise(E.bloom(F.col("name")))
        return mine.select("rid", "quarter", "brand", "name", v.alias("v"))

    rule = R.all_of(R.equal("quarter"), R.equal("brand"), R.hamming("v", HAMMING, BITS))
    quarters = QUARTERS if t is None else t
    keys = B.equal_keys("brand", BRANDS * quarters, _inside(F.col("quarter"), quarters) * BRANDS + _inside(F.col("brand") - 1, BRANDS))
    return Problem("product_skewed" if skewed else "product", party(0, F.col("p_name")), party(1, lost), rule, keys, ("quarter", "brand", "v"), float(rule.ball_size()))


def countable(p: Problem) -> Problem:
    """The problem in the form whose pairs can be counted without being listed.

    Points stay as they are; otherwise a party becomes its classes of equal
    records, ids of representatives with weights. For blockings of ``attributes``.
    """
    if euclidean_part(p.rule) is not None:
        return p
    a, b = (classes(x, [*p.rule.attributes, *p.attributes]) for x in (p.a, p.b))
    return replace(p, a=a, b=b)


def names(spark: SparkSession, sf_dir: str) -> Problem:
    """Suffixes of customers' and suppliers' names by nation: at most 2 edits and 1 differing digit."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("rid"), F.col("c_nationkey").alias("nation"), F.substring("c_name", 10, 100).alias("suffix"))
    s = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("rid"), F.col("s_nationkey").alias("nation"), F.substring("s_name", 10, 100).alias("suffix"))
    rule = R.all_of(R.equal("nation"), R.edit("suffix", 2), R.digits("suffix", 1))
    return Problem("names", c, s, rule, B.equal_keys("nation", 25, F.col("nation").cast("long")), ("nation", "suffix"))


#: Axes whose signs give the four bits of a vector's bin.
PLANES = tuple(tuple(1.0 if j % 4 == i else 0.0 for j in range(64)) for i in range(4))


def vectors(spark: SparkSession, sf_dir: str, window: int = 3) -> Problem:
    """Embeddings against copies perturbed by hash, Euclidean at most 0.2; sign bits as bins, cyclic windows."""
    e = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("rid"), F.col("embedding").cast("array<double>").alias("vec"))
    step = lambda x, i: x + 0.02 * (2 * (hash_int(F.concat_ws("|", F.lit("v"), F.col("rid"), i)) / F.lit(float(1 << 52))) - 1)
    moved = e.select("rid", F.transform("vec", step).alias("vec"))
    both = [x.withColumn("home", E.sign_bits(F.col("vec"), [list(p) for p in PLANES])) for x in (e, moved)]
    return Problem("vectors", both[0], both[1], R.vector_distance("vec", 0.2), B.cyclic_window(16, window, F.col("home")), ("vec",))


def word_grams(text: Column, n: int = 3) -> Column:
    """Hashes of the distinct runs of ``n`` lower-cased words of a whole text; shorter texts are one run, blank ones none."""
    return F.arrow_udf(lambda t: run_hashes(t, n), "array<bigint>")(F.lower(text))


SIMILAR = 0.75


ROLES = ("system", "user", "assistant")


def talks(spark: SparkSession, sf_dir: str) -> Problem:
    """Whole turns of even against odd conversations with one role, similar in three quarters of their word triples."""
    c = table(spark, sf_dir, "conversations")
    rid = F.concat_ws(":", "conv_id", "turn")
    c = c.select(rid.alias("rid"), "conv_id", "role", word_grams(F.col("text")).alias("g"))
    rule = R.all_of(R.equal("role"), R.qgram("g", SIMILAR))
    number = F.array_position(F.array(*map(F.lit, ROLES)), F.col("role")).cast("long")
    return Problem("talks", c.filter("conv_id % 2 = 0"), c.filter("conv_id % 2 = 1"), rule, B.equal_keys("role", len(ROLES) + 1, F.coalesce(number, F.lit(0).cast("long"))), ("role", "g"))


def passages(spark: SparkSession, sf_dir: str, least: float = 0.5) -> DataFrame:
    """Documents that hold at least a share of a benchmark passage's word 5-grams: set containment by grams as keys.

    ``doc_id, item_id, shared, total``. Grams are hashed to 64 bits and distinct
    per record; those of documents that no passage has are dropped before the
    shuffle while the passages' grams are few enough to be broadcast (checked).
    """

    def grams(df: DataFrame, key: str) -> DataFrame:
        w = F.split(F.btrim(F.lower(F.col("text"))), r"\s+")
        rows = df.select(key, w.alias("w")).filter(F.size("w") >= 5)
        h = F.transform("w", lambda x: F.xxhash64(x))
        rows = rows.select(key, h.alias("h"))
        g = F.slice("h", 1, F.size("h") - 4)
        for k in range(2, 6):  # shifted copies zipped together: linear in the words
            g = F.zip_with(g, F.slice("h", k, F.size("h") - 4), lambda a, b: F.xxhash64(a, b))
        return rows.select(key, F.explode(F.array_distinct(g)).alias("g"))

    d = grams(table(spark, sf_dir, "documents").select("doc_id", "text"), "doc_id")
    b = materialize(grams(table(spark, sf_dir, "benchmark").select("item_id", "text"), "item_id"), "passage-grams")
    total = b.groupBy("item_id").agg(F.count("*").alias("total"))
    names = b.select("g").distinct()
    if names.count() <= MOST_NAMES:
        d = d.join(F.broadcast(names), "g", "left_semi")
    shared = d.join(b, "g").groupBy("doc_id", "item_id").agg(F.count("*").alias("shared"))
    return shared.join(total, "item_id").filter(F.col("shared") >= least * F.col("total")).select("doc_id", "item_id", "shared", "total")


#: Grams of passages (eight bytes each) up to which they are broadcast to thin out the documents' grams before the shuffle.
MOST_NAMES = 2_000_000
