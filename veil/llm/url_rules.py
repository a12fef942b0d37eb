"""URL rules by expanded expressions and hash prefixes (native).

Each distinct URL is expanded into host suffixes at label borders and path
prefixes; the expressions are equi-joined with the rules on a short hash
prefix, confirmed on the full digest, and the longest confirmed rule decides.

A verdict depends on the URL alone, so distinct URLs are judged and the
verdicts joined back: a hot URL is expanded once. The rule side is broadcast
only below a checked number of rules; above it both sides are shuffled.

Defined results: null URLs and URLs without ``://`` have empty host and path,
fit no rule and get the default verdict; repeated rows are judged alike; an
empty rule table leaves every verdict to the default; input columns named as a
result (``host, path, rule, verdict``) are replaced by it, others pass through;
a URL of any length is expanded to no more suffixes and prefixes than the rules
have labels and lengths; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PREFIX_HEX = 8
BROADCAST_RULES = 100_000


def host_of(url: Column) -> Column:
    """After the first ``://`` up to ``/``, ``?``, ``#`` or the end; A-Z lower-cased; else empty."""
    raw = F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://([^/?#]*)", 1)
    return F.translate(raw, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    """What follows the host up to ``?``, ``#`` or the end; else empty."""
    return F.regexp_extract(F.coalesce(url, F.lit("")), r"(?s)^.*?://[^/?#]*([^?#]*)", 1)


def rule_table(spark, rules: list[tuple[str, str]]) -> DataFrame:
    """Rules from (action, ``host/path``) pairs; the host is lower-cased, the path starts with ``/``."""
    rows = [(a, e.split("/", 1)[0].lower(), "/" + e.split("/", 1)[1]) for a, e in rules]
    return spark.createDataFrame(rows, "verdict string, rule_host string, rule_path string")


def _keys(host: Column, path: Column) -> dict[str, Column]:
    digest = F.sha2(F.concat(host, path), 256)
    return {"digest": digest, "short": F.substr(digest, F.lit(1), F.lit(PREFIX_HEX))}


def judge(pages: DataFrame, rules: DataFrame, url: str = "url", default: str = "allow") -> DataFrame:
    """Add ``host``, ``path``, ``rule`` (null if none fits) and ``verdict`` to every row.

    Ties between confirmed rules of one length (one expression listed twice)
    go to ``block``.
    """
    rules = rules.withColumns({**_keys(F.col("rule_host"), F.col("rule_path")), "rule": F.concat("rule_host", "rule_path")})
    shape = rules.agg(
        F.count("*").alias("n"),
        F.max(F.size(F.split("rule_host", r"\."))).alias("labels"),
        F.array_sort(F.collect_set(F.length("rule_path"))).alias("lengths"),
    ).first()
    urls = pages.select(F.col(url).alias("__u")).distinct()
    urls = urls.withColumns({"host": host_of(F.col("__u")), "path": path_of(F.col("__u"))})
    labels, lengths = shape["labels"] or 0, [int(x) for x in shape["lengths"] or []]
    parts = F.split("host", r"\.")
    suffixes = F.transform(
        F.sequence(F.lit(1), F.least(F.size(parts), F.lit(max(labels, 1)))),
        lambda k: F.call_function("substring_index", F.col("host"), F.lit("."), -k),
    )
    prefixes = F.transform(
        F.filter(F.array(*map(F.lit, lengths)).cast("array<int>"), lambda k: k <= F.length("path")),
        lambda k: F.substring(F.col("path"), F.lit(1), k),
    )
    expressions = (
        urls.filter((F.col("host") != "") & (F.col("path") != ""))
        .select("__u", F.explode(suffixes).alias("h"), "path")
        .select("__u", "h", F.explode(prefixes).alias("p"))
        .select("__u", *[c.alias(k) for k, c in _keys(F.col("h"), F.col("p")).items()])
    )
    side = rules.select("short", F.col("digest").alias("full"), "rule", F.col("verdict").alias("ruled"))
    side = F.broadcast(side) if shape["n"] <= BROADCAST_RULES else side
    best = (
        expressions.join(side, "short")
        .filter(F.col("digest") == F.col("full"))
        .groupBy(F.col("__u").alias("__b"))
        .agg(F.max_by(F.struct("rule", "ruled"), F.struct(F.length("rule"), F.col("ruled"))).alias("best"))
    )
    judged = urls.join(best, F.col("__u") == F.col("__b"), "left").select(
        "__u",
        "host",
        "path",
        F.col("best.rule").alias("rule"),
        F.coalesce("best.ruled", F.lit(default)).alias("verdict"),
    )
    kept = pages.drop("host", "path", "rule", "verdict")
    return kept.join(judged, F.col(url).eqNullSafe(F.col("__u")), "left").drop("__u")
