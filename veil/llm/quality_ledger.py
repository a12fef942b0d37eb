"""Quality rules as a bitmask ledger (native).

Every rule is evaluated once per document. The ledger keeps the measurements
and one bit per failed rule; a policy is a bitmask with a version, applied
later without touching the text again, and ablations are bitwise aggregates
over the ledger. All expressions are built-in and row-local: no shuffle.

Defined results: null and blank texts have no words, fail the rules on length
and are rejected by every policy that holds those; repeated rows are judged
alike; extra columns pass through, and a column of the input whose name equals
a ledger column is kept out of the ledger's computation (the ledger's wins);
texts of any length are one row of work each; windows and lines that tie are
repeats of each other; an empty table gives an empty ledger.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from veil.llm.words import GAP, WORD, word_array

SYMBOLS = "#*$%&|<>"


@dataclass(frozen=True)
class Rule:
    """``fails`` maps the ledger's measurement columns to a boolean; division is avoided."""

    bit: int
    name: str
    fails: Column


def rules() -> list[Rule]:
    """All rules, each with a fixed bit; bits are never reused."""
    c = F.col
    return [
        Rule(0, "too_few_words", c("n_words") < 50),
        Rule(1, "repeated_windows", 100 * c("n_repeat_words") > 50 * c("n_words")),
        Rule(2, "symbol_heavy", 100 * c("n_symbols") > 50 * c("n_words")),
        Rule(3, "duplicate_lines", 100 * c("n_dup_lines") > 50 * c("n_lines")),
        Rule(4, "words_too_long", c("word_chars") > 15 * c("n_words")),
        Rule(5, "words_too_short", c("word_chars") < 2 * c("n_words")),
    ]


def mask_of(*names: str) -> int:
    """Bitmask of the named rules."""
    bits = {r.name: r.bit for r in rules()}
    return sum(1 << bits[n] for n in names)


#: Versioned policies. ``base`` holds the two rules that every policy includes.
POLICIES = {
    "base": ("too_few_words", "repeated_windows"),
    "v1": ("too_few_words", "repeated_windows", "symbol_heavy", "duplicate_lines"),
    "v2": ("too_few_words", "repeated_windows", "symbol_heavy", "duplicate_lines", "words_too_long", "words_too_short"),
}

MEASURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")


def measure(docs: DataFrame, text: str = "text") -> DataFrame:
    """Add the measurement columns (long).

    Repeated windows are found by sorting the hashes of all three-word windows
    with their positions inside the row; equal neighbours are repeats. Texts
    whose windows are all distinct skip the sort.
    """
    t = F.coalesce(F.col(text), F.lit(""))
    lines = F.filter(F.split(t, "\n", -1), lambda s: s.rlike(WORD))
    base = docs.drop(*MEASURES, "failed_bits").withColumns({"__w": word_array(t), "__l": lines})
    hashed = base.withColumn("__h", F.transform("__w", lambda w: F.xxhash64(w)))
    n = F.size("__h")
    windows = F.when(
        n >= 3,
        F.zip_with(
            F.zip_with(F.slice("__h", 1, n - 2), F.slice("__h", 2, n - 2), lambda a, b: F.xxhash64(a, b)),
            F.slice("__h", 3, n - 2),
            lambda ab, c: F.xxhash64(ab, c),
        ),
    ).otherwise(F.array().cast("array<long>"))
    keyed = hashed.withColumn("__g", windows).withColumn(
        "__s",
        F.when(
            F.size(F.array_distinct("__g")) < F.size("__g"),
            F.sort_array(F.transform("__g", lambda g, i: F.struct(g.alias("g"), i.alias("i")))),
        ),
    )
    s = F.col("__s")
    k = F.size(s)
    nxt, prv = F.slice(s, 2, k), F.concat(F.slice(s, 1, 1), F.slice(s, 1, k - 1))
    marks = F.zip_with(
        F.zip_with(s, nxt, lambda a, b: F.struct(a["i"].alias("i"), a["g"].alias("g"), (a["g"] == b["g"]).alias("n"))),
        prv,
        lambda a, b: F.when(F.coalesce(a["n"], F.lit(False)) | ((a["g"] == b["g"]) & (a["i"] != b["i"])), a["i"]),
    )
    flagged = keyed.withColumn("__p", F.filter(marks, lambda x: x.isNotNull()))
    covered = F.array_distinct(F.flatten(F.transform("__p", lambda i: F.array(i, i + 1, i + 2))))
    out = flagged.withColumns(
        {
            "n_words": F.size("__w").cast("long"),
            "word_chars": F.length(F.regexp_replace(t, GAP, "")).cast("long"),
            "n_symbols": F.length(F.regexp_replace(t, f"[^{SYMBOLS}]+", "")).cast("long"),
            "n_lines": F.size("__l").cast("long"),
            "n_dup_lines": (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long"),
            "n_repeat_words": F.when(s.isNull(), 0).otherwise(F.size(covered)).cast("long"),
        }
    )
    return out.drop("__w", "__l", "__h", "__g", "__s", "__p")


def ledger(docs: DataFrame, text: str = "text") -> DataFrame:
    """Measurements plus ``failed_bits`` (long), one bit per failed rule."""
    bits = F.lit(0).cast("long")
    for r in rules():
        bits = bits.bitwiseOR(F.when(r.fails, F.lit(1 << r.bit)).otherwise(0).cast("long"))
    return measure(docs, text).withColumn("failed_bits", bits)


def passes(policy: str) -> Column:
    """Whether a ledger row passes a policy: none of its bits is set."""
    return F.col("failed_bits").bitwiseAND(F.lit(mask_of(*POLICIES[policy])).cast("long")) == 0


def ablation(led: DataFrame, policy: str) -> DataFrame:
    """Per rule of a policy: documents failing it, failing only it, and kept if it were dropped.

    One pass, one row per rule: bitwise conditional counts, partially aggregated.
    """
    mask = mask_of(*POLICIES[policy])
    bits = F.col("failed_bits").bitwiseAND(F.lit(mask).cast("long"))
    chosen = [r for r in rules() if r.name in POLICIES[policy]]
    kept = F.count_if(bits == 0)
    row = led.agg(
        *[
            F.struct(
                F.lit(r.name).alias("rule"),
                F.count_if(bits.bitwiseAND(F.lit(1 << r.bit).cast("long")) != 0).alias("n_failed"),
                F.count_if(bits == (1 << r.bit)).alias("n_only"),
                (kept + F.count_if(bits == (1 << r.bit))).alias("n_kept_without"),
            ).alias(r.name)
            for r in chosen
        ]
    )
    return row.select(F.inline(F.array(*[F.col(r.name) for r in chosen])))


def keep(docs: DataFrame, policy: str = "v1", text: str = "text") -> DataFrame:
    """The documents that pass, with the columns they came with.

    The filter refers to a column without a fixed value, so it stays above the
    ledger: pushed down, it would repeat the measurements inside one expression.
    """
    named = {c: f"__in_{c}" for c in docs.columns if c in (*MEASURES, "failed_bits") and c != text}
    guarded = ledger(docs.withColumnsRenamed(named), text).withColumn("__once", F.monotonically_increasing_id())
    kept = guarded.filter(passes(policy) & (F.col("__once") >= 0))
    return kept.select(*[F.col(named.get(c, c)).alias(c) for c in docs.columns])
