"""Words as runs of characters other than space, tab and the four ASCII line controls."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

GAP = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"
_SPACES = " \t\n\x0b\x0c\r"


def word_array(text: Column) -> Column:
    """The words of a text in order; null and blank texts give an empty array."""
    core = F.btrim(text, F.lit(_SPACES))
    empty = F.array().cast("array<string>")
    return F.when(F.length(core) > 0, F.split(core, GAP, -1)).otherwise(empty)


def word_count(text: Column) -> Column:
    """Number of words as long; null gives 0."""
    core = F.btrim(text, F.lit(_SPACES))
    return F.when(F.length(core) > 0, F.size(F.split(core, GAP, -1))).otherwise(0).cast("long")
