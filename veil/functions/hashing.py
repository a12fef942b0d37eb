"""Hash uniforms: randomness as a pure function of named parts.

Retries, speculation and recomputation draw the same values; no operator uses
a generator whose state depends on partitions.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

UNIT = float(1 << 52)


def hash_int(text: Column) -> Column:
    """52-bit integer from the first 13 hex digits of the MD5."""
    return F.conv(F.substr(F.md5(text), F.lit(1), F.lit(13)), 16, 10).cast("long")


def uniform(*parts: Column | str) -> Column:
    """Uniform in [0, 1) from the parts joined by ``|``."""
    cols = [F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts]
    return hash_int(F.concat_ws("|", *cols)) / F.lit(UNIT)
