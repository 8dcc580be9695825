"""Counter-based random numbers: the same for a key under any parallelism, and in SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 60


def draw(*parts: Column | str | int) -> Column:
    """A 60-bit integer from the md5 of the parts joined by ``|``."""
    text = F.concat_ws("|", *(p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint")


def uniform(*parts: Column | str | int) -> Column:
    return draw(*parts) / F.lit(float(1 << BITS))
