"""Counter-based random integers: a hash of the counter, the same in every engine and partitioning."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def hash52(*parts: Column | str | int) -> Column:
    """52 bits of the MD5 of the parts joined by vertical bars."""
    text = F.concat_ws("|", *(p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts))
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 13), 16, 10).cast("bigint")


def unit(*parts: Column | str | int) -> Column:
    """A double in [0, 1)."""
    return hash52(*parts) / F.lit(float(1 << 52))
