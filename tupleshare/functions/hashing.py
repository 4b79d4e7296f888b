"""Numbers drawn from md5, equal in every engine, partition and retry."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def key(*parts: Column | str | int) -> Column:
    return F.md5(F.concat_ws("|", *(p.cast("string") if isinstance(p, Column) else F.lit(str(p)) for p in parts)).cast("binary"))


def uniform(*parts: Column | str | int) -> Column:
    """In [0, 1), from the first 13 hex digits."""
    return F.conv(F.substring(key(*parts), 1, 13), 16, 10).cast("bigint") / F.lit(float(16**13))
