"""Draws that depend on their keys only, so that they survive retries and can be repeated in any SQL engine."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def order(*keys: Column | str | int) -> Column:
    """A random but fixed order: the md5 digest of the keys."""
    return F.md5(F.concat_ws("|", *(k.cast("string") if isinstance(k, Column) else F.lit(str(k)) for k in keys)))


def uniform(*keys: Column | str | int) -> Column:
    """A number in [0, 1) from the first 32 bits of the digest."""
    return F.conv(F.substring(order(*keys), 1, 8), 16, 10).cast("double") / 4294967296.0
