"""Randomness that any engine repeats: fractions and buckets from md5."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: 8 hex digits of md5 as an integer stand for a fraction of this.
SPAN = 1 << 32


def hash_int(*parts: Column | str) -> Column:
    """The first 8 hex digits of md5 over the parts, colon-joined, as a bigint."""
    text = F.concat_ws(":", *(F.lit(p) if isinstance(p, str) else p.cast("string") for p in parts))
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("bigint")


def hash_below(share: float, *parts: Column | str) -> Column:
    """True for about `share` of all values of parts, always the same ones."""
    return hash_int(*parts) < int(share * SPAN)
