"""Which rows of a vector table take part."""

from __future__ import annotations

from pyspark.sql import functions as F


def sound(vec: str):
    """Not null or empty, without null or non-finite components."""
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return F.coalesce((F.size(vec) > 0) & ~bad, F.lit(False))
