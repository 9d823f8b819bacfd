"""Similarities and reshaping of array<double> vectors, all inside the JVM.

Scores grow with closeness: negative Euclidean distance, inner product, or
cosine. Sums run from the first component to the last, so that results do not
depend on how rows are spread.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

KINDS = ("l2", "ip", "cos")


def col(c) -> Column:
    return F.col(c) if isinstance(c, str) else c


def let(value: Column, body) -> Column:
    """``body`` of a value that is worked out once, also if a lambda inside uses it often."""
    return F.transform(F.array(value), body)[0]


def total(arr) -> Column:
    """Left-to-right sum of an array<double>."""
    return F.aggregate(col(arr), F.lit(0.0), lambda s, x: s + x)


def dot(a, b) -> Column:
    return total(F.zip_with(col(a), col(b), lambda x, y: x * y))


def sq_l2(a, b) -> Column:
    return total(F.zip_with(col(a), col(b), lambda x, y: (x - y) * (x - y)))


def norm(a) -> Column:
    return F.sqrt(total(F.transform(col(a), lambda x: x * x)))


def sim(a, b, kind: str = "l2") -> Column:
    """Score of two vectors; the cosine of a zero vector is null."""
    if kind == "l2":
        return -F.sqrt(sq_l2(a, b))
    if kind == "ip":
        return dot(a, b)
    if kind == "cos":
        size = norm(a) * norm(b)
        return F.when(size > 0, dot(a, b) / size)
    raise ValueError(f"kind must be one of {KINDS}")


def normalize(a) -> Column:
    """Unit length; null for the zero vector, which has no direction."""
    return let(F.struct(col(a).alias("a"), norm(a).alias("n")), lambda v: F.when(v["n"] > 0, F.transform(v["a"], lambda x: x / v["n"])))


def prefix(a, d: int) -> Column:
    return F.slice(col(a), 1, d)


def center(a, mean: list[float]) -> Column:
    mu = F.array(*(F.lit(float(m)) for m in mean))
    return F.zip_with(col(a), mu, lambda x, m: x - m)


def validate(df: DataFrame, d: int, vec: str = "vec") -> DataFrame:
    """Rows that can be indexed: d components, none null, NaN or infinite."""
    bad = F.exists(vec, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return df.where(F.coalesce((F.size(vec) == d) & ~bad, F.lit(False)))


def dimension(df: DataFrame, vec: str = "vec") -> int:
    """Dimension of the first vector; 0 for an empty table."""
    first = df.where(F.col(vec).isNotNull()).select(F.size(vec).alias("d")).first()
    return first["d"] if first else 0
