"""Scalar quantizers as expressions.

Per-vector bounds (pv): each centered vector is coded between its own smallest
and largest component. Contrast cases take one pair of bounds for all (gl) or a
pair for each dimension (pd). A second level codes what rounding left over.
Every level has 2^bits values, the nearest one wins, and halves go up.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from vecengine.functions.vectors import col, let, total


def scalar_code(x, bits: int, lo, hi) -> Column:
    """Code of one value; values out of bounds clip, equal bounds give 0."""
    step = (col(hi) - col(lo)) / F.lit(float(2**bits - 1))
    raw = F.floor((col(x) - col(lo)) / step + 0.5)
    return F.when(step > 0, F.greatest(F.lit(0), F.least(F.lit(2**bits - 1), raw))).otherwise(0).cast("int")


def scalar_decode(code, lo, step) -> Column:
    return col(lo) + col(step) * col(code).cast("double")


def half_round(x) -> Column:
    """Nearest half-precision value as a double, ties to even (subnormals too); beyond its range, infinity."""
    x = col(x)
    size = F.abs(x)
    exponent = F.greatest(F.floor(F.log2(size)), F.lit(-14))
    # log2 may be off by one at a power of two.
    exponent = F.when(F.pow(F.lit(2.0), exponent) > size, F.greatest(exponent - 1, F.lit(-14))).otherwise(exponent)
    unit = F.pow(F.lit(2.0), exponent - 10)
    near = F.rint(size / unit) * unit
    shown = F.when(near >= 65520.0, F.lit(float("inf"))).otherwise(near)
    return F.when(size == 0, x).otherwise(F.when(x < 0, -shown).otherwise(shown))


def fp8_round(x, exp_bits: int = 4, man_bits: int = 3) -> Column:
    """Nearest 8-bit float of the given split, ties to even, clipped to the largest finite value."""
    x = col(x)
    size, bias = F.abs(x), 2 ** (exp_bits - 1) - 1
    low = 1 - bias
    exponent = F.greatest(F.floor(F.log2(size)), F.lit(low))
    exponent = F.when(F.pow(F.lit(2.0), exponent) > size, F.greatest(exponent - 1, F.lit(low))).otherwise(exponent)
    unit = F.pow(F.lit(2.0), exponent - man_bits)
    top = float(2.0 ** (2**exp_bits - 2 - bias) * (2 - 2.0**-man_bits))
    near = F.least(F.rint(size / unit) * unit, F.lit(top))
    return F.when(size == 0, x).otherwise(F.when(x < 0, -near).otherwise(near))


def _codes(vec, lo: Column, step: Column, bits: int) -> Column:
    top = 2**bits - 1

    def one(x):
        return F.when(step > 0, F.greatest(F.lit(0), F.least(F.lit(top), F.floor((x - lo) / step + 0.5)))).otherwise(0).cast("int")

    return F.transform(col(vec), one)


def pvq(vec, bits: int, const: str = "f64") -> Column:
    """struct(codes, lo, step) of a centered vector, bounds its own.

    const 'f16' rounds the stored constants to half precision first; codes use
    the rounded ones, and components outside them clip.
    """
    lo, hi = F.array_min(col(vec)), F.array_max(col(vec))
    if const == "f16":
        lo, hi = half_round(lo), half_round(hi)
    bounds = F.struct(lo.alias("lo"), ((hi - lo) / F.lit(float(2**bits - 1))).alias("step"))
    return let(bounds, lambda b: F.struct(_codes(vec, b["lo"], b["step"], bits).alias("codes"), b["lo"].alias("lo"), b["step"].alias("step")))


def global_q(vec, bits: int, lo: float, hi: float) -> Column:
    """The same with one pair of bounds for the whole data set."""
    lo_, step = F.lit(float(lo)), F.lit((float(hi) - float(lo)) / (2**bits - 1))
    return F.struct(_codes(vec, lo_, step, bits).alias("codes"), lo_.alias("lo"), step.alias("step"))


def per_dim_codes(vec, bits: int, lows: list[float], highs: list[float]) -> Column:
    """Codes with bounds for each dimension."""
    top = 2**bits - 1
    bounds = F.array(*(F.struct(F.lit(float(a)).alias("lo"), F.lit((float(b) - float(a)) / top).alias("step")) for a, b in zip(lows, highs, strict=True)))
    return F.zip_with(col(vec), bounds, lambda x, b: F.when(b["step"] > 0, F.greatest(F.lit(0), F.least(F.lit(top), F.floor((x - b["lo"]) / b["step"] + 0.5)))).otherwise(0).cast("int"))


def per_dim_decode(codes, bits: int, lows: list[float], highs: list[float]) -> Column:
    top = 2**bits - 1
    bounds = F.array(*(F.struct(F.lit(float(a)).alias("lo"), F.lit((float(b) - float(a)) / top).alias("step")) for a, b in zip(lows, highs, strict=True)))
    return F.zip_with(col(codes), bounds, lambda c, b: b["lo"] + b["step"] * c.cast("double"))


def decode(q) -> Column:
    """Components of a struct(codes, lo, step)."""
    q = col(q)
    return F.transform(q["codes"], lambda c: q["lo"] + q["step"] * c.cast("double"))


def residual_codes(vec, q, bits2: int) -> Column:
    """Second level: what the first left over, in -step/2..step/2, in bits2 bits."""
    q = col(q)
    top = 2**bits2 - 1
    step2 = q["step"] / F.lit(float(top))

    def one(x, c):
        left = x - (q["lo"] + q["step"] * c.cast("double"))
        return F.when(step2 > 0, F.greatest(F.lit(0), F.least(F.lit(top), F.floor((left + q["step"] / 2) / step2 + 0.5)))).otherwise(0).cast("int")

    return F.zip_with(col(vec), q["codes"], one)


def decode2(q, codes2, bits2: int) -> Column:
    """Both levels together."""
    q = col(q)
    step2 = q["step"] / F.lit(float(2**bits2 - 1))
    return F.zip_with(q["codes"], col(codes2), lambda c, r: (q["lo"] + q["step"] * c.cast("double")) + (r.cast("double") * step2 - q["step"] / 2))


def asym_score(query, q, mean: list[float], kind: str = "l2") -> Column:
    """Score of a raw query against a code without decoding it.

    Uses sums of codes and the two constants only. For distances the mean is
    taken from the query; for the inner product its product with the query is
    added. Cosine works on unit vectors.
    """
    q = col(q)
    codes = F.transform(q["codes"], lambda c: c.cast("double"))
    if kind == "l2":
        shifted = F.zip_with(col(query), F.array(*(F.lit(float(m)) for m in mean)), lambda x, m: x - m - q["lo"])
        own = total(F.transform(shifted, lambda x: x * x))
        cross = total(F.zip_with(shifted, codes, lambda x, c: x * c))
        squares = total(F.transform(codes, lambda c: c * c))
        return -F.sqrt(F.greatest(F.lit(0.0), own - 2 * q["step"] * cross + q["step"] * q["step"] * squares))
    base = total(F.zip_with(col(query), F.array(*(F.lit(float(m)) for m in mean)), lambda x, m: x * m))
    cross = total(F.zip_with(col(query), codes, lambda x, c: x * c))
    return base + q["lo"] * total(col(query)) + q["step"] * cross
