"""Why a graph may be built from codes: the rounding error of the pruning rule."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecengine.functions import quantize
from vecengine.functions.vectors import sq_l2
from vecengine.operators.exact import _in_order, _matrix
from vecengine.operators.graph import knn_candidates

#: A rational approximation of the error function (absolute error below 1.5e-7).
ERF_P = 0.3275911
ERF_A = (0.254829592, -0.284496736, 1.421413741, -1.453152027, 1.061405429)


def erf(x) -> Column:
    a = F.abs(x)
    t = 1 / (1 + F.lit(ERF_P) * a)
    poly = F.lit(0.0)
    for c in reversed(ERF_A):
        poly = (poly + F.lit(c)) * t
    y = 1 - poly * F.exp(-a * a)
    return F.when(x < 0, -y).otherwise(y)


def triplets(db: DataFrame, kappa: int = 20, each: int = 8) -> DataFrame:
    """(x, xs, xp): xs among the kappa neighbours of x, xp farther from x than xs.

    Chosen by arithmetic on ids and ranks, so every engine takes the same.
    """
    near = knn_candidates(db, kappa).select("src", "rank", "id")
    s = near.where(F.col("rank") % 5 == F.col("src") % 5).select(F.col("src").alias("x"), F.col("rank").alias("rs"), F.col("id").alias("xs"))
    p = near.select(F.col("src").alias("x"), F.col("rank").alias("rp"), F.col("id").alias("xp"))
    chosen = s.join(p, "x").where("rp > rs").where((F.col("rp") + F.col("rs") + F.col("x")) % each == 0)
    return chosen.select("x", "xs", "xp")


def with_vectors(t: DataFrame, db: DataFrame) -> DataFrame:
    """Triplets with their three vectors as vx, vs, vp."""
    for key, name in (("x", "vx"), ("xs", "vs"), ("xp", "vp")):
        t = t.join(db.select(F.col("id").alias(key), F.col("vec").alias(name)), key)
    return t


def rule_margin(x, xs, xp) -> Column:
    """Half the difference of the squared distances x'-x* and x'-x: negative means 'prune' at alpha 1."""
    return (sq_l2(xs, xp) - sq_l2(x, xp)) / 2


def coded_triplets(db: DataFrame, t: DataFrame, bits: int, kind: str = "pv", mean=None) -> DataFrame:
    """Triplets with exact and decoded margins, the error of the margin, and the steps."""
    from vecengine.operators import model

    mean = model.dataset_mean(db) if mean is None else mean
    c = model.centered(db, mean)
    if kind == "pv":
        c = c.withColumn("q", quantize.pvq("vec", bits))
    else:
        lo, hi = model.global_bounds(c)
        c = c.withColumn("q", quantize.global_q("vec", bits, lo, hi))
    c = c.select("id", F.struct("vec", quantize.decode("q").alias("dec"), F.col("q.step").alias("step")).alias("vec"))
    w = with_vectors(t, c)
    exact = rule_margin("vx.vec", "vs.vec", "vp.vec")
    coded = rule_margin("vx.dec", "vs.dec", "vp.dec")
    return w.select(
        "x", "xs", "xp", exact.alias("margin"), coded.alias("coded"), F.size("vx.vec").alias("d"),
        F.col("vx.step").alias("step_x"), F.col("vs.step").alias("step_s"), F.col("vp.step").alias("step_p"),
        sq_l2("vx.vec", "vs.vec").alias("xs2"), sq_l2("vx.vec", "vp.vec").alias("xp2"), sq_l2("vs.vec", "vp.vec").alias("sp2"),
    ).withColumn("error", F.col("coded") - F.col("margin"))


def coded_margins(db: DataFrame, t: DataFrame, cases: list[tuple[str, int]], mean=None) -> DataFrame:
    """(margin, coded0, coded1, ..): exact margins of triplets, and those from the codes of each case (kind, bits of at most 8).

    Vectors are encoded once and fetched once for all cases: a code takes a byte
    on the way, so that a row with the codes of all cases is not much larger
    than its vector, and is decoded where the margins are.
    """
    from vecengine.operators import model

    mean = model.dataset_mean(db) if mean is None else mean
    c = model.centered(db, mean)
    bounds = model.global_bounds(c) if any(kind != "pv" for kind, _ in cases) else ()
    names = [f"q{i}" for i in range(len(cases))]
    for name, (kind, bits) in zip(names, cases, strict=True):
        c = c.withColumn(name, quantize.pvq("vec", bits) if kind == "pv" else quantize.global_q("vec", bits, *bounds))
    slim = [F.struct(F.transform(F.col(n)["codes"], lambda x: (x - 128).cast("tinyint")).alias("codes"), F.col(n)["lo"].alias("lo"), F.col(n)["step"].alias("step")).alias(n) for n in names]
    w = with_vectors(t, c.select("id", F.struct("vec", *slim).alias("vec"))).select("vx", "vs", "vp")

    def decoded(q: pa.StructArray) -> np.ndarray:
        lo, step = (q.field(name).to_numpy(zero_copy_only=False)[:, None] for name in ("lo", "step"))
        return lo + step * (_matrix(q.field("codes")) + 128)

    def margin(x: np.ndarray, xs: np.ndarray, xp: np.ndarray) -> np.ndarray:
        return (_in_order((xs - xp) ** 2) - _in_order((x - xp) ** 2)) / 2

    def margins(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                sides = batch.slice(at, 4096).columns
                out = [margin(*(_matrix(v.field("vec")) for v in sides))]
                out += [margin(*(decoded(v.field(name)) for v in sides)) for name in names]
                yield pa.RecordBatch.from_arrays([pa.array(o) for o in out], ["margin", *columns])

    columns = [f"coded{i}" for i in range(len(cases))]
    return w.mapInArrow(margins, ", ".join(f"{n} double" for n in ("margin", *columns)))


def error_moments(t: DataFrame) -> DataFrame:
    """Adds the mean and variance of the error that uniform rounding errors imply."""
    d = F.col("d")
    sx, ss, sp = (F.col(c) * F.col(c) for c in ("step_x", "step_s", "step_p"))
    mean = d / 24 * (ss - sx)
    var = (sp * F.col("xs2") + ss * F.col("sp2") + sx * F.col("xp2")) / 12 + d * (sx * sx + ss * ss) / 720 + d * sp * (sx + ss) / 144
    return t.withColumn("mu", mean).withColumn("var", var)


def folded_normal(mu, sigma) -> tuple[Column, Column]:
    """Mean and variance of the absolute value of a normal variable."""
    phi = 0.5 * (1 + erf(-mu / sigma / F.lit(math.sqrt(2))))
    mean = sigma * F.lit(math.sqrt(2 / math.pi)) * F.exp(-mu * mu / (2 * sigma * sigma)) + mu * (1 - 2 * phi)
    return mean, mu * mu + sigma * sigma - mean * mean
