"""Data-set statistics that codes depend on."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.functions import quantize
from vecengine.functions.vectors import center


def mean_rows(db: DataFrame, vec: str = "vec") -> DataFrame:
    """(j, mu): means of all components as exact decimal sums, whatever the order of rows."""
    cells = db.select(F.posexplode(vec).alias("j", "x"))
    s = F.sum(F.col("x").cast("decimal(38,15)"))
    return cells.groupBy("j").agg(F.round(s.cast("double") / F.count("*"), 12).alias("mu"))


def dataset_mean(db: DataFrame, vec: str = "vec") -> list[float]:
    """Mean vector to 12 digits; each task sums its own rows, so d numbers leave it, not n * d, and d doubles reach the driver.

    Null vectors do not count. For few components of a wide range, where sums of
    doubles lose digits, ``mean_rows`` is exact.
    """

    def sums(batches):
        acc, n = [], 0
        for batch in batches:
            x = batch.column(0).drop_null()
            if len(x):
                acc.append(x.flatten().to_numpy(zero_copy_only=False).reshape(len(x), -1).sum(axis=0))
                n += len(x)
        if n:
            total = [math.fsum(column) for column in zip(*acc, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(total)), pa.int32()), pa.array(total), pa.array([n] * len(total), pa.int64())], ["j", "s", "n"])

    parts = db.select(F.col(vec).cast("array<double>")).mapInArrow(sums, "j int, s double, n long")
    return [r["mu"] for r in parts.groupBy("j").agg(F.round(F.sum("s") / F.sum("n"), 12).alias("mu")).orderBy("j").collect()]


def global_bounds(centered: DataFrame, vec: str = "vec") -> tuple[float, float]:
    row = centered.agg(F.min(F.array_min(vec)).alias("lo"), F.max(F.array_max(vec)).alias("hi")).first()
    return row["lo"], row["hi"]


def dim_bounds(centered: DataFrame, vec: str = "vec") -> tuple[list[float], list[float]]:
    rows = centered.select(F.posexplode(vec).alias("j", "x")).groupBy("j").agg(F.min("x").alias("lo"), F.max("x").alias("hi")).orderBy("j").collect()
    return [r["lo"] for r in rows], [r["hi"] for r in rows]


def centered(db: DataFrame, mean: list[float]) -> DataFrame:
    return db.withColumn("vec", center("vec", mean))


def encode(db: DataFrame, codec: str, mean: list[float] | None = None) -> DataFrame:
    """(.., vec := decoded components + mean) by the codec's name.

    pv8, pv4x8, gl4, gl4x4, pd4, lp8, f16, f32, fp8e4 or fp8e5. Names follow the
    number of bits of each level.
    """
    if codec == "f32":
        return db
    if codec == "lp8":
        # One symmetric scale for all, nothing centered: an approximation of low-precision integer schemes.
        scale = db.agg(F.max(F.array_max(F.transform("vec", F.abs)))).first()[0] / 127.0
        return db.withColumn("vec", F.transform("vec", lambda x: F.floor(x / scale + 0.5) * F.lit(scale)))
    if codec == "f16":
        return db.withColumn("vec", F.transform("vec", quantize.half_round))
    if codec in ("fp8e4", "fp8e5"):
        e = int(codec[-1])
        return db.withColumn("vec", F.transform("vec", lambda x: quantize.fp8_round(x, e, 7 - e)))
    mean = dataset_mean(db) if mean is None else mean
    kind, bits = codec[:2], [int(b) for b in codec[2:].split("x")]
    c = centered(db, mean)
    if kind == "pd":
        lows, highs = dim_bounds(c)
        c = c.withColumn("vec", quantize.per_dim_decode(quantize.per_dim_codes("vec", bits[0], lows, highs), bits[0], lows, highs))
    else:
        if kind == "gl":
            lo, hi = global_bounds(c)
            c = c.withColumn("q", quantize.global_q("vec", bits[0], lo, hi))
        else:
            c = c.withColumn("q", quantize.pvq("vec", bits[0]))
        if len(bits) == 2:
            c = c.withColumn("r", quantize.residual_codes("vec", "q", bits[1])).withColumn("vec", quantize.decode2("q", "r", bits[1])).drop("r")
        else:
            c = c.withColumn("vec", quantize.decode("q"))
        c = c.drop("q")
    return c.withColumn("vec", center("vec", [-m for m in mean]))
