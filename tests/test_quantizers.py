import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from vecengine.functions import pack, quantize
from vecengine.functions.vectors import normalize, validate


def one(spark, vec, *cols):
    return spark.createDataFrame([(vec,)], "vec array<double>").select(*cols).first()


def test_worked_example_of_both_levels(spark):
    vec = [-1.0, 0.0, 0.5, 1.0]
    row = spark.createDataFrame([(vec,)], "vec array<double>").withColumn("q", quantize.pvq("vec", 2)).withColumn("r", quantize.residual_codes("vec", "q", 2)).select("q", quantize.decode("q").alias("d"), "r").first()
    assert row["q"]["codes"] == [0, 2, 2, 3]
    assert np.allclose(row["d"], [-1, 1 / 3, 1 / 3, 1])
    assert row["r"] == [2, 0, 2, 2]


def test_equal_components_have_step_zero(spark):
    q = one(spark, [0.3, 0.3, 0.3], quantize.pvq("vec", 8).alias("q"))["q"]
    assert q["codes"] == [0, 0, 0] and q["step"] == 0


@pytest.mark.parametrize("bits", [1, 2, 3, 4, 5, 8])
def test_rounding_error_is_at_most_half_a_step_and_extremes_are_exact(spark, bits):
    rng = np.random.default_rng(bits)
    df = spark.createDataFrame([(rng.normal(size=24).tolist(),) for _ in range(20)], "vec array<double>").withColumn("q", quantize.pvq("vec", bits))
    for r in df.select("vec", "q", quantize.decode("q").alias("d")).collect():
        err = np.abs(np.array(r["vec"]) - r["d"])
        assert err.max() <= r["q"]["step"] / 2 + 1e-12
        assert err[np.argmin(r["vec"])] < 1e-12 and err[np.argmax(r["vec"])] < 1e-12
        assert min(r["q"]["codes"]) >= 0 and max(r["q"]["codes"]) <= 2**bits - 1


@pytest.mark.parametrize("bits", range(1, 17))
def test_packing_round_trip(bits):
    codes = np.random.default_rng(bits).integers(0, 2**bits, 37)
    data = pack.pack_bits(codes, bits)
    assert len(data) == math.ceil(37 * bits / 8)
    assert (pack.unpack_bits(data, bits, 37) == codes).all()


def test_packed_bytes_agree_between_expression_and_kernel(spark):
    codes = [1, 15, 7, 0, 9]
    row = spark.createDataFrame([(codes,)], "c array<int>").select(pack.pack("c", 4).alias("four"), pack.pack("c", 8).alias("eight")).first()
    assert bytes(row["four"]) == pack.pack_bits(np.array(codes), 4) and bytes(row["eight"]) == bytes(codes)


def test_half_precision_agrees_with_numpy(spark):
    x = [0.0, 1.0, -0.1, 3.14159, 1e-5, 6e-8, 65519.0, 1 / 3, -2.5e-4]
    got = [r[0] for r in spark.createDataFrame([(v,) for v in x], "x double").select(quantize.half_round("x")).collect()]
    assert got == np.array(x).astype(np.float16).astype(float).tolist()


def test_published_footprints(spark):
    f = lambda *a: spark.range(1).select(pack.footprint(*a)).first()[0]
    assert f(96, 4, 32, 8) == 160 and f(200, 4, 32, 4) == 228 and f(768, 4, 32, 8) == 1184
    assert round(96 * 4 / f(96, 8, 0), 2) == 3.84 and round(768 * 4 / f(768, 8, 0), 2) == 3.98


def test_zero_vector_has_no_direction_and_bad_rows_are_refused(spark):
    assert one(spark, [0.0, 0.0], normalize("vec").alias("n"))["n"] is None
    df = spark.createDataFrame([([1.0, 2.0],), ([1.0, None],), ([float("nan"), 1.0],), ([1.0],), (None,)], "vec array<double>")
    assert validate(df, 2).count() == 1
    assert df.where(F.col("vec").isNull()).count() == 1
