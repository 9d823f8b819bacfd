"""SQL names, Arrow functions and table functions."""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecengine.functions.pack import pack_bits


def register(spark: SparkSession) -> None:
    """vec_l2, vec_ip, vec_cos and pvq_codes as SQL functions; pvq_pack and vec_mean as Arrow ones; pvq_cells and best_of as table functions."""
    fold = lambda e: f"aggregate({e}, 0D, (s, x) -> s + x)"
    ip = lambda a, b: fold(f"zip_with({a}, {b}, (x, y) -> x * y)")
    for name, body in (
        ("vec_l2", f"sqrt({fold('zip_with(a, b, (x, y) -> (x - y) * (x - y))')})"),
        ("vec_ip", ip("a", "b")),
        ("vec_cos", f"try_divide({ip('a', 'b')}, sqrt({ip('a', 'a')}) * sqrt({ip('b', 'b')}))"),
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN {body}")
    bound = "least(top, floor((x - array_min(v)) / ((array_max(v) - array_min(v)) / top) + 0.5))"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION pvq_codes(v ARRAY<DOUBLE>, top INT) RETURNS ARRAY<INT> RETURN transform(v, x -> CASE WHEN array_max(v) > array_min(v) THEN cast({bound} AS INT) ELSE 0 END)")
    spark.udtf.register("pvq_cells", PvqCells)
    spark.udtf.register("best_of", BestOf)
    spark.udf.register("pvq_pack", pvq_pack)
    spark.udf.register("vec_mean", vec_mean)


@F.pandas_udf(T.StructType([T.StructField("code", T.BinaryType()), T.StructField("lo", T.DoubleType()), T.StructField("step", T.DoubleType())]))
def pvq_pack(vec: pd.Series, bits: pd.Series) -> pd.DataFrame:
    """Centered vectors as packed codes and their constants."""
    out = pd.DataFrame({"code": None, "lo": np.nan, "step": np.nan}, index=vec.index).astype({"code": object})
    # Rows of one length and width are coded as one matrix.
    for (d, b), mine in vec.groupby([vec.map(lambda v: -1 if v is None else len(v)), bits]):
        if d < 1:
            continue
        x = np.stack(mine.to_numpy()).astype(float)
        lo, step = x.min(axis=1), (x.max(axis=1) - x.min(axis=1)) / (2**b - 1)
        safe = np.where(step > 0, step, 1.0)[:, None]
        code = np.where(step[:, None] > 0, np.clip(np.floor((x - lo[:, None]) / safe + 0.5), 0, 2**b - 1), 0).astype(int)
        out.loc[mine.index, "code"] = pd.Series([pack_bits(c, int(b)) for c in code], index=mine.index, dtype=object)
        out.loc[mine.index, "lo"], out.loc[mine.index, "step"] = lo, step
    return out


@F.pandas_udf(T.ArrayType(T.DoubleType()))
def vec_mean(vec: pd.Series) -> list[float]:
    """Mean of the vectors of a group. It has no partial step: sum by task first where groups are large."""
    return np.stack(vec.to_numpy()).mean(axis=0).tolist()


@F.udtf(returnType="j int, code int, approx double")
class PvqCells:
    """Table function: a row for each component of a centered vector, with its code and what that stands for."""

    def eval(self, vec: list, bits: int):
        if not vec:
            return
        lo, step = min(vec), (max(vec) - min(vec)) / (2**bits - 1)
        for j, x in enumerate(vec):
            code = max(0, min(2**bits - 1, int((x - lo) / step + 0.5))) if step > 0 else 0
            yield j, code, lo + step * code


@F.udtf(returnType="id long, score double")
class BestOf:
    """Table function over a table argument: the k best (id, score) of its partition, ties to the smaller id."""

    def __init__(self):
        self.best: list[tuple[float, int]] = []
        self.k = 0

    def eval(self, row: Row, k: int):
        self.k = k
        heapq.heappush(self.best, (row["score"], -row["id"]))
        if len(self.best) > k:
            heapq.heappop(self.best)

    def terminate(self):
        for score, i in sorted(self.best, reverse=True):
            yield -i, score
