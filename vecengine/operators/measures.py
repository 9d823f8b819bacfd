"""Accuracy measures and summaries of experiment results."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def recall(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """k-recall@k averaged over the queries of the truth: one row (recall).

    With fewer than k rows in the data set, the truth has as many as there are.
    """
    hits = truth.where(F.col("rank") <= k).select("qid", "id").join(found.where(F.col("rank") <= k).select("qid", "id").withColumn("hit", F.lit(1)), ["qid", "id"], "left")
    return hits.agg((F.count("hit") / F.count("*")).alias("recall"))


def rbo(a: DataFrame, b: DataFrame, depth: int, p: float = 0.98) -> DataFrame:
    """Rank-biased overlap of two ranked lists for each query: (qid, rbo, rbo_ext).

    rbo is the sum up to ``depth``; rbo_ext takes the agreement at that depth
    to hold beyond it. An id counts from the larger of its two ranks on.
    """
    both = a.select("qid", "id", F.col("rank").alias("ra")).join(b.select("qid", "id", F.col("rank").alias("rb")), ["qid", "id"])
    meets = both.select("qid", F.greatest("ra", "rb").alias("r")).where(F.col("r") <= depth).groupBy("qid", "r").agg(F.count("*").alias("n"))
    # A common id that is known from rank r on adds p^(s-1)/s at each depth s >= r.
    tails, tail = [0.0] * (depth + 2), 0.0
    for s in range(depth, 0, -1):
        tail += p ** (s - 1) / s
        tails[s] = tail
    weight = F.array(*(F.lit((1 - p) * tails[r]) for r in range(1, depth + 1)))
    sums = meets.groupBy("qid").agg(F.sum(F.col("n") * weight[F.col("r") - 1]).alias("rbo"), F.sum("n").alias("common"))
    every = a.select("qid").distinct().join(sums, "qid", "left")
    return every.select("qid", F.coalesce("rbo", F.lit(0.0)).alias("rbo"), (F.coalesce("rbo", F.lit(0.0)) + F.coalesce("common", F.lit(0)) / depth * F.lit(p**depth)).alias("rbo_ext"))


def pareto(results: DataFrame, group: str = "method") -> DataFrame:
    """Settings that no other of their group beats in both recall and queries per second; equal ones stay together."""
    best = Window.partitionBy(group).orderBy(F.desc("recall")).rangeBetween(Window.unboundedPreceding, Window.currentRow)
    own = F.struct("qps", "recall")
    return results.withColumn("best", F.max(own).over(best)).where(own == F.col("best")).drop("best")


def qps_at(results: DataFrame, target: float = 0.9, group: str = "method") -> DataFrame:
    """Queries per second at a recall, on the line between the two settings around it."""
    w = Window.partitionBy(group).orderBy("recall")
    front = pareto(results, group).dropDuplicates([group, "recall", "qps"]).withColumn("r2", F.lead("recall").over(w)).withColumn("q2", F.lead("qps").over(w))
    at = F.when(F.col("recall") == target, F.col("qps")).otherwise(F.col("qps") + (F.col("q2") - F.col("qps")) * (target - F.col("recall")) / (F.col("r2") - F.col("recall")))
    around = (F.col("recall") == target) | ((F.col("recall") < target) & (F.col("r2") > target))
    return front.where(around).select(group, at.alias("qps"))


def geomean(df: DataFrame, value: str, *by: str) -> DataFrame:
    return df.groupBy(*by).agg(F.exp(F.avg(F.log(value))).alias("geomean"))


def histogram(df: DataFrame, value: str, lo: float, hi: float, bins: int) -> DataFrame:
    """(bin, n); values out of range go to the outer bins."""
    b = F.floor((F.col(value) - lo) / ((hi - lo) / bins))
    return df.select(F.greatest(F.lit(0), F.least(F.lit(bins - 1), b)).cast("int").alias("bin")).groupBy("bin").agg(F.count("*").alias("n"))
