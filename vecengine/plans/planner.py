"""Which method and which parameters."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.operators import measures, shard

#: Rows up to which an exhaustive scan is chosen, and rows of a shard.
SCAN_ROWS, SHARD_ROWS = 20_000, 1_000_000
#: Bytes of the largest array of a shard: it is one cell of a row, and a task holds a few of them.
SHARD_BYTES = 512 << 20


@dataclass(frozen=True)
class SearchSpec:
    method: str
    codec: str
    degree: int
    window: int
    alphas: tuple[float, ...]
    shards: int
    filter_first: bool


def defaults(n: int, kind: str = "l2") -> tuple[int, tuple[float, ...]]:
    """Degree by the size of the data; the second pass relaxes above 1 for distances, below it for inner products."""
    degree = 32 if n <= 1_000_000 else 64 if n <= 100_000_000 else 128
    return degree, (1.0, 0.95) if kind == "ip" else (1.0, 1.2)


def shards(n: int, d: int, rows: int = SHARD_ROWS) -> int:
    """Shards of n rows of d components."""
    return max(1, -(-n // max(1, min(rows, SHARD_BYTES // (4 * max(1, d))))))


def deal(db: DataFrame, n: int, d: int, rows: int = SHARD_ROWS) -> DataFrame:
    """``db`` with its rows dealt evenly, by hash, to as many shards as it needs."""
    return db.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards(n, d, rows))).cast("int"))


def plan(n: int, d: int, kind: str = "l2", memory_bytes: int | None = None, selectivity: float = 1.0) -> SearchSpec:
    """Scan small or strongly filtered data; else a graph, with two levels if memory and dimension favour it."""
    degree, alphas = defaults(n, kind)
    if n * selectivity <= SCAN_ROWS:
        return SearchSpec("scan", "f32", 0, 0, (), 1, True)
    two = d >= 256 and (memory_bytes is None or memory_bytes >= n * (1.5 * d + 4 * degree))
    return SearchSpec("graph", "pv4x8" if two else "pv8", degree, 2 * degree, alphas, shards(n, d), selectivity < 0.05)


def choose_window(index: DataFrame, q: DataFrame, truth: DataFrame, target: float, k: int = 10, most: int = 512) -> DataFrame:
    """(window, recall, chosen) of each try: doubling up to the target, then halving the interval; none is chosen if ``most`` does not reach it.

    ``index`` is read by every try, so it should be a stored table. With fewer
    shards than cores, several tasks share the queries of a shard.
    """
    tried: dict[int, float] = {}
    cores = q.sparkSession.sparkContext.defaultParallelism
    parts = max(1, min(-(-q.count() // shard.QUERY_BATCH), -(-cores // max(1, index.select("shard").count()))))

    def recall(w: int) -> float:
        if w not in tried:
            tried[w] = measures.recall(shard.search_index(index, q, k, w, parts=parts), truth, k).first()["recall"]
        return tried[w]

    high = k
    while recall(high) < target and high < most:
        high *= 2
    low = high // 2
    while high - low > 2 and low >= k:
        middle = (low + high) // 2
        low, high = (low, middle) if recall(middle) >= target else (middle, high)
    rows = [(w, float(r), w == high and r >= target) for w, r in sorted(tried.items())]
    return q.sparkSession.createDataFrame(rows, "window int, recall double, chosen boolean").withColumn("recall", F.round("recall", 6))
