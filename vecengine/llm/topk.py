"""Exact top-k by the threshold algorithm over sorted per-dimension lists.

Rows are dealt to blocks, each with one sorted list for each dimension. A first
block gives every query a score that its kth result has to reach; with it, the
other blocks are read from the ends of their lists only until no unseen row can
reach that score, and a block whose best values together cannot is not opened.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecengine.llm.common import small_batches, staged
from vecengine.llm.vector_rows import sound

#: Queries and rows that meet in one task: a block of integer vectors and its lists, some 30 MB at 64 dimensions.
QUERY_BLOCK, ROW_BLOCK, FIRST_DEPTH = 8192, 8192, 16
NONE = -(1 << 62)
FOUND = "query_id long, vec_id long, score long, seen long"


class SortedLists:
    """A block of integer vectors with one sorted list for each dimension."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray):
        by_id = np.argsort(ids, kind="stable")
        self.ids, self.v = ids[by_id], vectors[by_id]
        self.lists = np.argsort(self.v, axis=0, kind="stable")
        self.sorted = np.take_along_axis(self.v, self.lists, axis=0)
        self.largest = int(np.abs(self.v).max(initial=0))
        self.f = self.v.astype(np.float64) if self.largest < 1 << 24 else None

    def _scores(self, rows, q):
        # Sums below 2^53 are exact as doubles.
        if self.f is not None and self.largest * int(np.abs(q).max(initial=0)) * len(q) < 1 << 53:
            return (self.f[rows] @ q.astype(np.float64)).astype(np.int64)
        return self.v[rows] @ q

    def top(self, q: np.ndarray, k: int, own, least: int = NONE) -> tuple[np.ndarray, np.ndarray, int]:
        """Rows and scores of the k best that score ``least`` or more, ties to the smaller id, and rows seen.

        Reads the lists best end first, to a depth that doubles; in a step only
        those lists whose next values add most to the bound, half of it
        together. No row that is still unseen can score more than the bound
        made of the values at each list's depth; the search ends when the kth
        score, or ``least``, exceeds it.
        """
        n, dims = len(self.ids), np.flatnonzero(q)
        if not n:
            return np.empty(0, np.int64), np.empty(0, np.int64), 0
        if not len(dims):
            rows = np.flatnonzero(self.ids != own) if own is not None else np.arange(n)
            rows = rows[:k] if least <= 0 else rows[:0]
            return rows, np.zeros(len(rows), np.int64), n
        up = q[dims] > 0
        # What the list of each dimension adds to a score at a depth, counted from its best end.
        gains = lambda depth: self.sorted[np.where(up, n - 1 - depth, depth), dims] * q[dims]
        seen, depth = np.zeros(n, bool), np.zeros(len(dims), np.int64)
        rows, scores = np.empty(0, np.int64), np.empty(0, np.int64)
        step = FIRST_DEPTH
        while True:
            at = gains(np.minimum(depth, n - 1))
            kth = scores.min() if len(scores) == k else NONE
            if int(at.sum()) < max(least, kth) or (depth >= n).any():
                break
            # What a list can still lose over the next step, largest first.
            ahead = at - gains(np.minimum(depth + step, n - 1))
            first = np.argsort(-ahead, kind="stable")
            many = 1 + int(np.searchsorted(np.cumsum(ahead[first]), ahead.sum() / 2))
            new = np.zeros(n, bool)
            for j in first[:many]:
                low, high = depth[j], min(n, depth[j] + step)
                new[self.lists[n - high : n - low, dims[j]] if up[j] else self.lists[low:high, dims[j]]] = True
                depth[j] += step
            new &= ~seen
            seen |= new
            fresh = np.flatnonzero(new)
            fresh = fresh[self.ids[fresh] != own] if own is not None else fresh
            some = self._scores(fresh, q)
            good = some >= least
            rows, scores = np.concatenate((rows, fresh[good])), np.concatenate((scores, some[good]))
            if len(rows) > k:
                best = np.lexsort((rows, -scores))[:k]
                rows, scores = rows[best], scores[best]
            if seen.sum() * 2 > n:  # most rows are read: the rest in one go
                step = n
            step = min(n, step * 2)
        best = np.lexsort((rows, -scores))[:k]
        return rows[best], scores[best], int(seen.sum())


def threshold_topk(db: DataFrame, is_query, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 1024) -> DataFrame:
    """k best rows by integer inner product for each row that ``is_query`` names.

    Components become floor(scale * x). Returns (query_id, rank, vec_id,
    score). Rows with null ids and null, empty or non-finite vectors take no
    part; a query meets rows of its own length only. A row does not find rows of
    its own id; repeated candidates, and repeated queries, count as they are.
    Queries and rows meet block by block; what leaves a block is k rows a query
    at most. Components must stay below 2^31 / scale in size. An empty table
    gives an empty result.
    """
    found = topk_found(db, is_query, k, id_col, vec_col, scale)
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.where("vec_id is not null").withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def rows_seen(found: DataFrame) -> DataFrame:
    """(query_id, seen): rows of all blocks whose scores were worked out, from ``topk_found``."""
    return found.groupBy("query_id").agg(F.sum("seen").alias("seen"))


def topk_found(db: DataFrame, is_query, k: int = 10, id_col: str = "vec_id", vec_col: str = "embedding", scale: int = 1024) -> DataFrame:
    """(query_id, vec_id, score, seen): what the blocks found, and the rows that each saw (once a query and block)."""
    small_batches(db.sparkSession)
    slim = db.select(F.col(id_col).cast("long").alias("id"), F.col(vec_col).cast("array<double>").alias("vec"), F.coalesce(is_query, F.lit(False)).alias("asks"))
    ints = slim.where(sound("vec") & F.col("id").isNotNull()).select("id", "asks", F.transform("vec", lambda x: F.floor(x * scale).cast("long")).alias("v"))
    n, m = ints.agg(F.count("*"), F.count_if("asks")).first()
    row_blocks, query_blocks = max(1, -(-n // ROW_BLOCK)), max(1, -(-m // QUERY_BLOCK))
    spread = lambda lo, hi: F.explode(F.sequence(F.lit(lo), F.lit(hi)))
    block = lambda count, salt: F.pmod(F.xxhash64("id", F.lit(salt)), F.lit(count)).cast("int")
    rows = ints.select("id", "v", block(row_blocks, 1).alias("rb"))
    asks = ints.where("asks").select("id", "v", block(query_blocks, 2).alias("qb"), F.lit(None).cast("long").alias("least"))
    none = F.lit(None).cast("long")
    side = lambda df, asks, qb, rb, least: df.select("id", "v", F.lit(asks).alias("asks"), rb.alias("rb"), qb.alias("qb"), least.alias("least"))

    def met(first: int, last: int, queries: DataFrame) -> DataFrame:
        left = side(rows.where(F.col("rb").between(first, last)), False, spread(0, query_blocks - 1), F.col("rb"), none)
        right = side(queries, True, F.col("qb"), spread(first, last), F.col("least"))
        return left.union(right).groupBy("rb", "qb").applyInArrow(lambda t: _meet(t, k), FOUND)

    one = met(0, 0, asks)
    if row_blocks == 1:
        return one
    one = staged(one, "topk-first")
    rank = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    kth = one.where("vec_id is not null").withColumn("r", F.row_number().over(rank)).where(F.col("r") == k).select(F.col("query_id").alias("q"), F.col("score").alias("reach"))
    told = asks.join(kth, F.col("id") == F.col("q"), "left").select("id", "v", "qb", F.col("reach").alias("least"))
    return one.union(met(1, row_blocks - 1, told))


def _meet(t: pa.Table, k: int) -> pa.Table:
    asks = t.column("asks").to_numpy(zero_copy_only=False)
    t = t.append_column("d", pc.list_value_length(t.column("v")))
    out = [[], [], [], []]
    for d in pc.unique(t.filter(pa.array(asks)).column("d")).to_pylist():
        mine = t.filter(pc.equal(t.column("d"), d))
        flag = mine.column("asks").to_numpy(zero_copy_only=False)
        v = mine.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
        ids, least = mine.column("id").to_numpy(), mine.column("least").fill_null(NONE).to_numpy()
        lists = SortedLists(ids[~flag], v[~flag])
        for i in np.flatnonzero(flag):
            found, scores, seen = lists.top(v[i], k, ids[i], int(least[i]))
            size = max(1, len(found))
            out[0].append(np.full(size, ids[i]))
            # A block without results still tells what it saw.
            out[1].append(lists.ids[found].astype(object) if len(found) else np.array([None]))
            out[2].append(scores if len(found) else np.zeros(1, np.int64))
            out[3].append(np.concatenate(([seen], np.zeros(size - 1, np.int64))))
    flat = [np.concatenate(x) if x else np.empty(0, object) for x in out]
    return pa.table({n: pa.array(x.tolist(), pa.int64()) for n, x in zip(("query_id", "vec_id", "score", "seen"), flat, strict=True)})
