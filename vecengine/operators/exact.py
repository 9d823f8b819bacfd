"""Exact search: every query against every row, in blocks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Bytes of queries up to which every task gets all of them; beyond, they go in blocks.
BROADCAST_BYTES = 64 << 20
#: Answers (queries times k) that each task may give; more are found in a grid of blocks, where few tasks answer the same query.
ANSWERS = 1 << 18
#: Most queries and bytes of rows that meet in one task of the grid.
QUERY_BLOCK, ROW_BYTES = 8192, 32 << 20
#: Scores held at once, and vectors of finalists.
CELLS, FINALISTS = 1 << 21, 1 << 15
#: Rounding of a sum of products, for each component, as a share of the norms; generous.
EPS = 1e-14


def topk(df: DataFrame, k: int, part: str = "qid") -> DataFrame:
    """k best by (score, smaller id) of each part, as rank 1..k."""
    best = Window.partitionBy(part).orderBy(F.desc("score"), "id")
    return df.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)


def _block_best(ids: np.ndarray, x: np.ndarray, qids: np.ndarray, q: np.ndarray, k: int, kind: str):
    """k best by (score, smaller id) of each query among the rows of a block; few queries at a time, for all scores of a few are held."""
    fine = np.isfinite(x).all(axis=1)
    ids, x = (ids, x) if fine.all() else (ids[fine], x[fine])
    squares = (x * x).sum(1)
    largest, unit = squares.max(initial=0), x
    if kind == "cos":
        with np.errstate(invalid="ignore", divide="ignore"):
            unit = x / np.sqrt(squares)[:, None]
    out, few = [], max(1, CELLS // max(1, len(ids)))
    for at in range(0, len(q), few):
        part = q[at : at + few]
        own = (part * part).sum(1)
        with np.errstate(all="ignore"):
            # For distances the square without the query's own: it orders the rows alike.
            s = 2 * (part @ x.T) - squares if kind == "l2" else (part / np.sqrt(own)[:, None] if kind == "cos" else part) @ unit.T
            slack = EPS * part.shape[1] * (own + largest if kind == "l2" else np.maximum(1, np.sqrt(own * largest)) if kind == "ip" else np.ones(len(part)))
        out.append(_choose(ids, s, x.__getitem__, slack, qids[at : at + few], part, k, kind))
    return _joined(out, qids, ids)


def _joined(parts: list, qids: np.ndarray, ids: np.ndarray):
    a, b, c = zip(*parts, strict=True) if parts else ((), (), ())
    return np.concatenate([qids[:0], *a]), np.concatenate([ids[:0], *b]), np.concatenate([np.empty(0), *c])


def _in_order(terms: np.ndarray) -> np.ndarray:
    """Sums of rows from the first component to the last, as ``vectors.total`` adds; NumPy's own sum adds in another order."""
    total = np.zeros(len(terms))
    for column in np.ascontiguousarray(terms.T):
        total += column
    return total


def _exact(y: np.ndarray, q: np.ndarray, kind: str) -> np.ndarray:
    """Scores of pairs, to the last place those of ``vectors.sim`` for distances and products: rules that compare the two meet exact ties among copies."""
    if kind == "l2":
        return -np.sqrt(_in_order((y - q) ** 2))
    if kind == "ip":
        return _in_order(y * q)
    with np.errstate(invalid="ignore", divide="ignore"):
        return (y / np.linalg.norm(y, axis=1, keepdims=True) * (q / np.linalg.norm(q, axis=1, keepdims=True))).sum(axis=1)


def _near(s: np.ndarray, k: int, slack: np.ndarray):
    """(query places, row places, numbers) of all that are within ``slack`` of a query's kth best, in order of the queries."""
    m, n = s.shape
    with np.errstate(all="ignore"):
        odd = not np.isfinite(s.sum())
    if odd:
        s[~np.isfinite(s)] = -np.inf
    floor, some = np.full(m, -np.inf), min(n, max(4096, 4 * k))
    if n > k:
        # The kth best of some rows bounds that of all from below; it leaves few rows to order.
        floor = np.partition(s[:, :some], some - k, axis=1)[:, some - k] - slack
        floor[~np.isfinite(floor)] = -np.inf
    at, near = np.nonzero(s >= floor[:, None])
    got = s[at, near]
    if n > some and len(at):
        each = np.bincount(at, minlength=m)
        wide = np.full((m, max(k, each.max())), -np.inf)
        wide[at, _places(at, m)] = got
        last = wide.shape[1] - k
        keep = got >= (np.partition(wide, last, axis=1)[:, last] - slack)[at]
        at, near, got = at[keep], near[keep], got[keep]
    keep = got > -np.inf
    return at[keep], near[keep], got[keep]


def _places(at: np.ndarray, m: int) -> np.ndarray:
    """0, 1, 2.. within each run of equal numbers below m."""
    each = np.bincount(at, minlength=m)
    return np.arange(len(at)) - (np.cumsum(each) - each)[at]


def _ranked(ids: np.ndarray, qids: np.ndarray, at: np.ndarray, near: np.ndarray, score: np.ndarray, k: int):
    order = np.lexsort((ids[near], -score, at))
    at, near, score = at[order], near[order], score[order]
    keep = _places(at, len(qids)) < k
    return qids[at[keep]], ids[near[keep]], score[keep]


def _best_of(parts: list, k: int) -> tuple:
    """k best by (score, smaller id) of each query in lists of (qids, ids, scores)."""
    qids, ids, score = (np.concatenate(one) for one in zip(*parts, strict=True))
    order = np.lexsort((ids, -score, qids))
    qids, ids, score = qids[order], ids[order], score[order]
    keep = _places(np.unique(qids, return_inverse=True)[1], len(qids)) < k
    return qids[keep], ids[keep], score[keep]


def _choose(ids: np.ndarray, s: np.ndarray, rows, slack: np.ndarray, qids: np.ndarray, q: np.ndarray, k: int, kind: str):
    """The k best from (queries, rows) numbers ``s`` that order the rows of a query but for ``slack``; ``rows`` gives vectors of places.

    Every row within ``slack`` of the kth best, ties of any number too, is a
    candidate; only then the exact scores and the ids decide.
    """
    at, near, _ = _near(s, k, slack)
    exact = np.concatenate([np.empty(0), *(_exact(rows(near[i : i + FINALISTS]), q[at[i : i + FINALISTS]], kind) for i in range(0, len(at), FINALISTS))])
    keep = np.isfinite(exact)
    return _ranked(ids, qids, at[keep], near[keep], exact[keep], k)


def _matrix(column) -> np.ndarray:
    column = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), -1) if len(column) else np.empty((0, 0))


def exact_knn(db: DataFrame, q: DataFrame, k: int, kind: str = "l2") -> DataFrame:
    """(qid, rank, id, score): k best of every query, all rows compared.

    Queries are sent to all tasks while they and their answers are few (checked),
    and each task keeps k rows a query before anything is shuffled. More queries
    meet the rows in a grid of blocks of bounded sizes.
    """
    # Null vectors drop out behind the projections: a filter on ``vec`` would be pushed below them, with copies of all that makes it.
    rows = db.select(F.col("id").cast("long"), F.col("vec").cast("array<double>"))
    asks = q.select(F.col("qid").cast("long"), F.col("vec").cast("array<double>"))
    shape = asks.agg(F.count("vec").alias("m"), F.max(F.size("vec")).alias("d")).first()
    if not shape["m"]:
        return db.sparkSession.createDataFrame([], "qid long, rank int, id long, score double")
    if shape["m"] * shape["d"] * 8 <= BROADCAST_BYTES and shape["m"] * k <= ANSWERS:
        got = asks.toPandas().dropna()
        sent = db.sparkSession.sparkContext.broadcast((got["qid"].to_numpy(), np.stack(got["vec"].to_numpy())))

        def scan(batches):
            qids, qs = sent.value
            best = []
            for batch in batches:
                batch = batch.filter(batch.column(1).is_valid())
                for at in range(0, batch.num_rows, 8192):
                    part = batch.slice(at, 8192)
                    best.append(_block_best(part.column(0).to_numpy(), _matrix(part.column(1)), qids, qs, k, kind))
                    best = [_best_of(best, k)]
            for one in best:
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in one], ["qid", "id", "score"])

        found = rows.mapInArrow(scan, "qid long, id long, score double")
    else:
        # Enough blocks for all cores, if queries are not very few.
        cores = 2 * db.sparkSession.sparkContext.defaultParallelism
        blocks = max(-(-shape["m"] // QUERY_BLOCK), min(cores, -(-shape["m"] // 1024)))
        n_row_blocks = -(-max(1, rows.count()) * shape["d"] * 8 // ROW_BYTES)
        spread = lambda n: F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
        left = rows.select("id", "vec", F.lit(0).alias("side"), F.pmod(F.xxhash64("id"), F.lit(n_row_blocks)).alias("rb"), spread(blocks).alias("qb"))
        right = asks.select(F.col("qid").alias("id"), "vec", F.lit(1).alias("side"), spread(n_row_blocks).alias("rb"), F.pmod(F.xxhash64("qid"), F.lit(blocks)).alias("qb"))

        def meet(t: pa.Table) -> pa.Table:
            t = t.filter(t.column("vec").is_valid())
            side = t.column("side").to_numpy() == 0
            x, ids = _matrix(t.column("vec")), t.column("id").to_numpy()
            if not side.any() or side.all():
                return pa.table({"qid": pa.array([], pa.int64()), "id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
            a, b, c = _block_best(ids[side], x[side], ids[~side], x[~side], k, kind)
            return pa.table({"qid": a, "id": b, "score": c})

        found = left.union(right).groupBy("rb", "qb").applyInArrow(meet, "qid long, id long, score double")
    return topk(found, k).select("qid", "rank", "id", "score")


def coded_knn(codes: DataFrame, q: DataFrame, k: int, mean: list[float]) -> DataFrame:
    """(qid, rank, id, score) by distance from ``codes(id, codes, lo, step)``, two constants a row and nothing decoded but the finalists.

    With the query less the mean, a distance is the product of query and codes
    and sums of each side alone: those of a row are worked out once a batch,
    for all queries. Queries must be few enough to send to all tasks (checked).
    """
    asks = q.select(F.col("qid").cast("long"), F.col("vec").cast("array<double>"))
    shape = asks.agg(F.count("vec").alias("m"), F.max(F.size("vec")).alias("d")).first()
    if not shape["m"]:
        return codes.sparkSession.createDataFrame([], "qid long, rank int, id long, score double")
    blocks = max(1, -(-shape["m"] * shape["d"] * 8 // BROADCAST_BYTES))
    found = None
    for block in range(blocks):
        mine = asks if blocks == 1 else asks.where(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == block)
        one = _coded_scan(codes, mine, k, np.asarray(mean))
        found = one if found is None else found.union(one)
    return topk(found, k).select("qid", "rank", "id", "score")


def _coded_scan(codes: DataFrame, asks: DataFrame, k: int, mean: np.ndarray) -> DataFrame:
    got = asks.toPandas().dropna()
    sent = codes.sparkSession.sparkContext.broadcast((got["qid"].to_numpy(), np.stack(got["vec"].to_numpy()) - mean))

    def scan(batches):
        qids, qs = sent.value
        total, own = qs.sum(1), (qs * qs).sum(1)
        for batch in batches:
            batch = batch.filter(batch.column(1).is_valid())
            for at in range(0, batch.num_rows, 8192):
                part = batch.slice(at, 8192)
                ids, c = part.column(0).to_numpy(), _matrix(part.column(1))
                lo, step = part.column(2).to_numpy(), part.column(3).to_numpy()
                squares = c.shape[1] * lo * lo + 2 * lo * step * c.sum(1) + step * step * (c * c).sum(1)
                rows = lambda near, c=c, lo=lo, step=step: lo[near, None] + step[near, None] * c[near]
                few, out = max(1, CELLS // max(1, len(ids))), []
                for i in range(0, len(qs), few):
                    one = slice(i, i + few)
                    s = 2 * (total[one, None] * lo + (qs[one] @ c.T) * step) - squares
                    slack = EPS * c.shape[1] * (own[one] + squares.max(initial=0))
                    out.append(_choose(ids, s, rows, slack, qids[one], qs[one], k, "l2"))
                a, b, s = _joined(out, qids, ids)
                yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(s)], ["qid", "id", "score"])

    slim = codes.select(F.col("id").cast("long"), F.col("codes").cast("array<int>"), F.col("lo").cast("double"), F.col("step").cast("double"))
    return slim.mapInArrow(scan, "qid long, id long, score double")
