"""Product quantization, with learned rotation, and with score-aware loss.

Codebooks are fitted on a bounded sample on the driver; encoding and scanning
run over all rows in Arrow batches.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.operators.exact import BROADCAST_BYTES, CELLS, _joined, _near, _ranked, topk
from vecengine.sources.io import staged

#: Rows at most that fit a codebook.
TRAIN_ROWS = 50_000


def sample(db: DataFrame, rows: int = TRAIN_ROWS) -> np.ndarray:
    """At most ``rows`` vectors, the same ones each time."""
    got = db.orderBy(F.xxhash64("id"), "id").limit(rows).select("vec").toPandas()["vec"]
    return np.stack(got.to_numpy()).astype(np.float64)


def lloyd(x: np.ndarray, k: int, iters: int = 12, seed: int = 7) -> np.ndarray:
    """k-means on the driver; empty clusters restart at the worst served rows."""
    rng = np.random.default_rng(seed)
    c = x[rng.choice(len(x), k, replace=len(x) < k)].copy()
    for _ in range(iters):
        near, least = _served(x, c)
        n = np.bincount(near, minlength=k)
        sums = np.stack([np.bincount(near, x[:, j], k) for j in range(x.shape[1])], axis=1)
        c = np.where(n[:, None] > 0, sums / np.maximum(n, 1)[:, None], c)
        if (n == 0).any():
            c[n == 0] = x[np.argsort(-least)[: int((n == 0).sum())]]
    return c


def _served(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Nearest centroid of each row, and the square of its distance; some rows at a time."""
    near, least, some = np.empty(len(x), np.int64), np.empty(len(x)), max(1, CELLS // len(c))
    for at in range(0, len(x), some):
        part = x[at : at + some]
        far = (part * part).sum(1)[:, None] - 2 * part @ c.T + (c * c).sum(1)
        near[at : at + some], least[at : at + some] = far.argmin(1), far.min(1)
    return near, least


def distributed_lloyd(db: DataFrame, k: int, iters: int = 8, seed: int = 7) -> np.ndarray:
    """k-means over all rows: centroids go out, sums of each task come back."""
    c = lloyd(sample(db, max(k * 50, 1000)), k, 4, seed)
    for _ in range(iters):
        sent = db.sparkSession.sparkContext.broadcast(c)

        def sums(batches, sent=sent):
            n, s = np.zeros(k, np.int64), np.zeros(sent.value.shape)
            for batch in batches:
                if batch.num_rows:
                    x = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                    near = nearest(x, sent.value)
                    np.add.at(s, near, x)
                    n += np.bincount(near, minlength=k)
            yield pa.RecordBatch.from_arrays([pa.array(np.arange(k), pa.int32()), pa.array(n), pa.array(s.tolist(), pa.list_(pa.float64()))], ["c", "n", "s"])

        cells = db.select(F.col("vec").cast("array<double>")).mapInArrow(sums, "c int, n long, s array<double>").select("c", "n", F.posexplode("s").alias("j", "x"))
        got = cells.groupBy("c", "j").agg(F.sum("n").alias("n"), F.sum("x").alias("x")).toPandas()
        n, s = np.zeros(k), np.zeros_like(c)
        n[got["c"]] = got["n"]
        s[got["c"], got["j"]] = got["x"]
        c = np.where(n[:, None] > 0, s / np.maximum(n, 1)[:, None], c)
    return c


def nearest(x: np.ndarray, c: np.ndarray, many: int = 1) -> np.ndarray:
    some, out = max(1, CELLS // len(c)), []
    for at in range(0, max(1, len(x)), some):
        far = (c * c).sum(1) - 2 * x[at : at + some] @ c.T
        out.append(far.argmin(1) if many == 1 else np.argsort(far, axis=1, kind="stable")[:, :many])
    return np.concatenate(out)


@dataclass
class Pq:
    """Codebooks (segments, centroids, width) and an optional rotation."""

    books: np.ndarray
    turn: np.ndarray | None = None
    eta: float = 1.0

    @property
    def segments(self) -> int:
        return len(self.books)

    def _split(self, x: np.ndarray) -> np.ndarray:
        x = x if self.turn is None else x @ self.turn
        width = self.books.shape[2]
        pad = self.segments * width - x.shape[1]
        return np.pad(x, ((0, 0), (0, pad))).reshape(len(x), self.segments, width)

    def encode(self, x: np.ndarray) -> np.ndarray:
        parts = self._split(x)
        out = np.empty((len(x), self.segments), np.uint8)
        for s in range(self.segments):
            out[:, s] = _assign(parts[:, s], self.books[s], self.eta)
        return out

    def decode(self, codes: np.ndarray) -> np.ndarray:
        parts = np.concatenate([self.books[s][codes[:, s]] for s in range(self.segments)], axis=1)
        return parts if self.turn is None else parts[:, : len(self.turn)] @ self.turn.T

    def table(self, q: np.ndarray, kind: str = "l2") -> np.ndarray:
        """(queries, segments, centroids): what each centroid adds to the score."""
        parts = self._split(q)[:, :, None, :]
        return (parts * self.books).sum(3) if kind == "ip" else -((parts - self.books) ** 2).sum(3)


def _assign(x: np.ndarray, book: np.ndarray, eta: float) -> np.ndarray:
    if eta == 1.0:
        return nearest(x, book)
    # An error along the vector costs eta times one across it.
    left = x[:, None, :] - book
    along = np.einsum("nkd,nd->nk", left, x) ** 2 / np.maximum((x * x).sum(1), 1e-12)[:, None]
    return ((left**2).sum(2) + (eta - 1) * along).argmin(1)


def train(x: np.ndarray, segments: int, k: int = 256, rotate: int = 0, eta: float = 1.0, seed: int = 7) -> Pq:
    """Codebooks by k-means a segment; ``rotate`` rounds of rotation by orthogonal Procrustes; ``eta`` above 1 weighs parallel errors."""
    width, k = -(-x.shape[1] // segments), min(k, 256, len(x))
    pq = Pq(np.zeros((segments, k, width)), None, eta)
    if rotate:
        pq.turn = np.eye(x.shape[1])
    for turn in range(rotate + 1):
        parts = pq._split(x)
        pq.books = np.stack([lloyd(parts[:, s], k, 12 if not rotate else 5, seed + s) for s in range(segments)])
        if eta != 1.0:
            for s in range(segments):
                pq.books[s] = _weighted(parts[:, s], pq.books[s], eta)
        if turn < rotate:
            coded = np.concatenate([pq.books[s][nearest(parts[:, s], pq.books[s])] for s in range(segments)], axis=1)[:, : x.shape[1]]
            u, _, v = np.linalg.svd(x.T @ coded)
            pq.turn = u @ v
    return pq


def _weighted(x: np.ndarray, book: np.ndarray, eta: float, iters: int = 5) -> np.ndarray:
    book = book.copy()
    unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
    weight = np.eye(x.shape[1]) + (eta - 1) * unit[:, :, None] * unit[:, None, :]
    for _ in range(iters):
        near = _assign(x, book, eta)
        for c in np.unique(near):
            mine = near == c
            a, b = weight[mine].sum(0), np.einsum("nij,nj->i", weight[mine], x[mine])
            book[c] = np.linalg.solve(a + 1e-9 * np.eye(len(a)), b)
    return book


def encode_frame(db: DataFrame, pq: Pq, *keep: str) -> DataFrame:
    """(.., id, code): one byte for each segment."""
    sent = db.sparkSession.sparkContext.broadcast(pq)

    def run(batches):
        for batch in batches:
            x = batch.column(batch.num_columns - 1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1) if batch.num_rows else np.empty((0, 1))
            codes = sent.value.encode(x) if len(x) else []
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(batch.num_columns - 1)), pa.array([c.tobytes() for c in codes], pa.binary())], [*batch.schema.names[:-1], "code"])

    slim = db.select(*keep, "id", F.col("vec").cast("array<double>"))
    kinds = ", ".join(f"{n} {t}" for n, t in slim.dtypes[:-1])
    return slim.mapInArrow(run, f"{kinds}, code binary")


def score_aware_eta(threshold: float, d: int) -> float:
    """What an error along the vector costs against one across it, where only products above ``threshold`` (of unit vectors) matter."""
    return (d - 1) * threshold**2 / (1 - threshold**2)


def scan(codes: DataFrame, pq: Pq, q: DataFrame, k: int, kind: str = "l2") -> DataFrame:
    """(qid, rank, id, score) by table look-up over all codes; look-up tables go out in blocks of a bounded size."""
    m = q.count()
    blocks = max(1, -(-m * pq.books.shape[0] * pq.books.shape[1] * 8 // BROADCAST_BYTES))
    # Each block is run at once, so that its tables need not stay.
    parts = [_scan(codes, pq, q if blocks == 1 else q.where(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == b), k, kind) for b in range(blocks)]
    return topk(reduce(DataFrame.union, parts), k).select("qid", "rank", "id", "score")


def _scan(codes: DataFrame, pq: Pq, q: DataFrame, k: int, kind: str) -> DataFrame:
    got = q.toPandas()
    if not len(got):
        return codes.sparkSession.createDataFrame([], "qid long, id long, score double")
    table = pq.table(np.stack(got["vec"].to_numpy()), kind)
    # Queries last: what a centroid adds to the scores of some queries stands together.
    sent = codes.sparkSession.sparkContext.broadcast((got["qid"].to_numpy(), np.ascontiguousarray(table.transpose(1, 2, 0))))

    def run(batches):
        qids, table = sent.value
        for batch in batches:
            if not batch.num_rows:
                continue
            ids = batch.column(0).to_numpy()
            c = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint8).reshape(len(ids), -1)
            few, out = max(1, CELLS // len(ids)), []
            for at in range(0, len(qids), few):
                s = np.zeros((len(ids), len(qids[at : at + few])))
                for j in range(c.shape[1]):
                    s += np.ascontiguousarray(table[j, :, at : at + few])[c[:, j]]
                s = np.ascontiguousarray(s.T)
                out.append(_ranked(ids, qids[at : at + few], *_near(s, k, np.zeros(len(s))), k))
            a, b, score = _joined(out, qids, ids)
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(score)], ["qid", "id", "score"])

    found = staged(codes.select("id", "code").mapInArrow(run, "qid long, id long, score double"), "scanned")
    sent.destroy()
    return found


@dataclass
class Ivf:
    """Cells by coarse centroids; rows of a cell stand together, coded or plain."""

    cells: np.ndarray
    pq: Pq | None
    rows: DataFrame


def ivf_build(db: DataFrame, nlist: int, pq: Pq | None = None, centroids: np.ndarray | None = None) -> Ivf:
    c = distributed_lloyd(db, nlist) if centroids is None else centroids
    sent = db.sparkSession.sparkContext.broadcast((c, pq))

    def run(batches):
        cells, pq_ = sent.value
        for batch in batches:
            if batch.num_rows:
                x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                data = x.astype(np.float64) if pq_ is None else pq_.encode(x)
                yield pa.RecordBatch.from_arrays([pa.array(nearest(x, cells).astype(np.int32)), batch.column(0), pa.array([d.tobytes() for d in data], pa.binary())], ["cell", "id", "code"])

    rows = db.select("id", F.col("vec").cast("array<double>")).mapInArrow(run, "cell int, id long, code binary")
    return Ivf(c, pq, staged(rows.repartition("cell"), "ivf"))


def ivf_search(index: Ivf, q: DataFrame, k: int, nprobe: int, kind: str = "l2") -> DataFrame:
    """(qid, rank, id, score): each query meets the rows of its nprobe nearest cells only."""
    spark = q.sparkSession
    sent = spark.sparkContext.broadcast((index.cells, index.pq))

    def route(batches):
        for batch in batches:
            if batch.num_rows:
                x = batch.column(1).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                near = nearest(x, sent.value[0], nprobe).reshape(len(x), -1)
                at = np.repeat(np.arange(len(x)), near.shape[1])
                yield pa.RecordBatch.from_arrays([pa.array(near.ravel().astype(np.int32)), batch.column(0).take(pa.array(at)), batch.column(1).take(pa.array(at))], ["cell", "qid", "vec"])

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows or not right.num_rows:
            return pa.table({"qid": pa.array([], pa.int64()), "id": pa.array([], pa.int64()), "score": pa.array([], pa.float64())})
        qids, ids = left.column("qid").to_numpy(), right.column("id").to_numpy()
        x = left.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(qids), -1)
        raw = b"".join(right.column("code").to_pylist())
        if sent.value[1] is None:
            y = np.frombuffer(raw).reshape(len(ids), -1)
            s = x @ y.T if kind == "ip" else -(((x[:, None, :] - y) ** 2).sum(2))
        else:
            c, table = np.frombuffer(raw, np.uint8).reshape(len(ids), -1), sent.value[1].table(x, kind)
            s = sum(table[:, j, c[:, j]] for j in range(c.shape[1]))
        best = np.lexsort((np.broadcast_to(ids, s.shape), -s), axis=1)[:, :k]
        return pa.table({"qid": np.repeat(qids, best.shape[1]), "id": ids[best].ravel(), "score": np.take_along_axis(s, best, 1).ravel()})

    probes = q.select(F.col("qid").cast("long"), F.col("vec").cast("array<double>")).mapInArrow(route, "cell int, qid long, vec array<double>")
    found = probes.groupBy("cell").cogroup(index.rows.groupBy("cell")).applyInArrow(meet, "qid long, id long, score double")
    return topk(found, k).select("qid", "rank", "id", "score")


def rerank(found: DataFrame, db: DataFrame, q: DataFrame, k: int, kind: str = "l2") -> DataFrame:
    """Shortlists scored again by the full vectors."""
    from vecengine.functions.vectors import sim

    both = found.select("qid", "id").join(db.select("id", "vec"), "id").join(q.select("qid", F.col("vec").alias("qvec")), "qid")
    return topk(both.select("qid", "id", sim("qvec", "vec", kind).alias("score")), k).select("qid", "rank", "id", "score")


def pca(x: np.ndarray, m: int) -> tuple[np.ndarray, np.ndarray]:
    """Mean and the m leading directions of a sample."""
    mean = x.mean(axis=0)
    _, vectors = np.linalg.eigh(np.cov((x - mean).T))
    return mean, vectors[:, ::-1][:, :m]
