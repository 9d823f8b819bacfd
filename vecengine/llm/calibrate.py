"""Labelled folds and a small logistic calibrator, shared by the classifiers."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.llm.common import crc_mod, staged

#: Rows of labels up to which they are broadcast (about 64 bytes each in a hashed relation); beyond, the
#: texts of the asked folds are shuffled by id instead, with the same result.
BROADCAST_ROWS = 4_000_000
#: At most so many labelled rows fit a calibrator.
CALIBRATION_ROWS = 20_000


def judged(labels: DataFrame, label: str, where, id_col: str = "doc_id") -> DataFrame:
    """(id, y): null labels and ids drop out; of conflicting labels of an id the larger counts."""
    rows = labels.select(F.col(id_col).cast("long").alias("id"), F.col(label).cast("int").alias("y"))
    return rows.where("id is not null and y is not null").where(where).groupBy("id").agg(F.max("y").alias("y"))


def labelled(docs: DataFrame, labels: DataFrame, label: str, where, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, text, y) of all labelled documents for which ``where`` (of ``id``) holds.

    Labels go to the documents while they are few (checked); beyond, the
    documents that ``where`` admits are shuffled to the labels.
    """
    ys = judged(labels, label, where, id_col)
    if ys.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS:
        ys = F.broadcast(ys)
    return docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).where(where).join(ys, "id")


def sampled(docs: DataFrame, labels: DataFrame, label: str, where, n: int, each: bool = False, most_bytes: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, y, text) of at most ``n`` labelled documents (``each``: of each label), those of the smallest hashed ids.

    Ids are chosen first, from ids, labels and hashes of texts alone; only the
    chosen rows' texts move, so what is gathered is bounded at any size. With
    ``most_bytes``, empty texts and longer ones are not chosen. Of the texts of
    a repeated id one is.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text")).where(where)
    rows = rows.where(F.octet_length("text").between(1, most_bytes)) if most_bytes else rows
    hashed = rows.select("id", F.xxhash64("text").alias("h"), "text")
    known = hashed.groupBy("id").agg(F.min("h").alias("h")).join(judged(labels, label, where, id_col), "id")
    order = [F.xxhash64("id"), F.col("id")]
    pick = lambda df: df.orderBy(*order).limit(n)
    chosen = pick(known.where("y > 0")).union(pick(known.where("y <= 0"))) if each else pick(known)
    chosen = staged(chosen, "sample-ids")
    texts = hashed.join(F.broadcast(chosen), ["id", "h"])
    return texts.groupBy("id", "y").agg(F.first("text").alias("text"))


def fold(*rests: int, mod: int = 5):
    return crc_mod("id", mod).isin(*rests)


def held_out(id_col: str = "doc_id", mod: int = 5):
    return F.coalesce(crc_mod(id_col, mod) == 0, F.lit(False))


class Logistic:
    """Ridge-damped logistic regression on a few standardized features."""

    def __init__(self, x, y, l2: float = 1e-3, weight_ones: float = 1.0, steps: int = 60, unknown: float = 0.0):
        """With ones or zeros only, that is the answer; without rows, ``unknown``."""
        y = np.asarray(y, float)
        self.constant = None
        if not len(y) or y.min() == y.max():
            self.constant = float(y[0]) if len(y) else unknown
            return
        x = np.asarray(x, float).reshape(len(y), -1)
        self.mean, self.scale = x.mean(0), x.std(0) + 1e-9
        z = np.column_stack([np.ones(len(x)), (x - self.mean) / self.scale])
        w, weight = np.zeros(z.shape[1]), np.where(y > 0, weight_ones, 1.0)
        for _ in range(steps):
            p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
            grad = z.T @ (weight * (p - y)) / len(y) + l2 * w
            hess = (z * (weight * p * (1 - p))[:, None]).T @ z / len(y) + (l2 + 1e-9) * np.eye(len(w))
            step = np.linalg.solve(hess, grad)
            w = w - step * min(1.0, 4 / (1e-12 + np.abs(step).max()))
            if np.abs(step).max() < 1e-8:
                break
        self.w = w

    def __call__(self, x) -> np.ndarray:
        x = np.asarray(x, float)
        if self.constant is not None:
            return np.full(len(x), self.constant)
        z = self.w[0] + ((x - self.mean) / self.scale) @ self.w[1:]
        return 1 / (1 + np.exp(-np.clip(z, -30, 30)))
