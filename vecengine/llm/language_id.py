"""Language identification by rank-order profiles of character n-grams."""

from __future__ import annotations

import sys
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

PROFILE = 400
UNKNOWN = "und"
#: An n-gram's code is its code points, 21 bits each; between words stands one space.
_BITS, _SPACE = 21, 32
#: Distinct n-grams that a task holds before it sums them up.
_PENDING = 4_000_000


@lru_cache(maxsize=1)
def _alphabet() -> np.ndarray:
    """Which code points are letters, of any script."""
    return np.fromiter((chr(c).isalpha() for c in range(sys.maxunicode + 1)), bool, sys.maxunicode + 1)


def letters(text: str) -> np.ndarray:
    """Code points of the lower-cased letters; whatever stands between words becomes one space."""
    points = np.frombuffer(text.lower().encode("utf-32-le", "replace"), "<u4").astype(np.int64)
    codes = np.where(_alphabet()[points], points, _SPACE)
    if not (codes != _SPACE).any():
        return codes[:0]
    codes = np.concatenate(([_SPACE], codes, [_SPACE]))
    return codes[(codes != _SPACE) | np.concatenate(([True], codes[:-1] != _SPACE))]


def ngrams(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-grams of one to three letters or spaces (no lone space) and how often each occurs; shorter ones have smaller codes."""
    c = letters(text)
    if not len(c):
        return c, c
    two = c[:-1] << _BITS | c[1:]
    return np.unique(np.concatenate((c[c != _SPACE], two, two[:-1] << _BITS | c[2:])), return_counts=True)


def _summed(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    codes, where = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
    return codes, np.bincount(where, np.concatenate([p[1] for p in parts]), len(codes)).astype(np.int64)


def _top(codes: np.ndarray, counts: np.ndarray, size: int) -> np.ndarray:
    """Most frequent first, ties by code."""
    if len(codes) > size:
        least = np.partition(counts, len(counts) - size)[len(counts) - size]
        keep = counts >= least
        codes, counts = codes[keep], counts[keep]
    return codes[np.argsort(-counts, kind="stable")][:size]


def profiles(train: DataFrame, text_col: str = "text", lang_col: str = "lang", size: int = PROFILE) -> dict[str, list[int]]:
    """Ranked n-grams of each language, counted over all of ``train``.

    Every task sums its own rows first, so that at most the distinct n-grams
    of a language leave it. What reaches the driver is ``size`` codes a
    language. Rows with null text or language do not count.
    """
    def count(batches):
        sums: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
        pending = 0
        for batch in batches:
            for text, lang in zip(batch.column(0), batch.column(1), strict=True):
                found = ngrams(text.as_py())
                sums.setdefault(lang.as_py(), []).append(found)
                pending += len(found[0])
            if pending > _PENDING:
                sums = {k: [_summed(v)] for k, v in sums.items()}
                pending = 0
        for lang, parts in sums.items():
            codes, counts = _summed(parts)
            for at in range(0, len(codes), 100_000):
                part = slice(at, at + 100_000)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(codes[part]), pa.string()), pa.array(codes[part]), pa.array(counts[part])], ["lang", "code", "n"])

    slim = train.select(F.col(text_col).cast("string").alias("text"), F.col(lang_col).cast("string").alias("lang")).where("text is not null and lang is not null")
    sums = slim.mapInArrow(count, "lang string, code long, n long").groupBy("lang", "code").agg(F.sum("n").alias("n"))
    ranked = sums.withColumn("r", F.row_number().over(Window.partitionBy("lang").orderBy(F.desc("n"), "code"))).where(F.col("r") <= size)
    out: dict[str, list[int]] = {}
    for row in ranked.orderBy("lang", "r").collect():
        out.setdefault(row["lang"], []).append(row["code"])
    return out


def identify(docs: DataFrame, known: dict[str, list[int]], id_col: str = "doc_id", text_col: str = "text", size: int = PROFILE, keep: tuple[str, ...] = ()) -> DataFrame:
    """Nearest profile of every whole text: (id, *keep, lang_pred, score).

    The distance is the sum, over the text's most frequent n-grams, of how far
    each is out of its place in the profile; one that the profile lacks costs
    ``size``. score is 1 minus the nearest distance over the sum of the two
    nearest (0.5 to 1; with one language 1; 0 for 'und'). Equal distances go to
    the smaller name. Null texts and texts without letters are 'und', as is
    everything if nothing was learnt. One row per input row.
    """
    names = sorted(known)
    table = [known[name] for name in names]

    def run(batches):
        every = np.unique(np.array([c for codes in table for c in codes], np.int64))
        place = np.full((len(names), len(every) + 1), size, np.int64)
        for row, codes in zip(place, table, strict=True):
            row[np.searchsorted(every, np.asarray(codes, np.int64))] = np.arange(len(codes))
        for batch in batches:
            pred, score = [], []
            for text in batch.column(batch.num_columns - 1):
                codes, counts = ngrams(text.as_py() or "")
                if not len(codes) or not names:
                    pred.append(UNKNOWN)
                    score.append(0.0)
                    continue
                mine = _top(codes, counts, size)
                at = np.minimum(np.searchsorted(every, mine), len(every) - 1)
                far = place[:, np.where(every[at] == mine, at, len(every))]
                far = np.where(far == size, size, np.abs(far - np.arange(len(mine)))).sum(axis=1)
                order = np.argsort(far, kind="stable")
                best, second = far[order[0]], far[order[1]] if len(names) > 1 else size * len(mine)
                pred.append(names[order[0]])
                score.append(1.0 if len(names) == 1 else float(1 - best / (best + second)) if best + second else 0.5)
            cols = [batch.column(i) for i in range(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(pred, pa.string()), pa.array(score, pa.float64())], [*batch.schema.names[:-1], "lang_pred", "score"])

    slim = docs.select(F.col(id_col), *keep, F.col(text_col).cast("string").alias("__text"))
    kinds = ", ".join(f"`{n}` {t}" for n, t in slim.dtypes[:-1])
    return slim.mapInArrow(run, f"{kinds}, lang_pred string, score double")
