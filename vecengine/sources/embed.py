"""Texts and pages as vectors: a stand-in for a passage encoder that needs no model."""

from __future__ import annotations

import hashlib
import re
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_WORD = re.compile("[a-z]+").findall
_MEMO = 400_000


def hash_embed(texts: DataFrame, d: int, id_col: str, text_col: str) -> DataFrame:
    """(id, vec): unit vectors of signed counts of hashed words.

    A word's first seven hexadecimal digits of MD5 give its place, the eighth
    its sign. Texts without words, or whose counts cancel, have no vector. Each
    text is summed where it is: no shuffle.
    """
    def run(batches):
        known: dict[str, tuple[int, int]] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 1000):
                part = batch.slice(at, 1000)
                out = np.zeros((part.num_rows, d))
                for row, text in zip(out, part.column(1), strict=True):
                    for word, n in Counter(_WORD(text.as_py() or "")).items():
                        if word not in known:
                            if len(known) > _MEMO:
                                known.clear()
                            h = hashlib.md5(word.encode()).hexdigest()
                            known[word] = int(h[:7], 16) % d, 1 if h[7] < "8" else -1
                        place, sign = known[word]
                        row[place] += sign * n
                size = np.sqrt((out * out).sum(axis=1))
                some = size > 0
                vec = (out[some] / size[some, None]).ravel()
                yield pa.RecordBatch.from_arrays([part.column(0).filter(pa.array(some)), pa.ListArray.from_arrays(np.arange(0, len(vec) + 1, d, dtype=np.int32), pa.array(vec))], ["id", "vec"])

    slim = texts.select(F.col(id_col).alias("id"), F.lower(F.col(text_col)).alias("text"))
    return slim.mapInArrow(run, f"id {dict(slim.dtypes)['id']}, vec array<double>")


def page_text(html) -> Column:
    """Visible text of a page, spaces collapsed."""
    html = F.col(html) if isinstance(html, str) else html
    bare = F.regexp_replace(F.regexp_replace(html, "<(script|style)[^>]*>[^<]*</(script|style)>", " "), "<[^>]*>", " ")
    return F.trim(F.regexp_replace(bare, "[ \t\r\n]+", " "))
