"""Quality by compression with zstandard dictionaries of good and bad text."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecengine.llm.calibrate import CALIBRATION_ROWS, Logistic, fold, held_out, sampled
from vecengine.llm.common import small_batches

#: Labelled rows of each class, and bytes of each, from which a dictionary is built.
DICTIONARY_ROWS, DICTIONARY_ROW_BYTES = 4_000, 1 << 16
DICTIONARY_BYTES, BLOCK, LEVEL = 110_000, 4096, 3


@dataclass
class Model:
    good: bytes
    bad: bytes
    calibrator: Logistic | None = None

    def compressors(self):
        made = []
        for data in (self.good, self.bad, b""):
            known = zstandard.ZstdCompressionDict(data) if data else None
            if known:
                known.precompute_compress(level=LEVEL)
            made.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=known, write_content_size=False, write_checksum=False, write_dict_id=False).compress)
        return made


def features(compressors, text: str | None) -> tuple[float, float, float]:
    """Normalised size difference, and the sizes with the good dictionary and with none per byte.

    The whole text goes in blocks, so that a long text does not become its own dictionary.
    """
    raw = (text or "").encode("utf-8", "replace")
    if not raw:
        return 0.0, 1.0, 1.0
    good, bad, none = (sum(len(c(raw[i : i + BLOCK])) for i in range(0, len(raw), BLOCK)) for c in compressors)
    return (bad - good) / (bad + good), good / len(raw), none / len(raw)


def _dictionary(texts: list[str]) -> bytes:
    blocks = [raw[i : i + BLOCK] for raw in (t.encode("utf-8", "replace") for t in texts) for i in range(0, len(raw), BLOCK)]
    if len(blocks) >= 50:
        try:
            return zstandard.train_dictionary(DICTIONARY_BYTES, blocks, level=LEVEL).as_bytes()
        except zstandard.ZstdError:  # too little text
            pass
    return b"".join(blocks)[-DICTIONARY_BYTES:]


def _featured(model: Model, keep: list[str]):
    def run(batches):
        compressors = model.compressors()
        for batch in batches:
            found = np.array([features(compressors, t.as_py()) for t in batch.column("text")]).reshape(-1, 3)
            yield pa.RecordBatch.from_arrays([*(batch.column(k) for k in keep), *(pa.array(found[:, i]) for i in range(3))], [*keep, "a", "b", "c"])

    return run


def _inputs(found: np.ndarray) -> np.ndarray:
    """Both ratios also squared: text may compress too well as well as too badly."""
    return np.column_stack([found, found[:, 0] ** 2, found[:, 1] ** 2, found[:, 0] * found[:, 1]])


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label: str = "quality") -> Model:
    """Dictionaries from folds 1 and 2, calibration on folds 3 and 4 (crc32(id) mod 5).

    Both use bounded samples: DICTIONARY_ROWS rows of each class of at most
    DICTIONARY_ROW_BYTES bytes, and CALIBRATION_ROWS rows.
    """
    small_batches(docs.sparkSession)
    chosen = sampled(docs, labels, label, fold(1, 2), DICTIONARY_ROWS, True, DICTIONARY_ROW_BYTES, id_col, text_col).toPandas()
    chosen = chosen.sort_values("id")
    model = Model(_dictionary(chosen.text[chosen.y > 0].tolist()), _dictionary(chosen.text[chosen.y <= 0].tolist()))
    sample = sampled(docs, labels, label, fold(3, 4), CALIBRATION_ROWS, id_col=id_col, text_col=text_col)
    got = sample.select("y", "text").mapInArrow(_featured(model, ["y"]), "y int, a double, b double, c double").toPandas()
    model.calibrator = Logistic(_inputs(got[["a", "b", "c"]].to_numpy().reshape(-1, 3)), got["y"].to_numpy(), unknown=1.0)
    return model


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = (), out: str = "score") -> DataFrame:
    """(id, *keep, score) of every whole text, one row per input row; narrow.

    Null and empty texts count as incompressible with no difference. With
    labels of one class only, every score is that class; without labels it is 1:
    nothing is known against a text.
    """
    small_batches(docs.sparkSession)
    # A text that is kept anyway goes to Python once.
    kept = text_col in keep and dict(docs.dtypes)[text_col] == "string"
    slim = docs.select(F.col(id_col), *keep) if kept else docs.select(F.col(id_col), *keep, F.col(text_col).cast("string").alias("__text"))
    width = len(keep) + 1
    at = 1 + keep.index(text_col) if kept else width

    def run(batches):
        compressors = model.compressors()
        for batch in batches:
            found = np.array([features(compressors, t.as_py()) for t in batch.column(at)]).reshape(-1, 3)
            cols = [batch.column(i) for i in range(width)]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(model.calibrator(_inputs(found)))], [*batch.schema.names[:width], out])

    kinds = ", ".join(f"`{n}` {t}" for n, t in slim.dtypes[:width])
    return slim.mapInArrow(run, f"{kinds}, `{out}` double")


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) of all documents."""
    model = fit(docs, labels)
    scored = score(docs.select("doc_id", held_out().alias("held_out"), "text"), model, keep=("held_out",))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
