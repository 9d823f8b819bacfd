"""From raw documents to packed training sequences, in four stages.

Each stage takes (spark, docs, sf_dir), and all but the last return the
columns of documents. ``run`` applies them one after the other; each result
is written as Parquet to the shared folder and read again.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecengine.llm import bpe, ngram_join, packing, quality, toxicity
from vecengine.llm.common import staged, table
from vecengine.llm.registry import RANKS


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a toxicity score below 0.5."""
    model = toxicity.fit(docs, table(spark, sf_dir, "labels"))
    rest = tuple(c for c in docs.columns if c != "doc_id")
    scored = toxicity.score(docs, model, keep=rest, out="__toxic")
    return scored.where(F.col("__toxic") < 0.5).select(*docs.columns)


def drop_poor(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents with a quality score of 0.3 or more."""
    model = quality.fit(docs, table(spark, sf_dir, "labels"))
    rest = tuple(c for c in docs.columns if c != "doc_id")
    scored = quality.score(docs, model, keep=rest, out="__quality")
    return scored.where(F.col("__quality") >= 0.3).select(*docs.columns)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by five-word shingles at a similarity of 0.8."""
    return ngram_join.keep_one(docs, 5, 80, 100).select(*docs.columns)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents in bins of the permitted lengths, counted in tokens."""
    return packing.best_fit(bpe.lengths(docs, public_tokenizers.path(RANKS)), length_col="length")


STAGES = [("toxicity", drop_toxic), ("quality", drop_poor), ("ngram_jaccard", drop_near_copies), ("packing", pack)]
#: The stages learn models and follow links without bound, which SQL cannot express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = staged(docs, f"pipeline-{name}")
    return docs
