"""Queries of this package and, where SQL can express them, their SQL."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import functions as F

from vecengine.llm import bpe, language_id, near_vectors, ngram_join, oracles, packing, quality, sharding, token_counts, topk, toxicity
from vecengine.llm.common import crc_mod, table

TOKENIZER, RANKS = "byte_bpe_50k.json", "byte_bpe_50k.tiktoken"


def op3_bpe_encode_decode(spark, sf_dir):
    return bpe.encode_decode(table(spark, sf_dir, "documents"), public_tokenizers.path(TOKENIZER), digests=True)


def op8_token_counts(spark, sf_dir):
    """Two edits to each document: one replacement and one insertion, placed by its id."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    n = F.coalesce(F.length("text"), F.lit(0)) + 1
    at = F.crc32(F.col("doc_id").cast("string"))
    edits = F.array(
        F.struct((at % n).cast("int").alias("at"), F.lit(12).alias("del"), F.lit(" [edited] ").alias("ins")),
        F.struct((at * 7 % n).cast("int").alias("at"), F.lit(0).alias("del"), F.lit("'ll see\n\n").alias("ins")),
    )
    return token_counts.count_tokens(docs.withColumn("edits", edits), public_tokenizers.path(TOKENIZER), "edits")


def op2_language_id(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    held_out = F.coalesce(crc_mod("doc_id", 4) == 2, F.lit(False))
    known = language_id.profiles(docs.where(~held_out & F.col("lang").isNotNull()))
    return language_id.identify(docs.select("doc_id", held_out.alias("held_out"), "text"), known, keep=("held_out",))


def op4_toxicity(spark, sf_dir):
    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op9_quality(spark, sf_dir):
    return quality.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_sharding(spark, sf_dir):
    return sharding.balanced_shards(table(spark, sf_dir, "documents"))


def op10_best_fit_packing(spark, sf_dir):
    return packing.best_fit(bpe.lengths(table(spark, sf_dir, "documents"), public_tokenizers.path(RANKS)), length_col="length")


def op6_embedding_near_dedup(spark, sf_dir):
    return near_vectors.near_vectors(table(spark, sf_dir, "embeddings"))


def op7_exact_topk(spark, sf_dir):
    return topk.threshold_topk(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


def op1_ngram_jaccard_join(spark, sf_dir):
    return ngram_join.jaccard_components(table(spark, sf_dir, "documents"), 3, 90, 100)


QUERIES = {f.__name__: f for f in (op1_ngram_jaccard_join, op2_language_id, op3_bpe_encode_decode, op4_toxicity, op5_sharding, op6_embedding_near_dedup, op7_exact_topk, op8_token_counts, op9_quality, op10_best_fit_packing)}
ORACLE_SQL: dict[str, str] = {
    "op1_ngram_jaccard_join": oracles.ngram_join(3, 90, 100),
    "op2_language_id": oracles.language_id(language_id.PROFILE),
    "op6_embedding_near_dedup": oracles.near_vectors(0.95),
    "op7_exact_topk": oracles.topk(10, 1024),
}
