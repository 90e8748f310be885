"""Queries of the corpus operators, one per operator, over whole tables."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from prunegraph.llm.common import shared_folder, table


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import toxicity

    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import packing

    return packing.pack_documents(table(spark, sf_dir, "documents"), tokenizer_path())


def op3_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import nearest

    return nearest.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op4_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import sharding

    placed = sharding.grow(table(spark, sf_dir, "documents"), f"{shared_folder(spark)}/slot-map-{uuid.uuid4().hex}")
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op5_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import quality

    found = quality.score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return found.select("doc_id", "lang", "n_bytes", "perplexity", "smoothed_perplexity", "threshold", "kept")


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import mixing

    return mixing.mix(table(spark, sf_dir, "documents"))


def op7_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import htmltext

    return htmltext.extract(table(spark, sf_dir, "pages"))


def op8_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import minhash

    return minhash.near_duplicates(table(spark, sf_dir, "documents"), words=3, percent=85)


def op9_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import graphs

    return graphs.near_vectors(table(spark, sf_dir, "embeddings"))


def op10_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    from prunegraph.llm import suffixes

    return suffixes.remove_repeats(table(spark, sf_dir, "documents")).drop("kept")


def queries() -> dict:
    return {"op1_toxicity": op1_toxicity, "op2_packing": op2_packing, "op3_nearest": op3_nearest, "op4_sharding": op4_sharding, "op5_quality": op5_quality, "op6_mixing": op6_mixing, "op7_html": op7_html, "op8_minhash": op8_minhash, "op9_vectors": op9_vectors, "op10_suffix_array": op10_suffix_array}


def oracle_sql() -> dict[str, str]:
    return {}
