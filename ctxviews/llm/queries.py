"""The queries opN_<name> of the training-data operators, over whole tables."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe_codec, cap_neardup, chroma, jaccard_join, language_id, packing, quality, suffix_dedup, token_counts, url_filter
from .common import keep, table


def op1_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The contract's columns and, as the operator's real output, what is left of each text, under the name that it has in documents."""
    return suffix_dedup.dedup(table(spark, sf_dir, "documents"), spark, ["doc_id"], with_text=True).withColumnRenamed("kept_text", "text")


def op2_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"), spark, public_tokenizers.path("piece_bpe_32k.model"))


def op3_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(table(spark, sf_dir, "pages").select("page_id", "url"), spark)


def op4_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_join.join(table(spark, sf_dir, "documents"), spark)


def op5_cap_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cap_neardup.near_duplicates(table(spark, sf_dir, "embeddings"), spark)


def op6_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_codec.encode(table(spark, sf_dir, "documents"), spark, public_tokenizers.path("word_bpe_49k.json"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), spark, public_tokenizers.path("byte_bpe_50k.json"))


def _held(mod: int, rest: int):
    return F.crc32(F.col("doc_id").cast("string")) % mod == rest


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("held_out", _held(4, 2))
    model = language_id.fit(docs.filter(~F.col("held_out")), spark)
    return language_id.identify(docs, spark, model, ["doc_id", "held_out"])


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = quality.fit(docs, labels.filter(~_held(5, 0)), spark)
    return quality.score(docs.withColumn("held_out", _held(5, 0)), spark, model, ["doc_id", "held_out"]).withColumn("predicted", (F.col("score") >= 0.3).cast("int"))


def op10_chroma(spark: SparkSession, sf_dir: str) -> DataFrame:
    prints = chroma.fingerprints(table(spark, sf_dir, "embeddings"), spark, "vec_id", "embedding", chroma.sonify)
    return chroma.search(keep(prints, spark), spark)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_suffix_dedup": op1_suffix_dedup,
    "op2_token_counts": op2_token_counts,
    "op3_url_filter": op3_url_filter,
    "op4_jaccard_join": op4_jaccard_join,
    "op5_cap_neardup": op5_cap_neardup,
    "op6_bpe_codec": op6_bpe_codec,
    "op7_packing": op7_packing,
    "op8_language_id": op8_language_id,
    "op9_quality": op9_quality,
    "op10_chroma": op10_chroma,
}

ORACLE_SQL: dict[str, str] = {}
