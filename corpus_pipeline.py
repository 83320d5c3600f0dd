"""A training-corpus pipeline of five stages over `documents`.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last
return the columns of docs.  Extra columns travel along, whatever their names.
Null and empty texts pass through every stage with their defined results: the
quality network scores them, language ID calls them `und` and rejects them.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxviews.llm import jaccard_join, language_id, packing, quality, suffix_dedup
from ctxviews.llm.common import keep, small, table

#: A document with a score under this is rejected.
LEAST_QUALITY = 0.3
#: An ambiguous language is accepted from this score on.
LEAST_LANGUAGE = 0.4
#: Passages of over 50 words: shorter repeats are left alone.
PASSAGE_WORDS = 51


def _apart(docs: DataFrame) -> DataFrame:
    """docs with columns named by place, so that no name of ours can clash."""
    return docs.toDF(*(f"d{i}" for i in range(len(docs.columns))))


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows whose score reaches LEAST_QUALITY stay, repeated ones too; null and empty texts get the network's score for those."""
    labels = table(spark, sf_dir, "labels").filter(F.crc32(F.col("doc_id").cast("string")) % 5 != 0)
    model = quality.fit(docs, labels, spark)
    own = _apart(docs)
    text = own.columns[docs.columns.index("text")]
    scored = quality.score(own, spark, model, own.columns, text)
    return scored.filter(F.col("score") >= LEAST_QUALITY).select(own.columns).toDF(*docs.columns)


def language_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows in a language stay, repeated ones too; texts without a letter (null and empty ones) go, and so do
    ambiguous texts with a score under LEAST_LANGUAGE."""
    model = language_id.fit(docs.filter(F.crc32(F.col("doc_id").cast("string")) % 4 != 2), spark)
    own = _apart(docs)
    text = own.columns[docs.columns.index("text")]
    told = language_id.identify(own, spark, model, own.columns, text)
    good = (F.col("lang_pred") != "und") & (~F.col("ambiguous") | (F.col("score") >= LEAST_LANGUAGE))
    return told.filter(good).select(own.columns).toDF(*docs.columns)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component stays, once: the one with the least id (null comes last), then node.

    Documents are told apart by id and text; those without words and id are never the same.
    """
    own = _apart(docs)
    number, text = (own.columns[docs.columns.index(c)] for c in ("doc_id", "text"))
    found = keep(jaccard_join.linked(own, spark, id_col=number, text_col=text), spark)
    nodes = found.filter("n_shingles > 0 or id is not null")
    first = nodes.groupBy("component").agg(F.min(F.struct(F.col("id").isNull(), "id", "node"))["node"].alias("stays"), F.min("node").alias("lo"), F.max("node").alias("hi"))
    first = keep(first.filter("lo < hi").select("component", "stays"), spark)
    gone = keep(nodes.join(small(first, spark), "component").filter("node <> stays").select("node").distinct(), spark)
    again = keep(nodes.groupBy("node").count().filter("count > 1").select("node"), spark)
    kept = own.withColumn("node", jaccard_join.node_key(own, number, text)).join(small(gone, spark), "node", "left_anti")
    if again.limit(1).count():
        once = kept.join(small(again, spark), "node", "left_semi").dropDuplicates(["node"])
        kept = kept.join(small(again, spark), "node", "left_anti").union(once)
    return kept.select(own.columns).toDF(*docs.columns)


def repeat_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated passages go; a document of nothing else (but white space) goes whole."""
    own = _apart(docs)
    text, number = (own.columns[docs.columns.index(c)] for c in ("text", "doc_id"))
    out = suffix_dedup.dedup(own, spark, [c for c in own.columns if c != text], with_text=True, text_col=text, id_col=number, n_words=PASSAGE_WORDS)
    out = out.filter("n_removed = 0 or kept_text rlike '[^ \\\\t-\\\\r]'").withColumn(text, F.col("kept_text"))
    if "n_chars" in docs.columns:
        n = own.columns[docs.columns.index("n_chars")]
        out = out.withColumn(n, F.when(F.col("n_removed") > 0, F.length(text).cast(dict(own.dtypes)[n])).otherwise(F.col(n)))
    return out.select(own.columns).toDF(*docs.columns)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row's pieces; an empty table gives none, a text without tokens its end id alone."""
    return packing.pack(docs, spark, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [
    ("quality classifier", quality_stage),
    ("language ID", language_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("suffix-array dedup", repeat_stage),
    ("packing", packing_stage),
]

#: The classifiers, components and suffix arrays are beyond SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES[:-1]:
        docs = keep(stage(spark, docs, sf_dir), spark)
    return STAGES[-1][1](spark, docs, sf_dir)
