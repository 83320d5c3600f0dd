"""Base data: the given tables as repository versions.

A repository is a `source`, a language group a `lang`, a snapshot one pair of both,
a file a document at path source/lang/doc_id.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """Deal a table of few partitions over all cores; larger ones stay as they are read."""
    n = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(n) if 2 * df.rdd.getNumPartitions() <= n else df


def files(spark: SparkSession, sf_dir: str, deal: bool = True) -> DataFrame:
    """repo, lang, version, path, doc_id, text of every document (null text is empty); deal=False leaves small tables as they are read."""
    d = table(spark, sf_dir, "documents").select("source", "lang", "doc_id", "text")
    return (spread(d) if deal else d).select(
        F.col("source").alias("repo"), "lang", F.lit(0).alias("version"),
        F.concat_ws("/", "source", "lang", F.col("doc_id").cast("string")).alias("path"), "doc_id", F.coalesce("text", F.lit("")).alias("text"),
    )


def page_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages as files of the markup adapter: repo = host, path = host and url path."""
    rest = F.regexp_extract("url", r"^[a-z]+://([^?#]*)", 1)
    return table(spark, sf_dir, "pages").select(F.regexp_extract(rest, r"^([^/]*)", 1).alias("repo"), F.lit(0).alias("version"), rest.alias("path"), "page_id", F.coalesce("html", F.lit("")).alias("text"))


def snapshots(f: DataFrame) -> DataFrame:
    """One row for each (repo, lang): files, lines and the difficulty stratum by number of files."""
    from pyspark.sql import Window as W

    s = f.groupBy("repo", "lang").agg(F.count("*").alias("n_files"), F.sum(F.size(F.split("text", "\n"))).alias("n_lines"))
    return s.withColumn("stratum", F.ntile(4).over(W.orderBy("n_files", "repo", "lang")))


#: Views that leave part of the files out, and the label that says which.
SCOPES = {"lexical": None, "structural": None, "dense": "toxic"}


def scope(f: DataFrame, labels: DataFrame, view: str) -> DataFrame:
    """Files that a view covers: labelled ones can fall out, unlabelled files stay."""
    label = SCOPES[view]
    return f if label is None else f.join(labels.filter(F.col(label) == 1).select("doc_id"), "doc_id", "left_anti")
