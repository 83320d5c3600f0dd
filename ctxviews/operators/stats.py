"""Clustered percentile bootstraps and simultaneous intervals, as joins of replicates with cluster sums."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxviews.functions.text import md5_number


def cluster_sums(df: DataFrame, cluster: str, value: str, by: list[str]) -> DataFrame:
    """by.., c (cluster number by name), s, n: the data shrink to clusters before any replicate is drawn."""
    from pyspark.sql import Window as W

    number = df.select(cluster).distinct().withColumn("c", F.row_number().over(W.orderBy(cluster)) - 1)
    return df.groupBy(*by, cluster).agg(F.sum(value).alias("s"), F.count("*").alias("n")).join(number, cluster).drop(cluster)


def replicates(spark: SparkSession, sums: DataFrame, by: list[str], b: int) -> DataFrame:
    """by.., b, theta: each replicate draws as many clusters as there are, by hash of (b, j)."""
    clusters = sums.select("c").distinct().agg(F.count("*").alias("n_c"))
    draws = spark.range(b).select(F.col("id").alias("b")).crossJoin(F.broadcast(clusters)).select("b", "n_c", F.explode(F.sequence(F.lit(0), F.col("n_c").cast("int") - 1)).alias("j"))
    draws = draws.withColumn("c", md5_number(F.concat(F.col("b").cast("string"), F.lit("#"), F.col("j").cast("string"))) % F.col("n_c"))
    return draws.join(sums, "c").groupBy(*by, "b").agg((F.sum("s") / F.sum("n")).alias("theta"))


def bootstrap(spark: SparkSession, df: DataFrame, cluster: str, value: str, by: list[str], b: int = 10_000, level: float = 0.95) -> DataFrame:
    """by.., mean, lower, upper: clustered percentile interval of the mean."""
    sums = cluster_sums(df, cluster, value, by)
    r = replicates(spark, sums, by, b)
    q = (1 - level) / 2
    bounds = r.groupBy(*by).agg(F.round(F.percentile("theta", q), 6).alias("lower"), F.round(F.percentile("theta", 1 - q), 6).alias("upper"))
    mean = sums.groupBy(*by).agg(F.round(F.sum("s") / F.sum("n"), 6).alias("mean"))
    return mean.join(bounds, by) if by else mean.crossJoin(bounds)


def simultaneous(spark: SparkSession, df: DataFrame, cluster: str, value: str, contrast: str, b: int = 10_000, level: float = 0.95) -> DataFrame:
    """contrast, mean, lower, upper from one quantile of the largest scaled deviation over all contrasts."""
    sums = cluster_sums(df, cluster, value, [contrast])
    r = replicates(spark, sums, [contrast], b)
    mean = sums.groupBy(contrast).agg((F.sum("s") / F.sum("n")).alias("mean"))
    sd = r.groupBy(contrast).agg(F.stddev_samp("theta").alias("sd"))
    base = mean.join(sd, contrast)
    scaled = r.join(F.broadcast(base), contrast).groupBy("b").agg(F.max(F.when(F.col("sd") > 0, F.abs(F.col("theta") - F.col("mean")) / F.col("sd")).otherwise(0.0)).alias("m"))
    cut = scaled.agg(F.percentile("m", level).alias("cut"))
    return base.crossJoin(F.broadcast(cut)).select(contrast, F.round("mean", 6).alias("mean"), F.round(F.col("mean") - F.col("cut") * F.col("sd"), 6).alias("lower"), F.round(F.col("mean") + F.col("cut") * F.col("sd"), 6).alias("upper"))
