"""Measures of retrieval, navigation, maintenance and delivery."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def qualified_fastest(cells: DataFrame, least: float) -> DataFrame:
    """The fastest configuration of each family whose mean overlap reaches `least`."""
    return cells.filter(F.col("overlap") >= least).groupBy("family").agg(F.min_by("config", "ms").alias("config"), F.round(F.min("ms"), 6).alias("ms"))


def file_recall(ranked: DataFrame, targets: DataFrame, k: int, by: list[str] | None = None) -> DataFrame:
    """Macro mean over queries of the share of targets among the first k files: ranked (by.., query_id, path, rank)."""
    by = by or []
    need = targets.groupBy("query_id").agg(F.count("*").alias("need"))
    hit = ranked.filter(F.col("rank") <= k).join(targets.select("query_id", "path").distinct(), ["query_id", "path"]).groupBy(*by, "query_id").agg(F.count("*").alias("hit"))
    arms = ranked.select(*by).distinct() if by else None
    base = need.crossJoin(F.broadcast(arms)) if by else need
    each = base.join(hit, [*by, "query_id"], "left").withColumn("hit", F.coalesce("hit", F.lit(0)))
    grouped = each.groupBy(*by) if by else each
    return grouped.agg(F.count("*").alias("n"), F.round(F.avg(F.col("hit") / F.col("need")), 6).alias("recall"), F.round(F.avg((F.col("hit") == F.col("need")).cast("double")), 6).alias("success"))


def pareto(points: DataFrame, cost: str, quality: str, panel: list[str]) -> DataFrame:
    """Points that no other point of their panel dominates: by cost, quality must exceed all before."""
    from pyspark.sql import Window as W

    w = W.partitionBy(*panel).orderBy(cost, F.desc(quality)).rowsBetween(W.unboundedPreceding, -1)
    return points.withColumn("before", F.max(quality).over(w)).filter(F.col("before").isNull() | (F.col(quality) > F.col("before"))).drop("before")


def match_rate(static: DataFrame, live: DataFrame, by: list[str]) -> DataFrame:
    """by.., n, matched, rate, both: requests whose normalized location sets agree, and those non-empty on both sides."""
    j = static.join(live.select("req_id", F.col("locs").alias("live")), "req_id")
    same = F.col("locs") == F.col("live")
    return j.groupBy(*by).agg(F.count("*").alias("n"), F.count_if(same).alias("matched"), F.round(F.count_if(same) / F.count("*"), 6).alias("rate"), F.count_if(same & (F.size("locs") > 0)).alias("both"))


def conditional_latency(timings: DataFrame) -> DataFrame:
    """One row over matched requests: p50 of request medians for each side, median paired saving, median ratio."""
    m = timings.groupBy("req_id").pivot("provider", ["static", "live"]).agg(F.median("millis"))
    return m.agg(F.count("*").alias("n"), F.round(F.median("static"), 6).alias("p50_static"), F.round(F.median("live"), 6).alias("p50_live"), F.round(F.median(F.col("live") - F.col("static")), 6).alias("median_saving"), F.round(F.median(F.col("live") / F.col("static")), 6).alias("median_ratio"))


def quantiles(df: DataFrame, by: list[str], value: str) -> DataFrame:
    """P5, P25, P50, P75, P95."""
    return df.groupBy(*by).agg(*[F.round(F.percentile(value, p / 100), 6).alias(f"p{p}") for p in (5, 25, 50, 75, 95)])


def edge_f1(found: DataFrame, truth: DataFrame, key: list[str], edge: list[str]) -> DataFrame:
    """key.., precision, recall, f1 of edge multisets."""
    a = found.groupBy(*key, *edge).agg(F.count("*").alias("m1"))
    b = truth.groupBy(*key, *edge).agg(F.count("*").alias("m2"))
    j = a.join(b, [*key, *edge], "full").select(*key, F.coalesce("m1", F.lit(0)).alias("m1"), F.coalesce("m2", F.lit(0)).alias("m2"))
    s = j.groupBy(*key).agg(F.sum(F.least("m1", "m2")).alias("both"), F.sum("m1").alias("a"), F.sum("m2").alias("b"))
    p, r = F.col("both") / F.nullif(F.col("a"), F.lit(0)), F.col("both") / F.nullif(F.col("b"), F.lit(0))
    return s.select(*key, F.round(F.coalesce(p, F.lit(1.0)), 6).alias("precision"), F.round(F.coalesce(r, F.lit(1.0)), 6).alias("recall"), F.round(2 * F.col("both") / (F.col("a") + F.col("b")), 6).alias("f1"))
