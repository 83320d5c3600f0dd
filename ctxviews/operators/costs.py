"""Cost accounting: maintenance speedups, amortization, lifecycle projections."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SHARE = 5
SCALES = (1, 5, 10, 20, 50, 100)


def speedup(rebuild: Column, update: Column, startup: Column | None = None, share: int = SHARE) -> Column:
    return rebuild / (update if startup is None else update + startup / share)


def conditional_summary(rows: DataFrame, by: list[str]) -> DataFrame:
    """Medians and quartiles of speedups over source-changing transitions that match; all rows are counted."""
    ok = F.col("changed") & F.col("matched")
    q = lambda p: F.round(F.percentile(F.when(ok, F.col("gamma")), p), 6)
    return rows.groupBy(*by).agg(F.count("*").alias("n"), F.count_if("changed").alias("source_changing"), F.count_if(ok).alias("matched"), q(0.25).alias("q25"), q(0.5).alias("median"), q(0.75).alias("q75"))


def project(costs: DataFrame, spark, scales: tuple[int, ...] = SCALES) -> DataFrame:
    """q, isolated, resident: per-session seconds, projected for each snapshot and then the median.

    costs: snapshot, b (materialization), l (loading), s (service trace), n (sessions of the trace).
    """
    q = spark.createDataFrame([(x,) for x in scales], "q int")
    each = costs.crossJoin(F.broadcast(q)).select("q", (F.col("b") / F.col("q") + F.col("l") + F.col("s") / F.col("n")).alias("i"), ((F.col("b") + F.col("l")) / F.col("q") + F.col("s") / F.col("n")).alias("r"))
    return each.groupBy("q").agg(F.round(F.median("i"), 6).alias("isolated"), F.round(F.median("r"), 6).alias("resident"))


def amortize(cells: DataFrame) -> DataFrame:
    """family, searches: extra build time over Flat divided by the time saved in a search; null if a search saves none."""
    flat = cells.filter("family = 'flat'").select(F.col("build_ms").alias("b0"), F.col("search_ms").alias("s0"))
    saved = F.col("s0") - F.col("search_ms")
    return cells.filter("family <> 'flat'").crossJoin(F.broadcast(flat)).select("family", F.when(saved > 0, F.ceil((F.col("build_ms") - F.col("b0")) / saved)).alias("searches"))
