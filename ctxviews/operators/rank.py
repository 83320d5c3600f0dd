"""Fusion, reranking and composition of ranked lists."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import tokens
from ctxviews.operators.lexical import top

KAPPA = 60


def rrf(lists: list[tuple[DataFrame, float]], k: int, key: str = "unit_id", kappa: int = KAPPA) -> DataFrame:
    """Reciprocal-rank fusion: one union and one grouping; a list without a unit adds nothing."""
    parts = [d.select("query_id", key, (F.lit(w) / (kappa + F.col("rank"))).alias("part")) for d, w in lists]
    both = parts[0]
    for p in parts[1:]:
        both = both.unionByName(p)
    return top(both.groupBy("query_id", key).agg(F.round(F.sum("part"), 9).alias("score")), k, key)


def graph_list(dense: DataFrame, edges: DataFrame, seeds: int, vid: str = "vid") -> DataFrame:
    """query_id, vid, rank: one hop in and out over reference edges from the first `seeds` units.

    Ordered by best seed rank, then supporting edges, then address; seeds count only if reached.
    """
    s = dense.filter(F.col("rank") <= seeds).select("query_id", F.col(vid).alias("seed"), "rank")
    ref = edges.filter("etype = 'reference'").filter("src <> dst")
    step = ref.select(F.col("src").alias("seed"), F.col("dst").alias(vid)).unionByName(ref.select(F.col("dst").alias("seed"), F.col("src").alias(vid)))
    hit = step.join(s, "seed").groupBy("query_id", vid).agg(F.min("rank").alias("best"), F.count("*").alias("support"))
    w = W.partitionBy("query_id").orderBy("best", F.desc("support"), vid)
    return hit.withColumn("rank", F.row_number().over(w)).select("query_id", vid, "rank")


def dense_graph_fusion(dense: DataFrame, edges: DataFrame, weights: DataFrame, seeds: int = 10, kappa: int = KAPPA, k: int = 10, vid: str = "vid") -> DataFrame:
    """w_g, query_id, vid, score, rank for every graph weight (rows of weights) in one pass."""
    g = graph_list(dense, edges, seeds, vid)
    both = dense.select("query_id", vid, F.col("rank").alias("rd")).join(g.withColumnRenamed("rank", "rg"), ["query_id", vid], "full")
    scored = both.crossJoin(F.broadcast(weights)).withColumn("score", F.round(F.coalesce(1 / (kappa + F.col("rd")), F.lit(0.0)) + F.coalesce(F.col("w_g") / (kappa + F.col("rg")), F.lit(0.0)), 9))
    w = W.partitionBy("w_g", "query_id").orderBy(F.desc("score"), vid)
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("w_g", "query_id", vid, "score", "rank")


def jaccard(a: Column, b: Column) -> Column:
    """Small scorer: overlap of token sets."""
    x, y = F.array_distinct(tokens(a)), F.array_distinct(tokens(b))
    union = F.size(F.array_union(x, y))
    return F.when(union == 0, 0.0).otherwise(F.size(F.array_intersect(x, y)) / union)


def char_cosine(a: Column, b: Column) -> Column:
    """Medium scorer: cosine of the sets of character 4-grams."""
    def g(c):
        low = F.lower(c)
        return F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length(low) - 3, F.lit(1))), lambda i: low.substr(i, F.lit(4))))

    x, y = g(a), g(b)
    return F.size(F.array_intersect(x, y)) / F.sqrt(F.size(x) * F.size(y))


def _span(x: Column, n: int):
    return lambda i: F.concat(F.lit(" "), F.concat_ws(" ", F.slice(x, i, n)), F.lit(" "))


def longest_run(a: Column, b: Column) -> Column:
    """Tokens of the longest run of a that b holds, up to eight."""
    x = tokens(a)
    text = F.concat(F.lit(" "), F.concat_ws(" ", tokens(b)), F.lit(" "))
    best = F.lit(0)
    for n in range(1, 9):
        spans = F.transform(F.sequence(F.lit(1), F.greatest(F.size(x) - n + 1, F.lit(1))), _span(x, n))
        has = F.exists(spans, lambda s: F.contains(text, s))
        best = F.when((F.size(x) >= n) & has, n).otherwise(best)
    return best


SCORERS = {
    "small": jaccard,
    "medium": char_cosine,
    "large": lambda a, b: char_cosine(a, b) + longest_run(a, b) / 8.0,
}


def pointwise(cands: DataFrame, scorer: str, cut: int, k: int, key: str = "unit_id") -> DataFrame:
    """Rerank the first `cut` candidates: rows (query_id, query_text, key, text, rank).  The cut is below the scorer."""
    few = cands.filter(F.col("rank") <= cut)
    scored = few.withColumn("score", F.round(SCORERS[scorer](F.col("query_text"), F.col("text")), 6))
    return top(scored.drop("rank"), k, key)


def distinct_files(ranked: DataFrame, path: str = "path") -> DataFrame:
    """query_id, path, rank: the first unit of each file stays; ranks close up."""
    first = ranked.groupBy("query_id", path).agg(F.min("rank").alias("first"))
    return first.withColumn("rank", F.row_number().over(W.partitionBy("query_id").orderBy("first", path))).drop("first")


def compose(ranked: DataFrame, units: DataFrame, k: int, key: str = "unit_id") -> DataFrame:
    """Code blocks with their source addresses, one for each file, text fetched after the cut."""
    u = units.select(key, "path", "start", "end", "text")
    cut = ranked.join(u, key)
    first = cut.withColumn("n", F.row_number().over(W.partitionBy("query_id", "path").orderBy("rank"))).filter("n = 1")
    out = first.withColumn("block", F.row_number().over(W.partitionBy("query_id").orderBy("rank"))).filter(F.col("block") <= k)
    return out.select("query_id", "block", "path", "start", "end", "text")
