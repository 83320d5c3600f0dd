"""Measured costs.  Their seconds are this machine's, so none of them has DuckDB SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from ctxviews.operators import costs, metrics, navigate, stats, units
from ctxviews.plans import measure, store
from ctxviews.plans.corpus import Corpus
from ctxviews.queries import query
from ctxviews.queries.delivery import synth_queries
from ctxviews.queries.plans import targets
from ctxviews.queries.upkeep import nav
from ctxviews.queries.views import thin_queries
from ctxviews.sources.tables import files, table

RESAMPLES = 20_000


def cells(spark, d):
    """Flat, IVF and HNSW on ten frozen indexes (the vectors of a label): ten warm-ups and a hundred searches for each configuration."""
    return store.stored(spark, d, "cells", lambda: measure.index_cells(table(spark, d, "embeddings"), "label"), ("embeddings",))


@query("q2_cells")
def _(spark, d):
    return cells(spark, d)


@query("d_qualified")
def _(spark, d):
    """The fastest configuration of each family whose mean overlap with Flat reaches 0.95, from the measured cells."""
    return metrics.qualified_fastest(measure.family_means(cells(spark, d)), 0.95)


@query("q2_ann_means")
def _(spark, d):
    """Mean Neighbor Recall@10 of each configuration with intervals from 20,000 resamples of the indexes."""
    return stats.bootstrap(spark, cells(spark, d), "index", "neighbor_recall", ["family", "config"], RESAMPLES)


@query("q2_amortize")
def _(spark, d):
    """Searches that repay the extra build time of each family's fastest qualified configuration, and its size beside Flat's."""
    m = measure.family_means(cells(spark, d))
    best = metrics.qualified_fastest(m, 0.95).select("family", "config")
    own = m.join(best, ["family", "config"])
    size = own.crossJoin(own.filter("family = 'flat'").select(F.col("bytes").alias("flat_bytes"))).select("family", "config", F.round(F.col("bytes") / F.col("flat_bytes"), 6).alias("size_ratio"))
    return costs.amortize(own.select("family", "build_ms", F.col("ms").alias("search_ms"))).join(size, "family")


@query("q2_ann_targets")
def _(spark, d):
    """On the lines of every snapshot that has targets: whether a configuration keeps Flat's target files everywhere."""
    c = measure.line_cells(spark, d, targets(spark, d), thin_queries(spark, d))
    return c.groupBy("family", "config").agg(F.count("*").alias("indexes"), F.round(F.avg("neighbor_recall"), 6).alias("neighbor_recall"), F.bool_and("kept").alias("all_kept"), F.count_if("kept").alias("kept"))


@query("q2_query_latency")
def _(spark, d):
    """P5 to P95 of exact search on one snapshot, one query at a time, by encoder."""
    return metrics.quantiles(measure.query_latency(spark, d, thin_queries(spark, d)), ["encoder"], "millis")


@query("q2_build_fit")
def _(spark, d):
    """Seconds of fresh dense builds over growing parts of the corpus: median, slope for a thousand lines, and lines against files."""
    rows = spark.createDataFrame(measure.build_costs(spark, d), "encoder string, level int, kloc double, seconds double, bytes long")
    wide = rows.groupBy("encoder", "kloc").pivot("level", [0, 2]).agg(F.first("seconds")).groupBy("encoder").agg(F.median(F.col("2") / F.col("0")).alias("lines_to_files"))
    fit = rows.groupBy("encoder", "level").agg(F.count("*").alias("builds"), F.median("seconds").alias("median_seconds"), F.regr_slope("seconds", "kloc").alias("seconds_per_kloc"), F.max("bytes").alias("bytes"))
    return fit.join(wide, "encoder")


@query("q3_latency_measured")
def _(spark, d):
    """Ten timed answers of both providers for each request on which they agree."""
    o, r = nav(spark, d)
    s, live = navigate.static(r, o), navigate.live(r, units.level2(files(spark, d)))
    same = s.select("req_id", "locs").join(live.select("req_id", F.col("locs").alias("theirs")), "req_id").filter("locs = theirs").select("req_id")
    return measure.conditional(measure.navigation_timings(r, o, units.level2(files(spark, d))), same)


@query("q4_speedup_measured")
def _(spark, d):
    """Seconds of each arm for one commit that edits about one file in fifty of every repository, and its speedup over the rebuild."""
    rows = spark.createDataFrame(measure.maintenance_arms(spark, *measure.small_commits(spark, d)), "arm string, seconds double")
    base = rows.filter("arm = 'rebuild'").select(F.col("seconds").alias("full"))
    return rows.crossJoin(base).select("arm", "seconds", costs.speedup(F.col("full"), F.col("seconds")).alias("gamma"))


@query("lc_measured")
def _(spark, d):
    """Cost of a session of 20 queries in two views and two definitions, alone and shared: isolated and resident."""
    q = synth_queries(spark, d)
    first = q.select("repo", "lang").distinct().orderBy("repo", "lang").limit(1)
    own = store.kept(q.join(first, ["repo", "lang"], "left_semi").select("query_id", "text"))
    first = store.few(first)
    mine = Corpus(spark, d).occurrences().join(first, ["repo", "lang"], "left_semi")  # requests are drawn inside a snapshot
    two = store.kept(navigate.requests(mine).filter("capability = 'definition'").orderBy("req_id").limit(2))
    m = measure.lifecycle(spark, d, own, two)
    c = spark.createDataFrame([("session", float(m["b"]), float(m["l"]), float(m["s"]), 1)], "snapshot string, b double, l double, s double, n int")
    return costs.project(c, spark).withColumn("b", F.lit(m["b"])).withColumn("l", F.lit(m["l"])).withColumn("s", F.lit(m["s"]))
