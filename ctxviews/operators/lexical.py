"""The lexical view: postings, BM25, trigrams, substring and regular-expression search."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import tokens
from ctxviews.operators import lists, rows

K1, B = 1.2, 0.75


def postings(u: DataFrame, key: str = "unit_id") -> DataFrame:
    """term, key, tf, positions (token ordinals).

    A unit's tokens never leave its row: nothing is shuffled.
    """
    return rows.post(u, tokens(F.col("text")), key)


def stats(u: DataFrame) -> DataFrame:
    return u.agg(F.count("*").alias("n"), F.avg(F.size(tokens(F.col("text")))).alias("avgdl"))


@dataclass
class Index:
    """A stored lexical view: lists (key, f terms, w weights without idf), terms (term, df), one row (n, avgdl), and the counts (key, dl, f, tf) themselves."""

    lists: DataFrame
    terms: DataFrame
    stats: DataFrame
    key: str = "unit_id"
    counts: DataFrame | None = None


def index(u: DataFrame, key: str = "unit_id", put: Callable[[str, Callable[[], DataFrame]], DataFrame] | None = None) -> Index:
    """The index of units; put(name, build) stores its tables (without it they stay plans).

    A unit's tokens are counted in its row.
    """
    put = put or (lambda name, build: build())
    counts = put("counts", lambda: rows.count(u, tokens(F.col("text")), key))
    one = put("stats", lambda: counts.agg(F.count("*").alias("n"), F.avg("dl").alias("avgdl")))
    terms = put("terms", lambda: counts.select(F.explode("f").alias("term")).groupBy("term").agg(F.count("*").alias("df")))
    part = lambda tf: tf * (K1 + 1) / (tf + K1 * (1 - B + B * F.col("dl") / F.col("avgdl")))
    return Index(counts.crossJoin(F.broadcast(one)).select(key, "f", F.transform("tf", part).alias("w")), terms, one, key, counts)


def bm25(queries: DataFrame, u: DataFrame | Index, k: int, key: str = "unit_id") -> DataFrame:
    """query_id, key, score, rank of the k best units for each query (scores rounded, ties by key)."""
    x = u if isinstance(u, Index) else index(u, key)
    terms = queries.select("query_id", F.explode(F.array_distinct(tokens(F.col("text")))).alias("term"))
    idf = F.log(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5))
    return lists.search(x.lists, terms.join(x.terms, "term").crossJoin(F.broadcast(x.stats)).select("query_id", F.col("term").alias("f"), idf.alias("w")), k, x.key)


def top(scored: DataFrame, k: int, key: str = "unit_id", by: str = "query_id", score: str = "score") -> DataFrame:
    """The k best rows of each group; the rank filter reaches below the exchange as a group limit."""
    w = W.partitionBy(by).orderBy(F.desc(score), key)
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def grams(c: Column) -> Column:
    n = F.length(c)
    return F.when(n >= 3, F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(n - 2, F.lit(1))), lambda i: c.substr(i, F.lit(3))))).otherwise(F.array().cast("array<string>"))


def trigrams(f: DataFrame) -> DataFrame:
    """gram, path: one row for each distinct gram of a file, taken line by line."""
    from ctxviews.operators.units import lines

    return lines(f.select("path", "text")).select("path", F.explode(grams(F.col("text"))).alias("gram")).distinct()


def substring(patterns: DataFrame, f: DataFrame, index: DataFrame) -> DataFrame:
    """pattern_id, path of files that hold a pattern: files with all its grams, verified on the text."""
    g = patterns.select("pattern_id", "pattern", F.explode(grams(F.col("pattern"))).alias("gram")).filter(~F.contains("gram", F.lit("\n")))
    need = g.groupBy("pattern_id", "pattern").agg(F.count("*").alias("need"))
    hits = index.join(g, "gram").groupBy("pattern_id", "path").agg(F.count("*").alias("have"))
    cand = hits.join(need, "pattern_id").filter("have = need")
    return cand.join(f.select("path", "text"), "path").filter(F.contains("text", "pattern")).select("pattern_id", "path")


def holding(passages: DataFrame, u: DataFrame, x: Index, few: Callable[[DataFrame], DataFrame] = lambda df: df) -> DataFrame:
    """query_id, key: units whose text holds a passage (query_id, text) as it stands.

    A passage's inner tokens are whole tokens of any text that holds it, so only units
    with its rarest inner token are looked at, and one that no unit has rules it out.
    Passages of fewer than three tokens have no inner ones: they alone meet all units.
    few(df) writes a table of a few rows for each passage and may send it to every task, so
    that neither the units' terms nor their texts are shuffled.
    """
    p = passages.select("query_id", F.col("text").alias("passage"), tokens(F.col("text")).alias("ts")).filter("passage is not null")
    inner = p.filter("size(ts) > 2").select("query_id", F.explode(F.array_distinct(F.slice("ts", 2, F.size("ts") - 2))).alias("term"))
    seen = inner.join(x.terms, "term", "left").groupBy("query_id").agg(F.count_if(F.col("df").isNull()).alias("none"), F.min(F.struct("df", "term")).alias("rare"))
    rare = few(seen.filter("none = 0").select("query_id", F.col("rare.term").alias("term")))
    cand = few(x.lists.select(x.key, F.explode("f").alias("term")).join(rare, "term").select("query_id", x.key))
    text = u.select(x.key, "text")
    out = cand.join(text, x.key).join(p.select("query_id", "passage"), "query_id").filter(F.contains("text", "passage"))
    short = text.join(p.filter("size(ts) <= 2").select("query_id", "passage"), F.contains("text", "passage"))
    return out.select("query_id", x.key).unionByName(short.select("query_id", x.key))


def regex(f: DataFrame, pattern: str, literal: str | None = None) -> DataFrame:
    """Lines that match; a literal of the pattern filters files before they are cut."""
    from ctxviews.operators.units import lines

    if literal:
        f = f.filter(F.contains("text", F.lit(literal)))
    return lines(f).filter(F.col("text").rlike(pattern)).select("path", "line", "text")


def normalize(hits: DataFrame) -> DataFrame:
    """Hits of any search as path, start, snippet and a score that may be null."""
    has = "score" in hits.columns
    return hits.select("path", F.col("line").alias("start"), F.substring("text", 1, 80).alias("snippet"), (F.col("score") if has else F.lit(None).cast("double")).alias("score"))


def delta(old: DataFrame, removed: DataFrame, added_units: DataFrame, key: str = "unit_id") -> DataFrame:
    """Postings after an edit: lists of removed units go, those of added units come.

    old: postings, or the counts of an index (key, f, tf), of which one short row a unit meets the removed units.
    """
    if "term" in old.columns:
        return old.join(removed.select(key), key, "left_anti").unionByName(postings(added_units, key))
    told = lambda x: x.select(key, F.concat_ws(" ", "f").alias("f"), F.concat_ws(" ", F.col("tf").cast("array<string>")).alias("tf"))
    stay = told(old).join(removed.select(key), key, "left_anti")
    come = told(rows.count(added_units, tokens(F.col("text")), key))
    pairs = F.arrays_zip(F.split("f", " ").alias("term"), F.split("tf", " ").cast("array<bigint>").alias("tf"))
    return stay.unionByName(come).filter("f <> ''").select(key, F.explode(pairs).alias("x")).select("x.term", key, "x.tf")
