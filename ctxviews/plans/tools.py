"""Tools of an agent: what each needs, which are open, and their SQL table functions."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxviews.operators import dense, structure
from ctxviews.plans.catalog import CAPABILITIES, ViewUnavailable
from ctxviews.plans.plan import Views, dense_list, lexical_list

NEEDS = {
    "semantic_search": "semantic_search", "bm25_search": "text_search", "regex_search": "text_search", "trigram_search": "text_search",
    "dependencies": "neighbours", "definition": "definition", "references": "references", "route": "neighbours", "catalog": None,
}


def required_views(names: list[str]) -> set[str]:
    """Views that the capabilities of the selected tools need."""
    caps = {NEEDS[n] for n in names} - {None}
    return {v for v, cs in CAPABILITIES.items() if caps & set(cs)}


def guard(names: list[str], capabilities: set[str], stale: set[str] = frozenset()) -> tuple[list[str], list[str]]:
    """(tools that are open, warnings): unavailable tools fall out, stale ones warn."""
    ok = [n for n in names if NEEDS[n] is None or NEEDS[n] in capabilities]
    return ok, [f"{n} answers from a stale view" for n in ok if NEEDS[n] in stale]


def register(spark: SparkSession, units: DataFrame, occurrences: DataFrame, edges: DataFrame) -> None:
    """Views ctx_units, ctx_occurrences, ctx_edges, and SQL functions ctx_definition, ctx_references,
    ctx_neighbours (temporary table functions in plain SQL, so Catalyst plans through them)."""
    units.createOrReplaceTempView("ctx_units")
    occurrences.createOrReplaceTempView("ctx_occurrences")
    edges.createOrReplaceTempView("ctx_edges")
    for name, body in {
        "ctx_definition": "select path, line from ctx_occurrences where symbol = ctx_definition.s and role = 1",
        "ctx_references": "select path, line from ctx_occurrences where symbol = ctx_references.s",
    }.items():
        spark.sql(f"create or replace temporary function {name}(s string) returns table(path string, line int) return {body}")
    spark.sql("create or replace temporary function ctx_neighbours(v string) returns table(node string, etype string) return select dst, etype from ctx_edges where src = ctx_neighbours.v union all select src, etype from ctx_edges where dst = ctx_neighbours.v")


SNIPPET = 80


def _located(hits: DataFrame, units: DataFrame, locations_only: bool) -> DataFrame:
    """path, start, snippet, score: hits (path, start, score) with the line they stand on, or without it."""
    if locations_only:
        return hits.select("path", "start", F.lit(None).cast("string").alias("snippet"), "score")
    text = units.select("path", "start", F.substring("text", 1, SNIPPET).alias("snippet"))
    return hits.join(text, ["path", "start"], "left").select("path", "start", "snippet", "score")


@dataclass
class Toolbox:
    """The nine tools over a corpus's views; each returns path, start, snippet, score, whatever it asked.

    compact: locations without snippets.  Tools of missing capabilities are refused.
    """

    views: Views
    occurrences: DataFrame | None = None
    capabilities: frozenset[str] = frozenset(c for cs in CAPABILITIES.values() for c in cs)
    compact: bool = False
    entries: list = field(default_factory=list)

    def call(self, tool: str, text: str = "", k: int = 10, depth: int = 2, to: str | None = None) -> DataFrame:
        """text: a query, pattern, symbol or vertex; to: where a route ends."""
        if not guard([tool], set(self.capabilities))[0]:
            raise ViewUnavailable(f"{tool} needs {NEEDS[tool]}")
        u, spark = self.views.units, self.views.units.sparkSession
        none = F.lit(None).cast("double").alias("score")
        if tool == "catalog":
            rows = [(e.view, 0, e.status, None) for e in self.entries]
            return spark.createDataFrame(rows, "path string, start int, snippet string, score double")
        if tool in ("bm25_search", "semantic_search"):
            q = spark.createDataFrame([("q", text)], "query_id string, text string")
            ranked = lexical_list(self.views, q, k) if tool == "bm25_search" else dense_list(self.views, q, k)
            return _located(ranked.join(u.select("unit_id", "path", "start"), "unit_id").orderBy("rank").select("path", "start", "score"), u, self.compact)
        if tool in ("regex_search", "trigram_search"):
            hit = F.col("text").rlike(text) if tool == "regex_search" else F.contains("text", F.lit(text))
            return _located(u.filter(hit).select("path", "start", none), u, self.compact)
        if tool in ("definition", "references"):
            o = self.occurrences.filter(F.col("symbol") == text)
            o = o.filter(F.col("role") == structure.DECLARES) if tool == "definition" else o
            return _located(o.select("path", F.col("line").alias("start"), none).distinct(), u, self.compact)
        seed = spark.createDataFrame([(text,)], "seed string")
        reach = structure.neighbours(seed, self.views.edges, depth, ("reference", "import"), "out").filter("hop > 0")
        if tool == "route":
            reach = reach.filter(F.col("node") == to)
        at = F.split("node", "#")
        return _located(reach.select(at[0].alias("path"), F.coalesce(F.try_element_at(at, F.lit(2)).cast("int"), F.lit(0)).alias("start"), F.col("hop").cast("double").alias("score")), u, self.compact)


def search(spark: SparkSession, units: DataFrame, text: str, k: int = 10, tool: str = "bm25_search") -> DataFrame:
    """path, start, snippet, score of one query over units alone: their lists and vectors are made on the way."""
    v = Views(units)
    if tool == "semantic_search":
        e = dense.ENCODERS[2]
        v.encoder, v.idf = e, dense.document_frequency(units, e)
        v.vectors = dense.vectors(units, e, v.idf)
    return Toolbox(v).call(tool, text, k)


def reachable(seeds: DataFrame, edges: DataFrame, depth: int) -> DataFrame:
    return structure.dependencies(seeds, edges, depth)
