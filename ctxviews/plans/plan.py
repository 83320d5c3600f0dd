"""Ranked plans: the tuple, its legality, the deterministic selector and the routes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ctxviews.functions.text import tokens
from ctxviews.operators import dense, lexical, lists, rank, rows, structure
from ctxviews.plans import store
from ctxviews.plans.catalog import ViewUnavailable

NEEDS = {"A": {"text_search"}, "B": {"semantic_search"}, "C": {"text_search", "semantic_search"}, "D": {"text_search", "references"}}


@dataclass(frozen=True)
class RankedPlan:
    """Route, widths, reranker and graph hop.  The caller owns k_out."""

    route: str
    k_ret: int = 100
    k_pre: int | None = None
    reranker: str | None = None
    expand: bool = False

    def validate(self, caps: set[str]) -> RankedPlan:
        if self.route not in NEEDS:
            raise ValueError(f"no route {self.route}")
        if self.expand and self.route != "D":
            raise ValueError("a graph hop is legal on route D only")
        if self.reranker and (self.k_pre is None or self.k_pre > self.k_ret):
            raise ValueError("a reranker needs a cut within the retrieval width")
        if self.k_pre is not None and not self.reranker:
            raise ValueError("a cut without a reranker")
        if missing := NEEDS[self.route] - caps:
            raise ViewUnavailable(f"route {self.route} needs {sorted(missing)}")
        return self


BUDGETS = {"low": (50, None, None), "medium": (100, 30, "small"), "high": (300, 100, "large")}
STRUCTURAL_WORDS = ["uses", "defines", "calls"]


def signals(queries: DataFrame, df: DataFrame, symbols: DataFrame) -> DataFrame:
    """query_id, text, lexical, semantic, structural: df is (term, df), symbols is (symbol)."""
    t = queries.select("query_id", F.explode(F.array_distinct(tokens(F.col("text")))).alias("term"))
    rare = t.join(df.filter("df = 1"), "term", "left_semi").select("query_id").distinct().withColumn("rare", F.lit(True))
    named = t.filter((F.length("term") >= 4) | F.col("term").isin(STRUCTURAL_WORDS)).join(symbols.select(F.col("symbol").alias("term")).union(symbols.sparkSession.createDataFrame([(w,) for w in STRUCTURAL_WORDS], "term string")).distinct(), "term", "left_semi").select("query_id").distinct().withColumn("named", F.lit(True))
    marks = F.col("text").rlike(r'["*+?\[\]()|\\]')
    return queries.join(rare, "query_id", "left").join(named, "query_id", "left").select("query_id", "text", (marks | F.coalesce("rare", F.lit(False))).alias("lexical"), (F.size(tokens(F.col("text"))) >= 6).alias("semantic"), F.coalesce("named", F.lit(False)).alias("structural"))


def choose(s: DataFrame, budget: str, caps: set[str]) -> DataFrame:
    """query_id, route, k_ret, k_pre, reranker, expand for a batch of queries, by fixed rules."""
    has = lambda r: F.lit(NEEDS[r] <= caps)
    if not any(NEEDS[r] <= caps for r in "ABC"):
        raise ViewUnavailable("no route is open")
    route = F.when(F.col("structural") & has("D"), "D").when(F.col("lexical") & F.col("semantic") & has("C"), "C").when(F.col("lexical") & has("A"), "A").when(has("B"), "B").when(has("C"), "C").otherwise("A")
    k_ret, k_pre, reranker = BUDGETS[budget]
    return s.select("query_id", route.alias("route"), F.lit(k_ret).alias("k_ret"), F.lit(k_pre).cast("int").alias("k_pre"), F.lit(reranker).cast("string").alias("reranker")).withColumn("expand", (F.col("route") == "D") & F.lit(budget != "low"))


@dataclass
class Views:
    """Handles of one snapshot's or corpus's views."""

    units: DataFrame  # unit_id, path, start, end, text
    vectors: DataFrame | None = None
    encoder: dense.Encoder | None = None
    idf: DataFrame | None = None
    edges: DataFrame | None = None
    lexical: lexical.Index | None = None


def lexical_list(v: Views, q: DataFrame, k: int) -> DataFrame:
    return lexical.bm25(q, v.lexical or v.units, k)


def dense_list(v: Views, q: DataFrame, k: int) -> DataFrame:
    qv = dense.encode(q.withColumnRenamed("query_id", "unit_id"), v.encoder, v.idf).withColumnRenamed("unit_id", "query_id")
    return dense.search_sparse(qv, v.vectors, k)


def dense_lists(v: Views, q: DataFrame, encoders: list[dense.Encoder], k: int) -> DataFrame:
    """encoder, query_id, unit_id, score, rank: dense_list of several encoders over tokens, of which the units are read and weighed once."""
    dims = tuple(e.dim for e in encoders)
    asked, name = None, F.concat_ws("|", "part", "query_id")
    for i, (e, start) in enumerate(zip(encoders, rows.starts(dims), strict=True)):
        own = dense.encode(q.withColumnRenamed("query_id", "unit_id"), e, v.idf).select(F.lit(i).alias("part"), F.col("unit_id").alias("query_id"), (F.col("bucket") + start).alias("f"), "w")
        asked = own if asked is None else asked.unionByName(own)
    found = lists.search(rows.weigh(v.lexical.counts, v.idf, dims), asked.withColumn("query_id", name), k)
    names = F.array(*[F.lit(e.name) for e in encoders])
    at = F.instr("query_id", "|")
    return found.select(names[F.substring("query_id", F.lit(1), at - 1).cast("int")].alias("encoder"), F.expr("substring(query_id, instr(query_id, '|') + 1)").alias("query_id"), "unit_id", "score", "rank")


def graph_seeded(v: Views, q: DataFrame, seeds: int, k: int) -> DataFrame:
    """Route D: sparse seeds, one hop over reference edges; no fusion.  Without stored edges those of the seeds are derived."""
    at = v.units.select("unit_id", "path", "start", vid_of(F.col("path"), F.col("start")).alias("vid"))
    s = store.few(store.few(lexical_list(v, q, seeds)).join(at, "unit_id"))
    g = rank.graph_list(s, v.edges if v.edges is not None else edges_of_lines(v.units, s), seeds)
    return g.filter(F.col("rank") <= k)


def edges_of_lines(u: DataFrame, lines: DataFrame) -> DataFrame:
    """The reference edges between two lines that some lines (path, start) have, for one hop, written once."""
    return store.few(structure.incident(u, lines, store.few).filter("etype = 'reference' and src <> dst"))


def run(plan: RankedPlan, v: Views, q: DataFrame, k_out: int) -> DataFrame:
    """Ranked list of a batch of queries on one plan."""
    if plan.route == "A":
        out = lexical_list(v, q, plan.k_ret)
    elif plan.route == "B":
        out = dense_list(v, q, plan.k_ret)
    elif plan.route == "C":
        out = rank.rrf([(lexical_list(v, q, plan.k_ret), 1.0), (dense_list(v, q, plan.k_ret), 1.0)], plan.k_ret)
    elif plan.expand:
        at = v.units.select("unit_id", F.concat("path", F.lit("#"), F.col("start").cast("string")).alias("vid"))
        out = graph_seeded(v, q, 10, plan.k_ret).join(at, "vid").select("query_id", "unit_id", (1 / F.col("rank")).alias("score"), "rank")
    else:
        out = lexical_list(v, q, plan.k_ret)
    if plan.reranker:
        text = q.select("query_id", F.col("text").alias("query_text"))
        few = out.filter(F.col("rank") <= plan.k_pre)
        return rank.pointwise(few.join(v.units.select("unit_id", "text"), "unit_id").join(text, "query_id"), plan.reranker, plan.k_pre, k_out)
    return out.filter(F.col("rank") <= k_out)


def equal_budget(arms: dict[str, DataFrame], budget: int) -> DataFrame:
    """arm, query_id, unit_id, rank: every arm may hand on `budget` candidates of a query, not more."""
    out = None
    for name, df in arms.items():
        a = df.filter(F.col("rank") <= budget).select(F.lit(name).alias("arm"), "query_id", "unit_id", "rank")
        out = a if out is None else out.unionByName(a)
    return out


@dataclass
class Pipeline:
    """An explicit chain of operators outside the routes: each maps a DataFrame to the next."""

    steps: list[tuple[str, Callable[[DataFrame], DataFrame]]] = field(default_factory=list)

    def then(self, name: str, f: Callable[[DataFrame], DataFrame]) -> Pipeline:
        return Pipeline([*self.steps, (name, f)])

    def __call__(self, df: DataFrame) -> DataFrame:
        for _, f in self.steps:
            df = f(df)
        return df


def vid_of(path: Column, line: Column) -> Column:
    return F.concat(path, F.lit("#"), line.cast("string"))


def reference_edges(l2: DataFrame) -> DataFrame:
    return structure.edges(structure.occurrences(l2))
