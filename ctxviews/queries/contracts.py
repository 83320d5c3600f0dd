"""What the catalog, sessions, plans, tools and the trace accept and refuse, as rows.

Each query runs the real objects and reports what came of it; its SQL is the contract.
"""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ctxviews.functions.text import md5_number, usage
from ctxviews.plans import catalog, plan, session, store, tools, trace
from ctxviews.queries import num, query
from ctxviews.sources.tables import files, table


def outcome(f) -> str:
    """ok, or the name of what was raised."""
    try:
        f()
        return "ok"
    except Exception as e:
        return type(e).__name__


def values(rows: list[tuple], names: str) -> str:
    text = ", ".join("(" + ", ".join("null" if v is None else f"'{v}'" if isinstance(v, str) else str(v).lower() for v in r) + ")" for r in rows)
    return f"select * from (values {text}) t({names})"


def built(spark, d) -> tuple[str, str]:
    """(root, version) of a catalog with two good views and one whose preparation is missing."""
    root = f"{store.shared_dir(spark)}/ctxviews-catalog-{uuid.uuid4().hex}"
    u = files(spark, d).select(F.col("path").alias("unit_id"), "text")
    few = lambda x: x.groupBy(F.length("unit_id").alias("n")).count()
    catalog.materialize(root, "v1", {v: catalog.builder(v, u, few) for v in ("lexical", "structural", "dense")})
    return root, "v1"


@query("u_build", values([("lexical", "ok", "text_search", None), ("structural", "failed", "", "BuildPreparationMissing"), ("dense", "ok", "semantic_search", None)], "view, status, capabilities, error"))
def _(spark, d):
    """Builders run one after another; one that lacks its preparation fails and leaves the others alone."""
    rows = [(e.view, e.status, ",".join(e.capabilities), e.error.split(":")[0] if e.error else None) for e in catalog.read(*built(spark, d))]
    return spark.createDataFrame(rows, "view string, status string, capabilities string, error string")


OPENED = [("lexical", "ok", 1, 0), ("lexical, dense", "ok", 2, 0), ("lexical behind head", "ok", 1, 1), ("structural", "ViewUnavailable", 0, 0), ("unknown", "ViewUnavailable", 0, 0), ("no catalog", "ViewUnavailable", 0, 0), ("old schema", "ViewSchemaMismatch", 0, 0)]


@query("u_open", values(OPENED, "request, outcome, handles, warnings"))
def _(spark, d):
    """Only needed views open; failed, unknown and outdated ones are refused, nothing is put in their place."""
    root, v = built(spark, d)
    old = [e for e in catalog.read(root, v)]
    for e in old:
        e.schema_version = 0
    catalog.publish(root, "v0", old)
    asked = {"lexical": (v, ["lexical"], None), "lexical, dense": (v, ["lexical", "dense"], None), "lexical behind head": (v, ["lexical"], "v2"), "structural": (v, ["lexical", "structural"], None), "unknown": (v, ["other"], None), "no catalog": ("v9", ["lexical"], None), "old schema": ("v0", ["lexical"], None)}
    rows = []
    for name, (version, needs, head) in asked.items():
        got = {}
        result = outcome(lambda a=(version, needs, head), got=got: got.update(x=catalog.open_views(spark, root, *a)))
        handles, warnings = got.get("x", ({}, []))
        rows.append((name, result, len(handles), len(warnings)))
    return spark.createDataFrame(rows, "request string, outcome string, handles int, warnings int")


MODES = [("views", "ok", "views"), ("catalog", "ok", "catalog"), ("repo", "ok", "repo"), ("none", "ValueError", None), ("two", "ValueError", None)]


@query("u_entry_modes", values(MODES, "given, outcome, mode"))
def _(spark, d):
    """Exactly one of three ways in; a catalog that is there is not built again."""
    root, v = built(spark, d)

    def never(location):
        raise AssertionError("built again")

    asked = {"views": {"views": {}}, "catalog": {"catalog": (root, v, ["dense"])}, "repo": {"repo": (root, v, {"lexical": never})}, "none": {}, "two": {"views": {}, "catalog": (root, v, [])}}
    rows = []
    for name, given in asked.items():
        got = {}
        result = outcome(lambda g=given, got=got: got.update(x=session.connect(spark, **g)))
        rows.append((name, result, got["x"].mode if got else None))
    return spark.createDataFrame(rows, "given string, outcome string, mode string")


PURPOSES = ("chunk", "graph", "incremental", "live")
BACKENDS = {"documents": ("lines", "occurrences", "closure", "scan"), "pages": ("elements", "href", "file", "scan"), "benchmark": ("lines", None, None, None), "conversations": ("lines", None, None, None)}


TEXTS = {"documents": "text", "pages": "html", "benchmark": "text", "conversations": "text"}
BACKEND_ROWS = values([(s, p, b) for s, bs in BACKENDS.items() for p, b in zip(PURPOSES, bs, strict=True)], "source, purpose, backend")


@query("u_backends", f"with b as ({BACKEND_ROWS}), t as (" + " union all ".join(f"select '{s}' as source, {c} as text from {s}" for s, c in TEXTS.items()) + ") select source, purpose, backend, count(*) as files, sum(length(coalesce(text, '')))::bigint as chars from t join b using (source) group by all")
def _(spark, d):
    """What each backend serves: the files and characters of each kind for each purpose; kinds without a backend stand with null."""
    rows = []
    for s in catalog.BackendRegistry.TIERS:
        for p in PURPOSES:
            got = {}
            outcome(lambda s=s, p=p, got=got: got.update(x=catalog.BackendRegistry.pick(s, p)))
            rows.append((s, p, got.get("x")))
    picked, texts = spark.createDataFrame(rows, "source string, purpose string, backend string"), None
    for s, c in TEXTS.items():
        t = table(spark, d, s).select(F.lit(s).alias("source"), F.length(F.coalesce(c, F.lit(""))).alias("n"))
        texts = t if texts is None else texts.unionByName(t)
    return texts.groupBy("source").agg(F.count("*").alias("files"), F.sum("n").cast("long").alias("chars")).join(F.broadcast(picked), "source").select("source", "purpose", "backend", "files", "chars")


TOOL_VIEWS = {"semantic_search": "dense", "bm25_search": "lexical", "regex_search": "lexical", "trigram_search": "lexical", "dependencies": "structural", "definition": "structural", "references": "structural", "route": "structural", "catalog": ""}


def asked(names) -> str:
    """SQL: the message of a conversation asks for one of names, by the hash of its text."""
    return f"[{', '.join(repr(n) for n in names)}][{num('text')} % {len(names)} + 1]"


def asks(spark, d, names, column: str):
    """The messages of the conversations with the name that each asks for."""
    m = table(spark, d, "conversations")
    return m.withColumn(column, F.element_at(F.array(*map(F.lit, names)), (md5_number(F.col("text")) % len(names) + 1).cast("int")))


@query("u_tools", f"with t as ({values([(t, v, v in ('lexical', '')) for t, v in TOOL_VIEWS.items()], 'tool, needs, open_with_text_search')}) select tool, needs, open_with_text_search, count(*) as requests from (select {asked(TOOL_VIEWS)} as tool from conversations where text is not null) join t using (tool) group by all")
def _(spark, d):
    """The tools that messages ask for: the view that each needs, whether it is open to a session with text search alone, how many ask."""
    rows = [(t, ",".join(sorted(tools.required_views([t]))), bool(tools.guard([t], {"text_search"})[0])) for t in tools.NEEDS]
    known = spark.createDataFrame(rows, "tool string, needs string, open_with_text_search boolean")
    return asks(spark, d, list(TOOL_VIEWS), "tool").groupBy("tool").agg(F.count("*").alias("requests")).join(F.broadcast(known), "tool").select(*known.columns, "requests")


PLANS = {
    "A": (plan.RankedPlan("A"), "ok"), "B without vectors": (plan.RankedPlan("B"), "ViewUnavailable"), "C without vectors": (plan.RankedPlan("C"), "ViewUnavailable"), "D with a hop": (plan.RankedPlan("D", expand=True), "ok"),
    "A with a hop": (plan.RankedPlan("A", expand=True), "ValueError"), "unknown": (plan.RankedPlan("E"), "ValueError"), "reranker without a cut": (plan.RankedPlan("A", reranker="small"), "ValueError"),
    "cut beyond the width": (plan.RankedPlan("A", 10, 20, "small"), "ValueError"), "cut without a reranker": (plan.RankedPlan("A", k_pre=5), "ValueError"), "reranked": (plan.RankedPlan("A", 100, 30, "small"), "ok"),
}


@query("p_legality", f"with p as ({values([(n, o) for n, (_, o) in PLANS.items()], 'name, outcome')}) select conv_id, turn, name, outcome from (select conv_id, turn, {asked(PLANS)} as name from conversations where text is not null) join p using (name)")
def _(spark, d):
    """Which plans a session with text search and references accepts, for the plan that each message asks for."""
    rows = [(n, outcome(lambda p=p: p.validate({"text_search", "references"}))) for n, (p, _) in PLANS.items()]
    judged = spark.createDataFrame(rows, "name string, outcome string")
    return asks(spark, d, list(PLANS), "name").join(F.broadcast(judged), "name").select("conv_id", "turn", "name", "outcome")


USED = "len(regexp_extract_all(coalesce(text, ''), '[\\p{L}\\p{N}]+|[^\\s\\p{L}\\p{N}]'))"


@query("c_trace", f"with e as (select conv_id::varchar as session, row_number() over (partition by conv_id order by turn) - 1 as seq, role as event, case when role = 'assistant' then 0 else {USED} end::bigint as prompt_tokens, case when role = 'assistant' then {USED} else 0 end::bigint as completion_tokens from conversations) select *, sum(prompt_tokens) over (partition by session order by seq)::bigint as prompt_so_far from e")
def _(spark, d):
    """The ledgers of all conversations, appended in two parts (up to turn 1, what follows) and read again in order."""
    from pyspark.sql import Window as W

    path = f"{store.shared_dir(spark)}/ctxviews-trace-{uuid.uuid4().hex}"
    said, spoken = usage(F.col("text")), F.coalesce(F.col("role") == "assistant", F.lit(False))
    none = F.lit(None).cast("string")
    e = table(spark, d, "conversations").select(F.col("conv_id").cast("string").alias("session"), F.col("role").alias("event"), none.alias("view"), none.alias("provider"), F.when(spoken, 0).otherwise(said).alias("prompt_tokens"), F.when(spoken, said).otherwise(0).alias("completion_tokens"), "turn")
    for part in ("turn <= 1", "turn > 1"):
        trace.extend(e.filter(part), path, "turn")
    so_far = F.sum("prompt_tokens").over(W.partitionBy("session").orderBy("seq"))
    return spark.read.schema(trace.SCHEMA).parquet(path).select("session", "seq", "event", "prompt_tokens", "completion_tokens", so_far.alias("prompt_so_far"))
