"""Navigation (static against live) and maintenance of the structural and dense views."""

from __future__ import annotations

from pyspark.sql import functions as F

from ctxviews.functions.text import md5_number
from ctxviews.operators import costs, dense, lists, maintain, metrics, navigate, units, versions
from ctxviews.plans.corpus import Corpus
from ctxviews.plans.store import kept, stored
from ctxviews.queries import FILES, OCC, TOKEN, num, query
from ctxviews.sources.tables import files, scope, table

# --- navigation -------------------------------------------------------------------------------

REQS = """, an as (select *, row_number() over (partition by repo, lang order by path, line, col) - 1 as at0, count(*) over (partition by repo, lang) as n from occ where role = 2),
 pk as (select * from an where n <= 5 or list_contains([n // 10, 3 * n // 10, 5 * n // 10, 7 * n // 10, 9 * n // 10], at0)),
 reqs as (select c||':'||path||':'||line||':'||col as req_id, repo, lang, c as capability, path, line, col, symbol from pk, (select unnest(['definition','references']) as c))"""


def _answers_sql(key: str, asked: str, defs: str, uses: str) -> str:
    return f""", fd as (select r.req_id, r.capability, d.path as lp, d.line as ll, case when d.path = r.path and d.line <= r.line then 0 else 1 end as far, case when d.path = r.path and d.line <= r.line then -d.line else 0 end as place from {asked} r join {defs} d on d.repo = r.repo and d.lang = r.lang and d.{key} = r.{key} where r.capability = 'definition'
 union all select r.req_id, r.capability, u.path, u.line, 0, 0 from {asked} r join (select distinct repo, lang, path, line, {key} from {uses}) u on u.repo = r.repo and u.lang = r.lang and u.{key} = r.{key} where r.capability = 'references'),
 lm as (select *, row_number() over (partition by req_id order by far, place, lp, ll) as k from fd qualify k <= case when capability = 'definition' then 8 else 40 end),
 st as (select req_id, string_agg(lp||':'||ll, ',' order by lp, ll) as locs from (select distinct req_id, lp, ll from lm) group by req_id),
 ans as (select r.req_id, r.lang, r.capability, coalesce(st.locs, '') as locs from reqs r left join st using (req_id))"""


STATIC = OCC + REQS + _answers_sql("symbol", "reqs", "(select * from occ where role = 1)", "occ")
LIVE = OCC + REQS + f", wr0 as (select repo, lang, path, line, regexp_extract_all(text, {TOKEN}) as ts from l2), wr as (select repo, lang, path, line, unnest(range(len(ts)))::int as col, unnest(ts) as written from wr0), asked as (select r.*, w.written from reqs r join wr w on w.path = r.path and w.line = r.line and w.col = r.col)" + _answers_sql("written", "asked", "(select * from wr where col = 0)", "wr")


def nav(spark, d):
    o = Corpus(spark, d).occurrences()
    return o, navigate.requests(o)


@query("q3_requests", f"with {OCC}{REQS} select req_id, repo, lang, capability, path, line, col, symbol from reqs")
def _(spark, d):
    return nav(spark, d)[1]


@query("q3_static_locs", f"with {STATIC} select req_id, capability, locs, 'static' as provider, '0' as version, 'occurrence' as granularity from ans")
def _(spark, d):
    o, r = nav(spark, d)
    return navigate.static(r, o).select("req_id", "capability", F.concat_ws(",", "locs").alias("locs"), "provider", "version", "granularity")


@query("q3_live_locs", f"with {LIVE} select req_id, capability, locs, 'live' as provider, 'worktree' as version, 'text' as granularity from ans")
def _(spark, d):
    _, r = nav(spark, d)
    return navigate.live(r, units.level2(files(spark, d))).select("req_id", "capability", F.concat_ws(",", "locs").alias("locs"), "provider", "version", "granularity")


@query("q3_match_rate", f"with a as (with {STATIC} select * from ans), b as (with {LIVE} select * from ans) select a.capability, a.lang, count(*) as n, count(*) filter (where a.locs = b.locs) as matched, round(count(*) filter (where a.locs = b.locs) / count(*), 6) as rate, count(*) filter (where a.locs = b.locs and a.locs <> '') as \"both\" from a join b using (req_id) group by all")
def match(spark, d):
    o, r = nav(spark, d)
    return metrics.match_rate(navigate.static(r, o), navigate.live(r, units.level2(files(spark, d))), ["capability", "lang"])


FALLBACK = OCC + """, rq as (select 'p'||doc_id as req_id, repo, lang, path, (doc_id % 5)::int as line, (doc_id % 9)::int as col from files),
 lc as (select r.*, o.symbol as exact, (select arg_max(x.symbol, x.line) from occ x where x.role = 1 and x.repo = r.repo and x.lang = r.lang and x.path = r.path and x.line <= r.line) as node from rq r left join occ o on o.repo = r.repo and o.lang = r.lang and o.path = r.path and o.line = r.line and o.col = r.col),
 reqs as (select req_id, repo, lang, path, line, col, coalesce(exact, node) as symbol, case when exact is not null then 'occurrence' when node is not null then 'enclosing' else 'none' end as granularity, 'definition' as capability from lc)""" + _answers_sql("symbol", "reqs", "(select * from occ where role = 1)", "occ")


@query("q3_fallback", f"with {FALLBACK} select a.req_id, a.locs, r.granularity from ans a join reqs r using (req_id)")
def _(spark, d):
    """Definitions at positions that need not be occurrences: the enclosing node answers, and says so."""
    o, f = Corpus(spark, d).occurrences(), files(spark, d)
    r = f.select(F.concat(F.lit("p"), F.col("doc_id").cast("string")).alias("req_id"), "repo", "lang", F.lit("definition").alias("capability"), "path", (F.col("doc_id") % 5).cast("int").alias("line"), (F.col("doc_id") % 9).cast("int").alias("col"))
    return navigate.static(r, o).select("req_id", F.concat_ws(",", "locs").alias("locs"), "granularity")


TIMINGS = "tm as (select user_id::varchar as req_id, case when event_type in ('view', 'click') then 'static' else 'live' end as provider, value as millis from events where value > 0)"


@query("q3_latency_summary", f"with {TIMINGS}, m as (select req_id, median(millis) filter (where provider = 'static') as s, median(millis) filter (where provider = 'live') as l from tm group by req_id) select count(*) as n, round(median(s), 6) as p50_static, round(median(l), 6) as p50_live, round(median(l - s), 6) as median_saving, round(median(l / s), 6) as median_ratio from m")
def _(spark, d):
    """The aggregation on events, whose values stand for milliseconds (a user's views and clicks for the static provider,
    other events for the live one), for its arithmetic only; q3_latency_measured has real ones."""
    static = F.coalesce(F.col("event_type").isin("view", "click"), F.lit(False))
    t = table(spark, d, "events").filter("value > 0").select(F.col("user_id").cast("string").alias("req_id"), F.when(static, "static").otherwise("live").alias("provider"), F.col("value").alias("millis"))
    return metrics.conditional_latency(t)


# --- versions ------------------------------------------------------------------------------------


def _evolve_sql() -> str:
    s = f"{FILES}, cr as (select repo, lang from (select repo, lang, row_number() over (partition by lang order by md5(repo)) as n from (select distinct repo, lang from files)) where n <= 2), b0 as (select f.repo, f.lang, f.doc_id, f.path, string_split(f.text, chr(10)) as l0 from files f join cr on cr.repo = f.repo and cr.lang = f.lang), e0 as (select *, coalesce(lead(l0[1]) over (partition by repo, lang order by doc_id), first_value(l0[1]) over (partition by repo, lang order by doc_id)) as donor from b0)"
    for t in range(1, 6):
        o = f"l{t - 1}"
        s += f""", h{t} as (select *, {num(f"doc_id||'|{t}'")} as h, ({num(f"doc_id||'|{t}'")} // 10) % len({o}) as p from e{t - 1}),
 e{t} as materialized (select * exclude (h, p), case when {o} is null then null when h % 10 = 0 then {o}[1:p] || [donor] || {o}[p+2:] when h % 10 = 1 then {o}[1:p] || [donor] || {o}[p+1:] when h % 10 = 2 and len({o}) > 1 then {o}[1:p] || {o}[p+2:] when h % 10 = 3 and h % 3 = 0 then null else {o} end as l{t}, case when h % 10 = 4 and {o} is not null then {o} || [donor] end as a{t} from h{t})"""
    parts = []
    for t in range(6):
        parts.append(f"select repo, lang, {t} as step, path, l{t} as lines from e5")
        parts += [f"select repo, lang, {t}, path||'_v{k}', a{k} from e5" for k in range(1, t + 1)]
    return s + ", ver as materialized (select * from (" + " union all ".join(parts) + ") where lines is not null)"


EVOLVE = _evolve_sql()
CHANGED = EVOLVE + """, vo as materialized (select repo||'@'||(step+1) as repo, lang, path, lines from ver where step < 5), vn as materialized (select repo||'@'||step as repo, lang, path, lines from ver where step > 0),
 ch as materialized (select coalesce(a.repo, b.repo) as repo, coalesce(a.lang, b.lang) as lang, coalesce(a.path, b.path) as path, case when a.path is null then 'added' when b.path is null then 'deleted' else 'modified' end as kind from vo a full join vn b on a.repo = b.repo and a.lang = b.lang and a.path = b.path where a.path is null or b.path is null or array_to_string(a.lines, chr(10)) <> array_to_string(b.lines, chr(10)))"""
HUNKS = CHANGED + """, pr as (select a.repo, a.lang, a.path, a.lines as o, b.lines as n, least(len(a.lines), len(b.lines)) as m from vo a join vn b on a.repo = b.repo and a.lang = b.lang and a.path = b.path join ch on ch.repo = a.repo and ch.lang = a.lang and ch.path = a.path where ch.kind = 'modified'),
 sf as (select *, coalesce(list_position(list_transform(range(m), lambda i: o[len(o) - i] = n[len(n) - i]), false) - 1, m) as hi from pr),
 pf as (select *, coalesce(list_position(list_transform(range(m - hi), lambda i: o[i + 1] = n[i + 1]), false) - 1, m - hi) as lo from sf),
 hk as materialized (select repo, lang, path, lo::int as old_start, (len(o) - hi - lo)::int as old_len, lo::int as new_start, (len(n) - hi - lo)::int as new_len from pf)"""


def both(spark, d):
    return versions.transitions(stored(spark, d, "versions", lambda: versions.evolve(files(spark, d))))


def graph(spark, d, side: str):
    """The stored graph of every transition's old or new version (the new one for evaluation only)."""
    v = both(spark, d)[side == "new"]
    put = lambda name, build: stored(spark, d, f"{side}-graph-{name}", build)
    t = put("tokens", lambda: maintain.token_index(v))
    decl = put("decl", lambda: maintain.declared(t))
    refs = put("refs", lambda: maintain.resolve(t, decl))
    return maintain.Graph(put("files", lambda: v.select("repo", "lang", "path")), t, decl, refs, put("imports", lambda: maintain.imports_of(refs)))


def transition(spark, d):
    return maintain.Transition.of(*both(spark, d), graph(spark, d, "old"), kept)


@query("w_edit_script", f"with {EVOLVE} select repo, lang, step, path, sha256(array_to_string(lines, chr(10))) as sha from ver")
def _(spark, d):
    return versions.evolve(files(spark, d)).select("repo", "lang", "step", "path", F.sha2(F.concat_ws("\n", "lines"), 256).alias("sha"))


@query("q4_changed_files", f"with {CHANGED} select repo, lang, path, kind from ch")
def _(spark, d):
    return versions.changed_files(*both(spark, d))


@query("q4_hunks", f"with {HUNKS} select * from hk")
def _(spark, d):
    old, new = both(spark, d)
    return versions.hunks(old, new, versions.changed_files(old, new))


def _occ_sql(src: str, p: str) -> str:
    return rf""", {p}l0 as (select repo, lang, path, unnest(range(len(lines)))::int as line, unnest(lines) as text from {src}), {p}l as (select * from {p}l0 where text <> ''), {p}d as materialized (select repo, lang, path, line, regexp_extract(lower(text), {TOKEN}, 0) as symbol from {p}l where length(regexp_extract(lower(text), {TOKEN}, 0)) >= 4), {p}t0 as (select repo, lang, path, line, regexp_extract_all(lower(text), {TOKEN}) as ts from {p}l), {p}t as (select repo, lang, path, line, unnest(range(len(ts)))::int as col, unnest(ts) as symbol from {p}t0), {p}occ as materialized (select t.*, case when col = 0 then 1 else 2 end as role from {p}t t where length(symbol) >= 4 and exists (select 1 from {p}d d where d.repo = t.repo and d.lang = t.lang and d.symbol = t.symbol)),
 {p}f as (select repo, lang, symbol, min(struct_pack(path := path, line := line)) as f from {p}d group by all), {p}n as (select u.repo, u.lang, u.path, u.line, u.col, max(d.line) as near from {p}occ u join {p}d d on d.repo = u.repo and d.lang = u.lang and d.path = u.path and d.symbol = u.symbol and d.line <= u.line where u.role = 2 group by all),
 {p}r as materialized (select u.repo, u.lang, u.path, u.line, u.col, u.symbol, case when n.near is not null then u.path else f.f.path end as def_path, coalesce(n.near, f.f.line) as def_line from {p}occ u join {p}f f on f.repo = u.repo and f.lang = u.lang and f.symbol = u.symbol left join {p}n n on n.repo = u.repo and n.lang = u.lang and n.path = u.path and n.line = u.line and n.col = u.col where u.role = 2)"""


def _facts_sql(name: str, refs: str) -> str:
    """CTEs {name}x (repo, lang, path, f) and {name} (repo, lang, n, digest) of the target graph with these references."""
    return f""", {name}i as (select repo, lang, path, symbol, def_path, min(struct_pack(line := line, col := col)) as a from {refs} where path <> def_path group by all),
 {name}x as (select repo, lang, path, 'file'||chr(31)||path as f from vn union all select repo, lang, path, 'symbol'||chr(31)||path||chr(31)||line||chr(31)||symbol from md
  union all select repo, lang, path, 'reference'||chr(31)||path||chr(31)||line||chr(31)||col||chr(31)||symbol||chr(31)||def_path||chr(31)||def_line from {refs}
  union all select repo, lang, path, 'import'||chr(31)||path||chr(31)||symbol||chr(31)||def_path||chr(31)||a.line||chr(31)||a.col from {name}i),
 {name} as (select repo, lang, count(*) as n, sum({num('f')})::bigint as digest from {name}x group by all)"""


def _shift(line: str, h: str) -> str:
    return f"case when {h}.path is null then {line} when {line} >= {h}.old_start and {line} < {h}.old_start + {h}.old_len then null when {line} >= {h}.old_start + {h}.old_len then {line} + {h}.new_len - {h}.old_len else {line} end"


TARGET = CHANGED + _occ_sql("vn", "m")
ARMS_SQL = HUNKS + _occ_sql("vo", "w") + _occ_sql("vn", "m") + f""", os as (select o.repo, o.lang, o.path, o.symbol, row_number() over (partition by o.repo, o.lang, o.path, o.symbol order by o.line)::int as ordinal, o.line as old_line from wd o join ch using (repo, lang, path)), ns as (select o.repo, o.lang, o.path, o.symbol, row_number() over (partition by o.repo, o.lang, o.path, o.symbol order by o.line)::int as ordinal, o.line as new_line from md o join ch using (repo, lang, path)),
 mp as (select os.*, {_shift('old_line', 'h')} as mapped from os left join hk h using (repo, lang, path)),
 jn as (select coalesce(a.repo, b.repo) as repo, coalesce(a.lang, b.lang) as lang, coalesce(a.path, b.path) as path, coalesce(a.symbol, b.symbol) as symbol, coalesce(a.ordinal, b.ordinal) as ordinal, a.old_line, a.mapped, b.new_line from mp a full join ns b on a.repo = b.repo and a.lang = b.lang and a.path = b.path and a.symbol = b.symbol and a.ordinal = b.ordinal),
 cls as materialized (select j.repo, j.lang, j.path, j.symbol, j.ordinal, case when new_line is null then 'deleted' when old_line is null then 'added' when coalesce(new_line >= h.new_start and new_line < h.new_start + h.new_len, false) or mapped is null or mapped <> new_line then 'affected' when old_line <> new_line then 'shifted' else 'unchanged' end as class, old_line, new_line from jn j left join hk h on h.repo = j.repo and h.lang = j.lang and h.path = j.path),
 gone as (select repo, lang, path, path as def_path from ch where kind = 'deleted'), al as (select repo, lang, path from ch where kind = 'added'),
 el as (select distinct repo, lang, path, unnest(range(new_start, new_start + new_len))::int as line from hk),
 rb0 as (select r.repo, r.lang, r.path, {_shift('r.line', 'a')} as line, r.col, r.symbol, r.def_path, {_shift('r.def_line', 'b')} as def_line from (select * from (select * from wr anti join gone using (repo, lang, path)) anti join gone using (repo, lang, def_path)) r left join hk a on a.repo = r.repo and a.lang = r.lang and a.path = r.path left join hk b on b.repo = r.repo and b.lang = r.lang and b.path = r.def_path),
 rb as materialized (select repo, lang, path, line::int as line, col, symbol, def_path, def_line::int as def_line from rb0 where line is not null and def_line is not null),
 sy as (select distinct repo, lang, symbol from cls where class in ('added', 'affected')), od as (select distinct repo, lang, symbol from md semi join ch using (repo, lang, path)),
 fl as (select repo, lang, path as def_path from ch), c as (select repo, lang, path, line, col, symbol, def_path, def_line from mr), o as (select repo, lang, path, line, col, symbol, def_path, def_line from wr),
 rs as materialized (select * from rb anti join sy using (repo, lang, symbol) union all select * from c semi join sy using (repo, lang, symbol) union all select * from (select * from c anti join sy using (repo, lang, symbol)) semi join el using (repo, lang, path, line) union all select * from (select * from c anti join sy using (repo, lang, symbol)) semi join al using (repo, lang, path)),
 rf as materialized (select * from (select * from (select * from o anti join ch using (repo, lang, path)) anti join od using (repo, lang, symbol)) anti join fl using (repo, lang, def_path) union all select * from c semi join ch using (repo, lang, path) union all select * from (select * from c anti join ch using (repo, lang, path)) semi join od using (repo, lang, symbol))"""
ARM_TABLES = {"file": "rf", "symbol": "rs", "closure": "c"}


@query("q4_symbol_classes", f"with {ARMS_SQL} select repo, lang, path, symbol, ordinal, class, old_line, new_line from cls")
def _(spark, d):
    return maintain.classify(transition(spark, d))


ACTIONS = """, key as (select repo, lang, path, line, col, symbol, def_path, def_line from mr), mv as (select r.repo, r.lang, r.path, r.line as was, r.col, r.symbol, r.def_path, r.def_line as dwas, """ + _shift("r.line", "a") + " as line, " + _shift("r.def_line", "b") + """ as def_line from wr r left join hk a on a.repo = r.repo and a.lang = r.lang and a.path = r.path left join hk b on b.repo = r.repo and b.lang = r.lang and b.path = r.def_path),
 ac as (select coalesce(v.repo, k.repo) as repo, coalesce(v.lang, k.lang) as lang, case when v.repo is null then 'added' when k.repo is null then 'deleted' when v.was = v.line and v.dwas = v.def_line then 'kept' else 'changed' end as action from mv v full join key k on v.repo = k.repo and v.lang = k.lang and v.path = k.path and v.line = k.line and v.col = k.col and v.symbol = k.symbol and v.def_path = k.def_path and v.def_line = k.def_line)"""


@query("q4_actions", f"with {ARMS_SQL}{ACTIONS} select repo, lang, action, count(*) as n from ac group by all")
def _(spark, d):
    """What happens to the references of every transition: kept, moved with their lines, deleted or added."""
    t = transition(spark, d)
    return maintain.fact_actions(t.old.refs, graph(spark, d, "new").refs, t).groupBy("repo", "lang", "action").agg(F.count("*").alias("n"))


@query("q4_rebased", f"with {ARMS_SQL} select * from rb")
def _(spark, d):
    t = transition(spark, d)
    return maintain.rebase_edges(t.old.refs, t)


@query("q4_invisible", f"with {ARMS_SQL}, li as (select repo, lang, path, line, symbol from md semi join ch using (repo, lang, path) where length(symbol) >= 6), ol as (select r.repo, r.lang, r.path, {_shift('r.line', 'a')} as line, r.symbol from wd r join ch on ch.repo = r.repo and ch.lang = r.lang and ch.path = r.path and ch.kind = 'modified' left join hk a on a.repo = r.repo and a.lang = r.lang and a.path = r.path) select repo, lang, path, line, symbol from wd anti join ch using (repo, lang, path) union all select * from li union all select * from (select * from ol where line is not null) anti join li using (repo, lang, path, line, symbol)")
def _(spark, d):
    """Vertices if the backend lists only symbols of six letters or more: the others stay where their line was not edited."""
    t = transition(spark, d)
    listed = maintain.declared(t.fresh).filter("length(symbol) >= 6")
    return maintain.vertices(t, listed)


@query("q4_graph_rebuilt", f"with {TARGET}{_facts_sql('dg', 'mr')} select * from dg")
def _(spark, d):
    return maintain.digest(maintain.facts(maintain.rebuild(both(spark, d)[1], kept)))


@query("q4_closure", f"with {TARGET}{_facts_sql('dg', 'mr')} select * from dg")
def _(spark, d):
    return maintain.digest(maintain.facts(maintain.ARMS["closure"](transition(spark, d), kept)))


@query("q4_graph_replaced", f"with {ARMS_SQL}{_facts_sql('dg', 'rf')} select * from dg")
def _(spark, d):
    return maintain.digest(maintain.facts(maintain.replace_files(transition(spark, d), kept)))


@query("q4_graph_repaired", f"with {ARMS_SQL}{_facts_sql('dg', 'rs')} select * from dg")
def _(spark, d):
    return maintain.digest(maintain.facts(maintain.repair(transition(spark, d), keep=kept)))


MATCH = f"with {ARMS_SQL}{_facts_sql('dt', 'mr')}{_facts_sql('df', 'rf')}{_facts_sql('ds', 'rs')}" + "".join(f", {n}z as (select repo, lang, count(*) as n, sum({num('f')})::bigint as digest from {n}x semi join ch using (repo, lang, path) group by all)" for n in ("dt", "df", "ds")) + """
 select t.repo, t.lang, t.repo||t.lang in (select repo||lang from ch) as source_changing, coalesce(f.n = t.n and f.digest = t.digest, false) as file_match, coalesce(s.n = t.n and s.digest = t.digest, false) as symbol_match, true as closure_match,
  coalesce(fz.n, 0) = coalesce(tz.n, 0) and coalesce(fz.digest, 0) = coalesce(tz.digest, 0) as file_scope, coalesce(sz.n, 0) = coalesce(tz.n, 0) and coalesce(sz.digest, 0) = coalesce(tz.digest, 0) as symbol_scope, true as closure_scope
 from dt t left join df f on f.repo = t.repo and f.lang = t.lang left join ds s on s.repo = t.repo and s.lang = t.lang left join dtz tz on tz.repo = t.repo and tz.lang = t.lang left join dfz fz on fz.repo = t.repo and fz.lang = t.lang left join dsz sz on sz.repo = t.repo and sz.lang = t.lang"""


def graph_match(spark, d):
    """repo, lang, source_changing; for each arm whether all facts, and those of changed files, equal the rebuilt target's."""
    t = transition(spark, d)
    want = kept(maintain.facts(graph(spark, d, "new")))
    truth, inside = maintain.digest(want), maintain.digest(maintain.in_scope(want, t))
    out = truth.select("repo", "lang").join(t.changed.select("repo", "lang").distinct().withColumn("c", F.lit(True)), ["repo", "lang"], "left").select("repo", "lang", F.coalesce("c", F.lit(False)).alias("source_changing"))
    one = lambda df, name: df.select("repo", "lang", F.struct("n", "digest").alias(name))
    for name, arm in maintain.ARMS.items():
        got = kept(maintain.facts(arm(t, kept)))
        for flag, a, b in ((f"{name}_match", truth, maintain.digest(got)), (f"{name}_scope", inside, maintain.digest(maintain.in_scope(got, t)))):
            m = one(a, "w").join(one(b, "g"), ["repo", "lang"], "full").select("repo", "lang", F.col("w").eqNullSafe(F.col("g")).alias(flag))
            out = out.join(m, ["repo", "lang"], "left").withColumn(flag, F.coalesce(flag, F.lit(flag.endswith("scope"))))
    return out


@query("q4_graph_match", MATCH)
def _(spark, d):
    return graph_match(spark, d)


@query("q4_match_counts", "select count(*) as transitions, count(*) filter (where source_changing) as source_changing, count(*) filter (where source_changing and file_match) as file, count(*) filter (where source_changing and symbol_match) as symbol, count(*) filter (where source_changing and closure_match) as closure, count(*) filter (where source_changing and file_match and symbol_match) as file_and_symbol, count(*) filter (where source_changing and symbol_scope) as symbol_scope from (" + MATCH + ")")
def _(spark, d):
    """How many source-changing transitions each arm gets right, and on how many two arms can be compared head to head."""
    m, c = graph_match(spark, d), F.col("source_changing")
    n = lambda x, name: F.count_if(c & x).alias(name)
    both_ = F.col("file_match") & F.col("symbol_match")
    return m.agg(F.count("*").alias("transitions"), F.count_if(c).alias("source_changing"), n(F.col("file_match"), "file"), n(F.col("symbol_match"), "symbol"), n(F.col("closure_match"), "closure"), n(both_, "file_and_symbol"), n(F.col("symbol_scope"), "symbol_scope"))


def _f1_sql(arm: str) -> str:
    key = "repo, lang, path, line, col, symbol, def_path, def_line"
    return f"select '{arm}' as arm, repo, lang, round(coalesce(sum(least(m1, m2)) / nullif(sum(m1), 0), 1), 6)::double as precision, round(coalesce(sum(least(m1, m2)) / nullif(sum(m2), 0), 1), 6)::double as recall, round(2 * sum(least(m1, m2)) / (sum(m1) + sum(m2)), 6)::double as f1 from (select {key}, sum(a) as m1, sum(b) as m2 from (select {key}, 1 as a, 0 as b from {ARM_TABLES[arm]} union all select {key}, 0, 1 from c) group by all) group by repo, lang"


@query("q4_edge_f1", f"with {ARMS_SQL} " + " union all ".join(f"select * from ({_f1_sql(a)})" for a in ARM_TABLES))
def _(spark, d):
    t, truth, out = transition(spark, d), graph(spark, d, "new").refs, None
    for name, arm in maintain.ARMS.items():
        r = metrics.edge_f1(arm(t, kept).refs, truth, ["repo", "lang"], maintain.EDGE).withColumn("arm", F.lit(name))
        out = r if out is None else out.unionByName(r)
    return out


def _served_sql(p: str, refs: str) -> str:
    """CTE {p}s: req_id, locs of the requests rq, answered from the declarations md and these references."""
    return f""", {p}x as (select distinct repo, lang, path, line, col from {refs}), {p}q as (select r.req_id, r.repo, r.lang, r.capability, r.path, r.line, case when x.path is not null then r.symbol else (select arg_max(d.symbol, d.line) from md d where d.repo = r.repo and d.lang = r.lang and d.path = r.path and d.line <= r.line) end as symbol from rq r left join {p}x x on x.repo = r.repo and x.lang = r.lang and x.path = r.path and x.line = r.line and x.col = r.col),
 {p}u as (select distinct repo, lang, symbol, path, line from (select repo, lang, symbol, path, line from md union all select repo, lang, symbol, path, line from {refs})),
 {p}k as (select * from {p}u qualify row_number() over (partition by repo, lang, symbol order by path, line) <= 40),
 {p}a as (select r.req_id, d.path as lp, d.line as ll, row_number() over (partition by r.req_id order by case when d.path = r.path and d.line <= r.line then 0 else 1 end, case when d.path = r.path and d.line <= r.line then -d.line else 0 end, d.path, d.line) as k from {p}q r join md d on d.repo = r.repo and d.lang = r.lang and d.symbol = r.symbol where r.capability = 'definition' union all select r.req_id, u.path, u.line, 0 from {p}q r join {p}k u on u.repo = r.repo and u.lang = r.lang and u.symbol = r.symbol where r.capability = 'references'),
 {p}s as (select req_id, string_agg(lp||':'||ll, ',' order by lp, ll) as locs from (select distinct req_id, lp, ll from {p}a where k <= 8) group by req_id)"""


REPLAY = f", rq as (select repo||'|'||lang||'|'||cap||':'||path||':'||line||':'||col as req_id, repo, lang, cap as capability, path, line, col, symbol from c semi join ch using (repo, lang, path), (select unnest(['definition','references']) as cap)){_served_sql('t', 'mr')}{_served_sql('rr', 'rs')}"


@query("q4_replay", f"with {ARMS_SQL}{REPLAY} select r.repo, r.lang, r.capability, a.arm, count(*) as requests, round(avg(case when a.arm = 'closure' then 1.0 when coalesce(t.locs, '') = coalesce(s.locs, '') then 1.0 else 0.0 end), 6) as agreement from rq r left join ts t using (req_id) left join rs_ s using (req_id), (select unnest(['symbol','closure']) as arm) a group by all".replace("rs_ s", "rrs s"))
def _(spark, d):
    """Definition and reference requests at all anchors of changed files, answered from the repaired and
    the rebuilt graph after both were written and read again: how many agree, for two arms."""
    t = transition(spark, d)
    want = kept(maintain.occurrences_of(graph(spark, d, "new")))
    anchors = want.filter("role = 2").join(t.changed.select("repo", "lang", "path"), ["repo", "lang", "path"], "left_semi")
    reqs = anchors.withColumn("capability", F.explode(F.array(*map(F.lit, navigate.LIMITS)))).select(F.concat_ws("|", "repo", "lang", navigate.req_id()).alias("req_id"), "repo", "lang", "capability", "path", "line", "col", "symbol")
    truth = kept(navigate.static(reqs, want).select("req_id", "repo", "lang", "capability", F.col("locs").alias("want")))
    out = None
    for name in ("symbol", "closure"):
        served = kept(maintain.occurrences_of(maintain.ARMS[name](t, kept)))
        got = navigate.static(reqs, served).select("req_id", "locs")
        j = truth.join(got, "req_id", "left").groupBy("repo", "lang", "capability").agg(F.count("*").alias("requests"), F.round(F.avg(F.coalesce(F.col("want") == F.col("locs"), F.lit(False)).cast("double")), 6).alias("agreement")).withColumn("arm", F.lit(name))
        out = j if out is None else out.unionByName(j)
    return out


REQUESTS = """, tc as (select r.*, exists (select 1 from el e where e.repo = r.repo and e.lang = r.lang and e.path = r.path and e.line = r.line) or exists (select 1 from al a where a.repo = r.repo and a.lang = r.lang and a.path = r.path) as hit, (select min(new_start + new_len) from hk h where h.repo = r.repo and h.lang = r.lang and h.path = r.path and new_len <> old_len) as from_line from c r semi join ch using (repo, lang, path)),
 us as (select repo, lang, count(*) as file_defs, count(*) filter (where hit or coalesce(line >= from_line, false)) as symbol_defs from tc group by all), sc as (select repo, lang, count(*) as file_refs, count(*) filter (where class = 'added') as symbol_refs from cls where new_line is not null group by all)"""


@query("q4_requests", f"with {ARMS_SQL}{REQUESTS} select coalesce(s.repo, u.repo) as repo, coalesce(s.lang, u.lang) as lang, coalesce(file_refs, 0) as file_refs, coalesce(file_defs, 0) as file_defs, coalesce(symbol_refs, 0) as symbol_refs, coalesce(symbol_defs, 0) as symbol_defs from sc s full join us u on s.repo = u.repo and s.lang = u.lang")
def _(spark, d):
    t = transition(spark, d)
    c = maintain.classify(t)
    new = graph(spark, d, "new").refs.join(t.changed.select("repo", "lang", "path"), ["repo", "lang", "path"], "left_semi")
    touched = maintain.edited(t, new).select("repo", "lang", "path", "line", "col", F.lit(True).alias("hit")).distinct()
    moved = t.hunks.filter("new_len <> old_len").groupBy("repo", "lang", "path").agg(F.min(F.col("new_start") + F.col("new_len")).alias("from_line"))
    u = new.join(touched, ["repo", "lang", "path", "line", "col"], "left").join(moved, ["repo", "lang", "path"], "left")
    state = F.when(F.col("hit"), "new").when(F.col("line") >= F.col("from_line"), "rebased").otherwise("kept")
    return maintain.request_counts(c, u.withColumn("state", state))


COSTS = f"ct as (select repo, lang, n % 3 > 0 as changed, n % 4 > 0 as matched, (60 + {num('repo||lang')} % 40) / (6 + ({num('lang||repo')} % 10) + 10.0 / 5) as gamma from (select repo, lang, row_number() over (order by repo, lang) as n from (select distinct source as repo, lang from documents)))"


@query("q4_speedup", f"with {COSTS} select 'symbol' as arm, count(*) as n, count(*) filter (where changed) as source_changing, count(*) filter (where changed and matched) as matched, round(quantile_cont(gamma, 0.25) filter (where changed and matched), 6) as q25, round(quantile_cont(gamma, 0.5) filter (where changed and matched), 6) as median, round(quantile_cont(gamma, 0.75) filter (where changed and matched), 6) as q75 from ct")
def _(spark, d):
    """Γ and its conditional summary on frozen costs: T_f = 60 + x, T_u = 6 + y, T_s = 10."""
    from pyspark.sql import Window as W

    s = table(spark, d, "documents").select(F.col("source").alias("repo"), "lang").distinct().withColumn("n", F.row_number().over(W.orderBy("repo", "lang")))
    gamma = costs.speedup(60 + md5_number(F.concat("repo", "lang")) % 40, 6 + md5_number(F.concat("lang", "repo")) % 10, F.lit(10.0))
    return costs.conditional_summary(s.select(F.lit("symbol").alias("arm"), (F.col("n") % 3 > 0).alias("changed"), (F.col("n") % 4 > 0).alias("matched"), gamma.alias("gamma")), ["arm"])


@query("q4_fresh_fresh", f"with {TARGET}, fr as (select repo, lang from (select distinct repo, lang from ch) order by repo, lang limit 4) select repo, lang, true as same from fr")
def _(spark, d):
    """Four transitions rebuilt twice, from differently dealt files: the facts must agree."""
    old, new = both(spark, d)
    four = versions.changed_files(old, new).select("repo", "lang").distinct().orderBy("repo", "lang").limit(4)
    own = new.join(four, ["repo", "lang"], "left_semi")
    a, b = (maintain.digest(maintain.facts(maintain.rebuild(x, kept))) for x in (own, own.repartition(5, "path")))
    return a.join(b.select("repo", "lang", F.col("digest").alias("again")), ["repo", "lang"]).select("repo", "lang", (F.col("digest") == F.col("again")).alias("same"))


# --- dense deltas -----------------------------------------------------------------------------------

VSIDE = lambda src, p: f", {p}0 as (select repo, lang, path, unnest(lines) as text from {src} where try_cast(regexp_extract(path, '([0-9]+)(_v[0-9])?$', 1) as bigint) not in (select doc_id from labels where toxic = 1)), {p} as (select repo, lang, sha256('hash256'||chr(31)||text) as ck from {p}0 where text <> '')"


@query("q4_vector_delta", f"with {CHANGED}{VSIDE('vo', 'x')}{VSIDE('vn', 'y')}, sk as (select distinct ck from x) select y.repo, y.lang, case when sk.ck is null then 'encode' else 'reuse' end as action, count(*) as n from y left join sk using (ck) group by all")
def _(spark, d):
    old, new = (_dense_units(v, spark, d) for v in both(spark, d))
    return dense.delta(old, new, "hash256").groupBy("repo", "lang", "action").agg(F.count("*").alias("n"))


def _dense_units(v, spark, d):
    doc = F.regexp_extract("path", r"([0-9]+)(_v[0-9])?$", 1).cast("long")
    own = scope(v.withColumn("doc_id", doc), table(spark, d, "labels"), "dense")
    u = own.select("repo", "lang", "path", F.posexplode("lines").alias("start", "text")).filter("text <> ''")
    return u.withColumn("unit_id", F.concat_ws("#", "repo", "path", F.col("start").cast("string")))


def vector_sides(spark, d):
    """(owner of each new unit, incremental index, fresh index, delta) of all transitions; an index is (unit_id, f, w).

    The stored vectors are kept by content key.  The incremental index keeps the rows of
    units that did not change, takes reused vectors from the store and encodes the rest.
    """
    old, new = (_dense_units(v, spark, d) for v in both(spark, d))
    e = dense.ENCODERS[2]
    idf = Corpus(spark, d).idf(e)  # frozen with the model
    key = dense.content_key("hash256")
    store = stored(spark, d, "vector-store", lambda: lists.grouped(dense.encode(old.select(key.alias("unit_id"), "text").distinct(), e, idf)).withColumnRenamed("unit_id", "content_key"), ("documents", "labels"))
    index = old.select("unit_id", key.alias("content_key")).join(store, "content_key")
    marked = kept(dense.delta(old, new, "hash256"))
    made = lists.grouped(dense.encode(marked.filter("action = 'encode'").select(F.col("content_key").alias("unit_id"), "text").distinct(), e, idf)).withColumnRenamed("unit_id", "content_key")
    inc = kept(dense.update(index, marked.select("unit_id", "content_key"), store.unionByName(made)))
    fresh = kept(lists.grouped(dense.encode(new, e, idf)))
    return new.select("unit_id", "repo", "lang"), inc.select("unit_id", "f", "w"), fresh, marked


def _own(index, owner):
    """An index whose features belong to their transition, so that one search serves all of them."""
    return index.join(owner, "unit_id").select("unit_id", F.transform("f", lambda b: F.concat_ws("|", "repo", "lang", b.cast("string"))).alias("f"), "w")


@query("q4_vector_match")
def _(spark, d):
    """Incremental against fresh vectors by transition: identities, numbers, and the exact top ten of every
    benchmark query, in order and as sets; with the share encoded and what that does to the index."""
    owner, inc, fresh, marked = vector_sides(spark, d)
    rows = lambda x: x.select("unit_id", F.explode(F.map_from_arrays("f", "w")).alias("bucket", "w"))
    j = rows(fresh).join(rows(inc).withColumnRenamed("w", "w2"), ["unit_id", "bucket"], "full").withColumn("diff", F.abs(F.coalesce("w", F.lit(0.0)) - F.coalesce("w2", F.lit(0.0))))
    same = j.join(owner, "unit_id").groupBy("repo", "lang").agg(F.countDistinct("unit_id").alias("units"), (F.count_if(F.col("w").isNull() | F.col("w2").isNull()) == 0).alias("identities"), (F.max("diff") < 1e-9).alias("vectors"))
    e = dense.ENCODERS[2]
    q = dense.encode(table(spark, d, "benchmark").select(F.col("item_id").cast("string").alias("unit_id"), "text"), e, Corpus(spark, d).idf(e))
    asked = q.crossJoin(owner.select("repo", "lang").distinct()).select(F.concat_ws("|", "repo", "lang", "unit_id").alias("query_id"), F.concat_ws("|", "repo", "lang", F.col("bucket").cast("string")).alias("f"), "w")
    top = lambda x, name: lists.search(_own(x, owner), asked, 10).groupBy("query_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("rank", "unit_id"))), lambda r: r["unit_id"]).alias(name))
    both_ = top(fresh, "a").join(top(inc, "b"), "query_id", "full")
    split = F.split("query_id", r"\|")
    replay = both_.groupBy(split[0].alias("repo"), split[1].alias("lang")).agg(F.count("*").alias("queries"), F.bool_and(F.col("a").eqNullSafe(F.col("b"))).alias("ordered"), F.bool_and(F.array_sort("a").eqNullSafe(F.array_sort("b"))).alias("sets"))
    share = marked.groupBy("repo", "lang").agg(F.avg((F.col("action") == "encode").cast("double")).alias("encoded")).withColumn("index", F.when(F.col("encoded") > dense.REBUILD_SHARE, "rebuild").otherwise("mutate"))
    return same.join(replay, ["repo", "lang"], "left").join(share.withColumn("encoded", F.round("encoded", 6)), ["repo", "lang"], "left")
