"""Context delivery, measures, lifecycle and the synthesized query workload."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import digest, md5_number, tokens, usage
from ctxviews.operators import costs, delivery, metrics, stats
from ctxviews.plans import plan
from ctxviews.plans.corpus import Corpus
from ctxviews.plans.store import few, kept, stored
from ctxviews.queries import L2, TOKEN, num, query, unit_id
from ctxviews.queries.plans import boot_sql, dense_sql
from ctxviews.queries.views import UNITS_SQL, bm25_sql, hnsw_recall, ivf_recall, l2_units
from ctxviews.sources.tables import files, snapshots, table

UNIT_KEY = unit_id("path", 2, "line", "line")
USE = lambda x: f"len(regexp_extract_all(coalesce({x}, ''), '[\\p{{L}}\\p{{N}}]+|[^\\s\\p{{L}}\\p{{N}}]'))"
MSG = f"""m0 as (select *, sum((role = 'user')::int) over (partition by conv_id order by turn) as nu, coalesce(sum((role = 'assistant')::int) over (partition by conv_id order by turn rows between unbounded preceding and 1 preceding), 0) as said from conversations), m as (select conv_id as traj, turn, case when role = 'system' then 'system' when role = 'assistant' then 'completion' when nu = 1 then 'query' else 'observation' end as role, coalesce(text, '') as text, {USE('text')} as tokens from m0 where said < 16),
 m1 as (select *, coalesce(role = 'observation' and lag(role) over w = 'completion' and lag(length(text)) over w >= 200, false) as rd from m window w as (partition by traj order by turn)), m2 as (select *, min(case when rd then turn end) over (partition by traj) as cut from m1),
 sd as (select traj, concat_ws(chr(10), coalesce(string_agg(distinct case when rd then 'turn/'||turn end, ' ' order by case when rd then 'turn/'||turn end), ''), arg_max(text, turn) filter (where rd), substr(arg_max(text, turn) filter (where role = 'completion' and text <> ''), 1, 600)) as seed from m2 where turn <= cut group by traj)"""


@query("q5_seed", f"with {MSG} select traj, sha256(seed) as seed_sha, {USE('seed')}::bigint as seed_tokens from sd")
def _(spark, d):
    m = delivery.rewrite_point(delivery.messages(table(spark, d, "conversations")))
    return delivery.seed(m).select("traj", F.sha2("seed", 256).alias("seed_sha"), usage(F.col("seed")).alias("seed_tokens"))


def first_queries(spark, d):
    m = delivery.messages(table(spark, d, "conversations")).filter("role = 'query'")
    return m.select(F.col("traj").cast("string").alias("query_id"), "text")


CONVQ = f"select traj::varchar as query_id, text from (with {MSG} select * from m where role = 'query')"


def candidates(spark, d, k=10):
    """The first k dense lines for each first question, frozen before any prompt is built."""
    v = Corpus(spark, d).views()
    return few(plan.dense_list(v, first_queries(spark, d), k)).join(v.units.select("unit_id", "text"), "unit_id")


CAND = f"with {UNITS_SQL}, q as ({CONVQ}){dense_sql(10)}"


@query("q5_candidates", CAND + " select query_id, unit_id, rank from dn")
def _(spark, d):
    return candidates(spark, d).select("query_id", "unit_id", "rank")


@query("q5_replay_tokens", CAND + f""", blk as (select query_id::bigint as traj, sum({USE('un.text')}) as block from dn join un on un.key = dn.unit_id group by all), {MSG},
 mm as (select m2.*, coalesce(block, 0) as block, {USE('seed')} as st from m2 left join blk using (traj) left join sd using (traj)),
 calls as (select c.traj, c.turn, c.tokens, c.cut, c.block, c.st, coalesce(sum(p.tokens) filter (where p.role in ('system','query')), 0) as fixed, coalesce(sum(p.tokens) filter (where p.role not in ('system','query')), 0) as grown, coalesce(sum(p.tokens) filter (where p.role not in ('system','query') and p.turn > p.cut), 0) as after from mm c left join mm p on p.traj = c.traj and p.turn < c.turn where c.role = 'completion' group by all)
 select traj, policy, count(*) as invocations, sum(tokens + case when policy = 'grep' then fixed + grown when policy = 'compact' and coalesce(turn > cut, false) then fixed + st + after else fixed + grown + block end)::bigint as tokens from calls, (select unnest(['grep','eager','compact']) as policy) group by all""")
def _(spark, d):
    block = candidates(spark, d).groupBy(F.col("query_id").cast("long").alias("traj")).agg(F.sum(usage(F.col("text"))).alias("tokens"))
    return delivery.replay_tokens(table(spark, d, "conversations"), block)


# --- synthesized queries and scripted agents ------------------------------------------------------

SYNTH = L2 + f""", sn as (select repo, lang from (select distinct repo, lang from files) order by md5(repo||'/'||lang) limit 25), cand as (select l2.repo, l2.lang, path, line, text, row_number() over (partition by l2.repo, l2.lang order by md5(path||'#'||line)) as n from l2 join sn on sn.repo = l2.repo and sn.lang = l2.lang),
 ct as (select *, regexp_extract_all(lower(text), {TOKEN}) as ts from cand where n <= 20), sy0 as (select repo||'/'||lang||'/'||n as query_id, repo, lang, path, line, n, case n % 3 when 0 then 'exact' when 1 then 'dropped' else 'shuffled' end as kind, case n % 3 when 0 then array_to_string(ts, ' ') when 1 then array_to_string(list_filter(ts, lambda x, i: (i - 1) % 3 <> 2), ' ') else array_to_string(list_sort(ts), ' ') end as text from ct where len(ts) >= 3 and split_part(path, '/', 2) = lang),
 synth as materialized (select query_id, repo, lang, path, line, kind, text from sy0 qualify row_number() over (partition by repo, lang, text order by n) = 1)"""


def synth_queries(spark, d):
    """Twenty lines of each of 25 snapshots as queries: exact, every third token dropped, or sorted tokens.

    Rejected are targets with fewer than three tokens, files of another language, and repeated queries.
    """
    f = files(spark, d)
    name = F.md5(F.concat_ws("/", "repo", "lang"))
    sn = f.select("repo", "lang").distinct().orderBy(name).limit(25)
    l2 = Corpus(spark, d).units().join(sn, ["repo", "lang"], "left_semi")
    n = F.row_number().over(W.partitionBy("repo", "lang").orderBy(F.md5(F.concat("path", F.lit("#"), F.col("start").cast("string")))))
    c = l2.withColumn("n", n).filter("n <= 20").withColumn("ts", tokens(F.col("text"))).filter("size(ts) >= 3").filter(F.split("path", "/")[1] == F.col("lang"))
    kind = F.when(F.col("n") % 3 == 0, "exact").when(F.col("n") % 3 == 1, "dropped").otherwise("shuffled")
    text = F.when(F.col("n") % 3 == 0, F.concat_ws(" ", "ts")).when(F.col("n") % 3 == 1, F.concat_ws(" ", F.filter("ts", lambda x, i: i % 3 != 2))).otherwise(F.concat_ws(" ", F.sort_array("ts")))
    q = c.select(F.concat_ws("/", "repo", "lang", F.col("n").cast("string")).alias("query_id"), "repo", "lang", "path", F.col("start").alias("line"), "n", kind.alias("kind"), text.alias("text"))
    once = F.row_number().over(W.partitionBy("repo", "lang", "text").orderBy("n"))
    return q.withColumn("once", once).filter("once = 1").drop("once", "n")


@query("w_synth_queries", f"with {SYNTH} select query_id, repo, lang, path, line, kind, text from synth")
def _(spark, d):
    return synth_queries(spark, d)


def _agents(budgets, ks) -> str:
    return ", ".join(f"('agent{b}', {b}, {k})" for b in budgets for k in ks)


def trajectories_sql(ks=(10,), budgets=(1, 2, 3, 4, 5)) -> str:
    """CTE tr: query_id, repo, lang, kind, agent, policy, k, turns, tokens_used, recall."""
    return bm25_sql("select query_id, text from synth", SYNTH + f", un as (select {UNIT_KEY} as key, path, line, text from l2)", 10) + dense_sql(10) + f""",
 rk as materialized (select 'grep' as list, query_id, unit_id, rank from bm union all select 'candidates', query_id, unit_id, rank from dn), bl as materialized (select r.list, r.query_id, r.rank, {USE('un.text')} as tk, un.path = s.path and un.line = s.line as hit from rk r join un on un.key = r.unit_id join synth s on s.query_id = r.query_id),
 ag(agent, budget, k) as (values {_agents(budgets, ks)}), ar as (select s.query_id, s.repo, s.lang, s.kind, {USE('s.text')} + 40 as tokens, agent, budget, k, policy, case when policy = 'grep' then 'grep' else 'candidates' end as list from synth s, ag, (select unnest(['grep','eager','compact']) as policy)),
 a0 as (select ar.*, coalesce(sum(b.tk) filter (where b.rank <= k and policy <> 'grep'), 0) as block, coalesce(max(b.tk) filter (where b.rank = 1), 0) as tk1, min(b.rank) filter (where b.hit) as hit_at, count(b.rank) as nb from ar left join bl b on b.query_id = ar.query_id and b.list = ar.list group by all), a1 as (select *, least(budget, nb, 16) as most from a0),
 a2 as (select *, case when hit_at is not null and hit_at <= most then hit_at else most end as turns from a1), a3 as (select a2.*, coalesce(sum((b.tk + 12) * (turns + 1 - b.rank)) filter (where b.rank <= turns), 0) as sent, coalesce(sum((b.tk + 12) * (turns + 1 - b.rank)) filter (where b.rank <= turns and b.rank > 1), 0) as sent2 from a2 left join bl b on b.query_id = a2.query_id and b.list = a2.list group by all),
 tr as materialized (select query_id, repo, lang, kind, agent, policy, k, turns::int as turns, ((turns + 1) * (tokens + 12) + case when policy = 'compact' then block + turns * tk1 + sent2 else (turns + 1) * block + sent end)::bigint as tokens_used, case when coalesce(hit_at <= least(5, case when policy = 'grep' then turns else greatest(turns, k) end), false) then 1.0::double else 0.0::double end as recall from a3)"""


def trajectories(spark, d, ks=(10,), budgets=(1, 2, 3, 4, 5)):
    def build():
        q = kept(synth_queries(spark, d))
        v = Corpus(spark, d).views()
        u = v.units.select("unit_id", "path", "start", "end", "text")
        grep = plan.lexical_list(v, q.select("query_id", "text"), 10).withColumn("list", F.lit("grep"))
        cand = plan.dense_list(v, q.select("query_id", "text"), 10).withColumn("list", F.lit("candidates"))
        t = q.select("query_id", F.col("path").alias("tp"), F.col("line").alias("tl"))
        r = few(grep.select("query_id", "unit_id", "rank", "list").unionByName(cand.select("query_id", "unit_id", "rank", "list"))).join(u, "unit_id").join(t, "query_id")
        r = r.select("query_id", "list", "rank", usage(F.col("text")).alias("tokens"), ((F.col("path") == F.col("tp")) & (F.col("start") == F.col("tl"))).alias("hit"), "path", "start", "end")
        agents = spark.createDataFrame([(f"agent{b}", b, k) for b in budgets for k in ks], "agent string, budget int, k int")
        out = kept(delivery.scripted(r, q.select("query_id", "repo", "lang", "kind", (usage(F.col("text")) + 40).alias("tokens")), agents))
        targets = q.select("query_id", "path", F.col("line").alias("start"), F.col("line").alias("end"))
        return delivery.answer_recall(out, targets).drop("spans")

    return stored(spark, d, f"trajectories-{ks}-{budgets}", build)


@query("q5_trajectory_tokens", trajectories_sql() + " select * from tr")
def _(spark, d):
    return trajectories(spark, d)


@query("q5_answer_recall", trajectories_sql() + " select agent, policy, count(*) as n, round(avg(recall), 6) as answer_recall from tr group by all")
def _(spark, d):
    return trajectories(spark, d).groupBy("agent", "policy").agg(F.count("*").alias("n"), F.round(F.avg("recall"), 6).alias("answer_recall"))


EFFECT = ", ef as (select a.agent, a.policy, a.t as tokens, a.r as recall, a.r - b.r as delta, a.t / b.t as ratio from (select agent, policy, avg(tokens_used) as t, avg(recall) as r from tr group by all) a join (select agent, avg(tokens_used) as t, avg(recall) as r from tr where policy = 'grep' group by all) b using (agent))"


@query("q5_policy_effect", trajectories_sql() + EFFECT + " select agent, policy, round(tokens, 6) as tokens, round(recall, 6) as recall, round(delta, 6) as delta, round(ratio, 6) as ratio from ef")
def _(spark, d):
    return delivery.policy_effects(trajectories(spark, d))


SLICES = ", sl as (select policy, lang, kind, count(*) as n, avg(tokens_used) as t, avg(recall) as r from (select policy, 'all' as lang, 'all' as kind, tokens_used, recall from tr union all select policy, lang, 'all', tokens_used, recall from tr union all select policy, 'all', kind, tokens_used, recall from tr) group by all)"


@query("q5_slices", trajectories_sql() + SLICES + " select a.policy, a.lang, a.kind, a.n, round(a.t, 6) as tokens, round(a.r, 6) as recall, round(a.r - b.r, 6) as delta, round(a.t / b.t, 6) as ratio from sl a join sl b on a.lang = b.lang and a.kind = b.kind and b.policy = 'grep'")
def _(spark, d):
    return delivery.slices(trajectories(spark, d))


SWEEP = (1, 3, 5, 10)


@query("q5_k_sweep", trajectories_sql(SWEEP, (3,)) + " select k, policy, round(avg(tokens_used), 6) as tokens, round(avg(recall), 6) as recall from tr group by all")
def _(spark, d):
    return trajectories(spark, d, SWEEP, (3,)).groupBy("k", "policy").agg(F.round(F.avg("tokens_used"), 6).alias("tokens"), F.round(F.avg("recall"), 6).alias("recall"))


RESAMPLES = 10_000
SELECT = ", pd as (select t.repo, t.agent, t.policy, t.recall - b.recall as x from tr t join tr b on b.query_id = t.query_id and b.agent = t.agent and b.policy = 'grep'), " + boot_sql("agent, policy", RESAMPLES, "pd") + EFFECT + ", lo as (select agent, policy, round(quantile_cont(theta, 0.025), 6) as lower from rp group by all)"


@query("q5_select", trajectories_sql() + SELECT + " select agent, arg_min(policy, struct_pack(t := round(tokens, 6), p := policy)) as policy from ef join lo using (agent, policy) where lower >= -0.05 group by agent")
def _(spark, d):
    """The margin rule: paired clustered bootstrap of recall against grep, then fewest tokens."""
    t = trajectories(spark, d)
    base = t.filter("policy = 'grep'").select("query_id", "agent", F.col("recall").alias("r0"))
    paired = t.join(base, ["query_id", "agent"]).withColumn("delta", F.col("recall") - F.col("r0"))
    lower = stats.bootstrap(spark, paired, "repo", "delta", ["agent", "policy"], RESAMPLES).select("agent", "policy", "lower")
    return delivery.select_policy(delivery.policy_effects(t).join(lower, ["agent", "policy"]))


# --- measures --------------------------------------------------------------------------------------

SCORES = f"sc as (select source as repo, lang, ({num('doc_id::varchar')} % 100) / 100.0::double as x from documents)"


def scores(spark, d):
    return table(spark, d, "documents").select(F.col("source").alias("repo"), "lang", (md5_number(F.col("doc_id").cast("string")) % 100 / 100.0).alias("x"))


@query("m_bootstrap", f"with {SCORES}, {boot_sql('lang', RESAMPLES, 'sc')} select m.lang, m.mean, r.lower, r.upper from (select lang, round(sum(s) / sum(n), 6) as mean from sm group by lang) m join (select lang, round(quantile_cont(theta, 0.025), 6) as lower, round(quantile_cont(theta, 0.975), 6) as upper from rp group by lang) r using (lang)")
def _(spark, d):
    return stats.bootstrap(spark, scores(spark, d), "repo", "x", ["lang"], 10_000)


@query("m_simultaneous", f"with {SCORES}, {boot_sql('lang', RESAMPLES, 'sc')}, bs as (select lang, mean, sd from (select lang, sum(s) / sum(n) as mean from sm group by lang) join (select lang, stddev_samp(theta) as sd from rp group by lang) using (lang)), mx as (select b, max(case when sd > 0 then abs(theta - mean) / sd else 0 end) as m from rp join bs using (lang) group by b), ct as (select quantile_cont(m, 0.95) as cut from mx) select lang, round(mean, 6) as mean, round(mean - cut * sd, 6) as lower, round(mean + cut * sd, 6) as upper from bs, ct")
def _(spark, d):
    return stats.simultaneous(spark, scores(spark, d), "repo", "x", "lang", 10_000)


@query("m_pareto", "with p as (select source as panel, doc_id, n_chars as cost, (doc_id * 7919 % 1000) / 1000.0::double as quality from documents) select panel, doc_id, cost, quality from p a where not exists (select 1 from p b where b.panel = a.panel and ((b.cost < a.cost and b.quality >= a.quality) or (b.cost <= a.cost and b.quality > a.quality)))")
def _(spark, d):
    p = table(spark, d, "documents").select(F.col("source").alias("panel"), "doc_id", F.col("n_chars").alias("cost"), (F.col("doc_id") * 7919 % 1000 / 1000.0).alias("quality"))
    w = W.partitionBy("panel", "cost", "quality")  # equal points stand or fall together
    front = metrics.pareto(p.select("panel", "cost", "quality").distinct(), "cost", "quality", ["panel"])
    return p.join(front, ["panel", "cost", "quality"], "left_semi").select("panel", "doc_id", "cost", "quality")


@query("m_fit", "select l_returnflag, round(regr_slope(l_extendedprice, l_quantity), 4) as slope, round(corr(l_extendedprice, l_quantity), 6) as corr from lineitem group by all")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.corr("l_extendedprice", "l_quantity"), 6).alias("corr"))


@query("m_latency_quantiles", "select event_type, " + ", ".join(f"round(quantile_cont(value, {p / 100}), 6) as p{p}" for p in (5, 25, 50, 75, 95)) + " from events group by event_type")
def _(spark, d):
    return metrics.quantiles(table(spark, d, "events"), ["event_type"], "value")


@query("m_recall", "with t as (select o_custkey as query_id, o_orderkey as path, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) as rank, o_orderpriority in ('1-URGENT','2-HIGH') as target from orders) select count(*) as n, round(avg(h / need), 6) as recall, round(avg((h = need)::int), 6) as success from (select query_id, count(*) filter (where target) as need, count(*) filter (where target and rank <= 3) as h from t group by all having count(*) filter (where target) > 0)")
def _(spark, d):
    o = table(spark, d, "orders").select(F.col("o_custkey").alias("query_id"), F.col("o_orderkey").alias("path"), F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")).alias("rank"), F.col("o_orderpriority").isin("1-URGENT", "2-HIGH").alias("target"))
    return metrics.file_recall(o.select("query_id", "path", "rank"), o.filter("target").select("query_id", "path"), 3)


@query("m_neighbor")
def _(spark, d):
    a = ivf_recall(spark, d).select(F.lit("ivf").alias("family"), F.col("fraction").cast("string").alias("config"), "neighbor_recall")
    b = hnsw_recall(spark, d).select(F.lit("hnsw").alias("family"), F.col("ef").cast("string").alias("config"), "neighbor_recall")
    return a.unionByName(b)


# --- lifecycle and construction ----------------------------------------------------------------------


@query("lc_projection", f"with cs as (select source||'/'||lang as snapshot, 100 + {num('source||lang')} % 50 as b, 7 + ({num('lang||source')} % 10) / 10.0::double as l, 0.5::double + ({num('source')} % 100) / 100.0::double as s from (select distinct source, lang from documents)), e as (select q, b / q + l + s / 20 as i, (b + l) / q + s / 20 as r from cs, (select unnest([1,5,10,20,50,100])::int as q)) select q, round(median(i), 6) as isolated, round(median(r), 6) as resident from e group by q")
def _(spark, d):
    s = table(spark, d, "documents").select("source", "lang").distinct()
    c = s.select((100 + md5_number(F.concat("source", "lang")) % 50).alias("b"), (7 + md5_number(F.concat("lang", "source")) % 10 / 10.0).alias("l"), (0.5 + md5_number(F.col("source")) % 100 / 100.0).alias("s"), F.lit(20).alias("n"))
    return costs.project(c, spark)


@query("lc_requests", f"with {SYNTH}, v as (select unnest(['dense','bm25']) as view), per as (select repo||'/'||lang as snapshot, count(*) as nq from synth group by all) select snapshot, nq * 2 as ranked, 2 as definitions, nq * 2 + 2 as requests from per")
def _(spark, d):
    q = synth_queries(spark, d).groupBy(F.concat_ws("/", "repo", "lang").alias("snapshot")).agg(F.count("*").alias("nq"))
    return q.select("snapshot", (F.col("nq") * 2).alias("ranked"), F.lit(2).alias("definitions"), (F.col("nq") * 2 + 2).alias("requests"))


@query("q2_build_work", f"with {L2}, x as (select repo, lang, 2 as level, text from l2 union all select repo, lang, 0, text from files) select repo, lang, level, count(*) as units, sum(len(regexp_extract_all(lower(text), {TOKEN})))::bigint as tokens, count(distinct sha256(text)) as encodings from x group by all")
def _(spark, d):
    f = files(spark, d)
    x = l2_units(spark, d).select("repo", "lang", F.lit(2).alias("level"), "text").unionByName(f.select("repo", "lang", F.lit(0).alias("level"), "text"))
    return x.groupBy("repo", "lang", "level").agg(F.count("*").alias("units"), F.sum(F.size(tokens(F.col("text")))).alias("tokens"), F.countDistinct(F.sha2("text", 256)).alias("encodings"))
