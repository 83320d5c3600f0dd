"""Ranked plans and the retrieval experiments."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import tokens
from ctxviews.operators import dense, lexical, metrics, rank, stats, structure, units
from ctxviews.plans import plan
from ctxviews.plans.corpus import Corpus
from ctxviews.plans.store import few, kept
from ctxviews.queries import DECL, EDGES, FILES, L2, TOKEN, num, query
from ctxviews.queries.views import FULL, THIN, UNITS_SQL, bigram_features, bm25_sql, char_features, encode_sql, full_queries, thin_queries, token_features
from ctxviews.sources.tables import files, table


def targets(spark, d):
    """Files that hold a benchmark passage, and the queries that have any."""
    c = Corpus(spark, d)
    u = c.units(0)
    found = few(lexical.holding(full_queries(spark, d), u, c.lexical(0), few))
    return kept(found.join(u.select("unit_id", "repo", "lang", "path"), "unit_id").drop("unit_id"))


TARGETS = f"targets as (select b.query_id, f.repo, f.lang, f.path from files f join ({FULL}) b on contains(f.text, b.text))"


@query("w_targets_file", f"with {FILES}, {TARGETS} select query_id, repo, lang, path from targets")
def _(spark, d):
    return targets(spark, d)


@query("w_targets_block", f"with {L2} select b.query_id, l2.path, l2.line from l2 join ({FULL}) b on contains(l2.text, b.text)")
def _(spark, d):
    c = Corpus(spark, d)
    u = c.units()
    return few(lexical.holding(full_queries(spark, d), u, c.lexical(), few)).join(u.select("unit_id", "path", F.col("start").alias("line")), "unit_id").drop("unit_id")


def views(spark, d, encoder=dense.ENCODERS[2], edges=False, texts=True):
    return Corpus(spark, d).views(encoder, edges, texts=texts)


@query("p_select", f"with {DECL}, q as ({FULL}), qt as (select distinct query_id, unnest(regexp_extract_all(lower(text), {TOKEN})) as term from q), tf as (select line, path, unnest(list_distinct(regexp_extract_all(lower(text), {TOKEN}))) as term from l2), df1 as (select term from tf group by term having count(*) = 1), s as (select query_id, text, (regexp_matches(text, '[\"*+?\\[\\]()|\\\\]') or query_id in (select query_id from qt join df1 using (term))) as lexical, len(regexp_extract_all(lower(text), {TOKEN})) >= 6 as semantic, query_id in (select query_id from qt where term in ('uses','defines','calls') or (length(term) >= 4 and term in (select symbol from decl))) as structural from q) select query_id, case when structural then 'D' when lexical and semantic then 'C' when lexical then 'A' else 'B' end as route, 100 as k_ret, 30 as k_pre, 'small' as reranker, structural as expand from s")
def _(spark, d):
    df = Corpus(spark, d).lexical().terms
    sym = structure.declarations(units.level2(files(spark, d))).select("symbol").distinct()
    return plan.choose(plan.signals(full_queries(spark, d), df, sym), "medium", {"text_search", "semantic_search", "references"})


@query("p_route_a", bm25_sql(FULL, L2, 10) + " select query_id, unit_id, score, rank from bm")
def _(spark, d):
    return plan.run(plan.RankedPlan("A"), views(spark, d, None, texts=False), full_queries(spark, d), 10)


def dense_sql(k: int, dim: int = 256, feat=token_features) -> str:
    h = "('0x'||substr(md5(f),1,8))::bigint"
    return f"""{encode_sql(dim, 'un', 'v', 'un', feat)}, qq as (select query_id as key, text from q), qh_w as (select key, {h} % {dim} as bucket, sum(case when ({h} >> 16) % 2 = 0 then 1.0::double else -1.0::double end * tf * idf) as w from (select key, f, count(*) as tf from (select key, unnest({feat('text')}) as f from qq) group by all) join v_df using (f) group by all), qh as (select key, bucket, w / sqrt(sum(w * w) over (partition by key)) as w from qh_w where abs(w) > 1e-9),
 ds as (select qh.key as query_id, v.key as unit_id, round(sum(v.w * qh.w), 6) as score from v join qh using (bucket) group by all), dn as (select *, row_number() over (partition by query_id order by score desc, unit_id)::int as rank from ds qualify rank <= {k})"""


@query("p_route_b", f"with {UNITS_SQL}, q as ({FULL}){dense_sql(10)} select query_id, unit_id, rank from dn")
def _(spark, d):
    return plan.run(plan.RankedPlan("B"), views(spark, d, texts=False), full_queries(spark, d), 10).select("query_id", "unit_id", "rank")


ROUTE_C = bm25_sql(FULL, UNITS_SQL, 100) + dense_sql(100) + ", two as (select query_id, unit_id, 1.0::double / (60 + rank) as part from bm union all select query_id, unit_id, 1.0::double / (60 + rank) from dn), fs as (select query_id, unit_id, round(sum(part), 9) as score from two group by all), fused as (select *, row_number() over (partition by query_id order by score desc, unit_id)::int as rank from fs qualify rank <= 10)"


@query("p_route_c", ROUTE_C + " select query_id, unit_id, score, rank from fused")
def route_c(spark, d):
    return plan.run(plan.RankedPlan("C"), views(spark, d, texts=False), full_queries(spark, d), 10)


GRAPH = """, eg as (select src, dst from edges where etype = 'reference' and src <> dst), hop as (select src as seed, dst as vid from eg union all select dst, src from eg), gh as (select s.query_id, hop.vid, min(s.rank) as best, count(*) as support from seedlist s join hop on hop.seed = s.vid group by all), gl as (select query_id, vid, row_number() over (partition by query_id order by best, support desc, vid)::int as rank from gh)"""


@query("p_route_d", bm25_sql(FULL, EDGES, 10) + f", addr as (select {'sha256(path||chr(31)||2||chr(31)||line||chr(31)||line)'} as unit_id, path||'#'||line as vid from l2), seedlist as (select bm.query_id, addr.vid, bm.rank from bm join addr using (unit_id)){GRAPH} select query_id, vid, rank from gl where rank <= 10")
def _(spark, d):
    return plan.graph_seeded(views(spark, d, None), full_queries(spark, d), 10, 10)


@query("p_compose", ROUTE_C + ", c as (select f.query_id, f.rank, u.path, u.line, u.text, row_number() over (partition by f.query_id, u.path order by f.rank) as n from fused f join un u on u.key = f.unit_id) select query_id, row_number() over (partition by query_id order by rank)::int as block, path, line as start, line as \"end\", text from c where n = 1 qualify block <= 5")
def _(spark, d):
    v = views(spark, d)
    return rank.compose(few(plan.run(plan.RankedPlan("C"), v, full_queries(spark, d), 10)), v.units, 5)


# --- retrieval quality ------------------------------------------------------------------------


def _files_of(ranked, u, extra=()):
    r = few(ranked).join(u.select("unit_id", "path"), "unit_id")
    first = r.groupBy(*extra, "query_id", "path").agg(F.min("rank").alias("first"))
    return first.withColumn("rank", F.row_number().over(W.partitionBy(*extra, "query_id").orderBy("first", "path"))).drop("first")


def recall_sql(ctes: str, ranked: str, k: int = 10) -> str:
    """File recall and success at k of `ranked` (query_id, unit_id, rank), macro over queries with targets."""
    return f"""{ctes}, fr0 as (select r.query_id, u.path, min(r.rank) as first from {ranked} r join un u on u.key = r.unit_id group by all), fr as (select *, row_number() over (partition by query_id order by first, path) as rank from fr0), {TARGETS},
 need as (select query_id, count(*) as need from targets group by query_id), hit as (select fr.query_id, count(*) as hit from fr join targets t using (query_id, path) where fr.rank <= {k} group by all), ev as (select need, coalesce(hit, 0) as hit from need left join hit using (query_id))"""


def recall_by_encoder(ranked, t, encoders):
    """encoder, n, recall, success: a row for each encoder, also if it found nothing or there is no target."""
    own, out = kept(ranked), None
    for e in encoders:
        r = metrics.file_recall(own.filter(F.col("encoder") == e.name).drop("encoder"), t, 10).select(F.lit(e.name).alias("encoder"), "n", "recall", "success")
        out = r if out is None else out.unionByName(r)
    return out


def dense_recall(spark, d, encoders=dense.ENCODERS, q=None, level=2):
    c = Corpus(spark, d)
    q = q if q is not None else thin_queries(spark, d)
    t, out = targets(spark, d), None
    if all(e.features == "token" for e in encoders):
        v = c.views(encoders[0], level=level)
        ranked = plan.dense_lists(v, q, encoders, 100)
        return recall_by_encoder(_files_of(ranked, v.units, ("encoder",)), t, encoders)
    for e in encoders:
        v = c.views(e, level=level)
        r = metrics.file_recall(_files_of(plan.dense_list(v, q, 100), v.units), t, 10).withColumn("encoder", F.lit(e.name))
        out = r if out is None else out.unionByName(r)
    return out.select("encoder", "n", "recall", "success")


@query("q1_dense_recall", " union all ".join(f"(with {UNITS_SQL}, q as ({THIN}){recall_sql(dense_sql(100, e.dim), 'dn')} select '{e.name}' as encoder, count(*) as n, round(avg(hit / need), 6) as recall, round(avg((hit = need)::int), 6) as success from ev)" for e in dense.ENCODERS))
def _(spark, d):
    return dense_recall(spark, d)


@query("q1_dense_recall_full", f"with {UNITS_SQL}, q as ({FULL}){recall_sql(dense_sql(100, 256), 'dn')} select 'hash256' as encoder, count(*) as n, round(avg(hit / need), 6) as recall, round(avg((hit = need)::int), 6) as success from ev")
def _(spark, d):
    return dense_recall(spark, d, [dense.ENCODERS[2]], full_queries(spark, d))


UNITS0_SQL = L2 + ", un as (select sha256(path||chr(31)||0||chr(31)||0||chr(31)||(len(string_split(text, chr(10))) - 1)) as key, path, 0 as line, text from files)"
RECALL_OF = "count(*) as n, round(avg(hit / need), 6) as recall, round(avg((hit = need)::int), 6) as success from ev"


@query("q1_dense_recall_l0", " union all ".join(f"(with {UNITS0_SQL}, q as ({THIN}){recall_sql(dense_sql(100, e.dim), 'dn')} select '{e.name}' as encoder, {RECALL_OF})" for e in dense.ENCODERS))
def _(spark, d):
    """The same five encoders over whole files."""
    return dense_recall(spark, d, level=0)


@query("q1_encoder_features", " union all ".join(f"(with {UNITS_SQL}, q as ({THIN}){recall_sql(dense_sql(100, 256, f), 'dn')} select '{n}' as encoder, {RECALL_OF})" for n, f in (("bigram256", bigram_features), ("char256", char_features))))
def _(spark, d):
    return dense_recall(spark, d, [dense.Encoder("bigram256", 256, "bigram"), dense.Encoder("char256", 256, "char")])


def block_targets(spark, d):
    """query_id, unit_id of the lines that hold a passage: the symbols that a query wants."""
    c = Corpus(spark, d)
    return kept(lexical.holding(full_queries(spark, d), c.units(), c.lexical(), few))


BLOCKS = f"blocks as (select b.query_id, un.key as path from un join ({FULL}) b on contains(un.text, b.text))"
SYMBOL = f"{BLOCKS}, need as (select query_id, count(*) as need from blocks group by query_id), hit as (select r.query_id, count(*) as hit from dn r join blocks b on b.query_id = r.query_id and b.path = r.unit_id where r.rank <= 10 group by all), ev as (select need, coalesce(hit, 0) as hit from need left join hit using (query_id))"


@query("q1_symbol_recall", " union all ".join(f"(with {UNITS_SQL}, q as ({THIN}){dense_sql(100, e.dim)}, {SYMBOL} select '{e.name}' as encoder, {RECALL_OF})" for e in dense.ENCODERS))
def _(spark, d):
    """Symbol Recall@10: the share of a query's target lines among its first ten units, by encoder."""
    v, q = Corpus(spark, d).views(), thin_queries(spark, d)
    t = block_targets(spark, d).select("query_id", F.col("unit_id").alias("path"))
    r = plan.dense_lists(v, q, dense.ENCODERS, 100).select("encoder", "query_id", F.col("unit_id").alias("path"), "rank")
    return recall_by_encoder(r, t, dense.ENCODERS)


CUTS = (30, 50, 100)


def rerank_recall(spark, d, scorers=("small", "medium", "large"), cuts=CUTS):
    """File recall of every scorer and cut; a candidate is scored once, whatever the cuts."""
    v, q, t = views(spark, d), thin_queries(spark, d), targets(spark, d)
    cand = few(plan.dense_list(v, q, max(cuts))).join(v.units.select("unit_id", "text"), "unit_id").join(q.select("query_id", F.col("text").alias("query_text")), "query_id")
    each = F.array(*[F.struct(F.lit(s).alias("scorer"), F.round(rank.SCORERS[s](F.col("query_text"), F.col("text")).cast("double"), 6).alias("score")) for s in scorers])
    scored = kept(cand.select("query_id", "unit_id", "rank", F.explode(each).alias("x")).select("query_id", "unit_id", "rank", "x.scorer", "x.score"))
    arms = scored.withColumn("cut", F.explode(F.array(*map(F.lit, cuts)))).filter(F.col("rank") <= F.col("cut"))
    w = W.partitionBy("scorer", "cut", "query_id").orderBy(F.desc("score"), "unit_id")
    arms = arms.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= 30).select("scorer", "cut", "query_id", "unit_id", "rank")
    return metrics.file_recall(_files_of(arms, v.units, ("scorer", "cut")), t, 10, ["scorer", "cut"])


def _tokens_sql(x: str) -> str:
    return f"regexp_extract_all(lower({x}), {TOKEN})"


def _grams_sql(x: str) -> str:
    return f"list_distinct(list_transform(range(1, greatest(length(lower({x})) - 3, 1) + 1), lambda i: substr(lower({x}), i, 4)))"


def _scorer_sql(name: str) -> str:
    x, y = f"list_distinct({_tokens_sql('q.text')})", f"list_distinct({_tokens_sql('un.text')})"
    g, h = _grams_sql("q.text"), _grams_sql("un.text")
    cosine = f"len(list_intersect({g}, {h})) / sqrt(len({g}) * len({h}))"
    t, body = _tokens_sql("q.text"), f"' '||array_to_string({_tokens_sql('un.text')}, ' ')||' '"
    longest = "greatest(" + ", ".join(f"case when len({t}) >= {n} and len(list_filter(range(1, greatest(len({t}) - {n} + 1, 1) + 1), lambda i: contains({body}, ' '||array_to_string({t}[i:i+{n - 1}], ' ')||' '))) > 0 then {n} else 0 end" for n in range(1, 9)) + ")"
    return {"small": f"case when len(list_distinct(list_concat({x}, {y}))) = 0 then 0.0 else len(list_intersect({x}, {y})) / len(list_distinct(list_concat({x}, {y}))) end", "medium": cosine, "large": f"{cosine} + {longest} / 8.0"}[name]


def _rerank_sql(scorer: str, cut: int) -> str:
    return f"(with {UNITS_SQL}, q as ({THIN}){dense_sql(100)}, rs as (select dn.query_id, dn.unit_id, round({_scorer_sql(scorer)}, 6) as score from dn join un on un.key = dn.unit_id join q using (query_id) where dn.rank <= {cut}), rr as (select *, row_number() over (partition by query_id order by score desc, unit_id) as rank from rs qualify rank <= 30){recall_sql('', 'rr')} select '{scorer}' as scorer, {cut} as cut, {RECALL_OF})"


@query("q1_rerank_small", " union all ".join(_rerank_sql("small", c) for c in CUTS))
def _(spark, d):
    return rerank_recall(spark, d, ("small",))


@query("q1_rerank_recall", " union all ".join(_rerank_sql(s, c) for s in ("small", "medium", "large") for c in CUTS))
def _(spark, d):
    return rerank_recall(spark, d)


WEIGHTS = (0.25, 0.5, 0.75, 1.0, 1.25, 1.5, 2.0)


def fused_vids(spark, d, weights, k=10, width=300):
    v = views(spark, d)
    at = v.units.select("unit_id", "path", "start", plan.vid_of(F.col("path"), F.col("start")).alias("vid"))
    dn = kept(few(plan.dense_list(v, thin_queries(spark, d), width)).join(at, "unit_id").select("query_id", "vid", "path", "start", "rank"))
    w = spark.createDataFrame([(x,) for x in weights], "w_g double")
    edges = plan.edges_of_lines(v.units, dn.filter("rank <= 10"))
    return rank.dense_graph_fusion(dn, edges, w, 10, rank.KAPPA, k)


AT = "addr as (select sha256(path||chr(31)||2||chr(31)||line||chr(31)||line) as unit_id, path||'#'||line as vid from l2)"
FUSED = f"{EDGES}, un as (select sha256(path||chr(31)||2||chr(31)||line||chr(31)||line) as key, path, line, text from l2), {AT}, q as ({THIN}){dense_sql(300)}, dv as (select dn.query_id, addr.vid, dn.rank from dn join addr using (unit_id)), seedlist as (select * from dv where rank <= 10){GRAPH}, fz as (select w_g, query_id, vid, round(coalesce(1.0::double / (60 + dv.rank), 0) + coalesce(w_g / (60 + gl.rank), 0), 9) as score from dv full join gl using (query_id, vid), (select unnest([0.25,0.5,0.75,1.0,1.25,1.5,2.0])::double as w_g))"


@query("q1_fusion", f"with {FUSED} select w_g, query_id, vid, score, row_number() over (partition by w_g, query_id order by score desc, vid)::int as rank from fz qualify rank <= 10")
def _(spark, d):
    return fused_vids(spark, d, WEIGHTS)


def split_success(spark, d, held: bool, weights=WEIGHTS):
    """Success@10/5/1 for each graph weight on the tuning or on the held-out repositories.

    The 20 sources in md5 order: the first 12 tune, the others are held out; a
    query belongs to the repository of its least target.
    """
    repos = files(spark, d).select("repo").distinct().withColumn("n", F.row_number().over(W.orderBy(F.md5("repo")))).filter(F.col("n") > 12 if held else F.col("n") <= 12)
    t = targets(spark, d)
    own = t.groupBy("query_id").agg(F.min_by("repo", "path").alias("repo")).join(F.broadcast(repos), "repo", "left_semi")
    mine = t.join(own, "query_id", "left_semi")
    fused = fused_vids(spark, d, weights, 60)
    first = fused.withColumn("path", F.regexp_extract("vid", r"^(.*)#", 1)).groupBy("w_g", "query_id", "path").agg(F.min("rank").alias("first"))
    ranked = first.withColumn("rank", F.row_number().over(W.partitionBy("w_g", "query_id").orderBy("first", "path")))
    out = None
    for k in (10, 5, 1):
        m = metrics.file_recall(ranked, mine, k, ["w_g"]).select("w_g", "n", F.col("success").alias(f"success{k}"))
        out = m if out is None else out.join(m.drop("n"), "w_g")
    return out


def _split_sql(held: bool) -> str:
    return f"""with {FUSED}, fk as (select *, row_number() over (partition by w_g, query_id order by score desc, vid) as rank from fz qualify rank <= 60), fp0 as (select w_g, query_id, regexp_extract(vid, '^(.*)#', 1) as path, min(rank) as first from fk group by all), fp as (select *, row_number() over (partition by w_g, query_id order by first, path) as rank from fp0), {TARGETS},
 rp as (select repo, row_number() over (order by md5(repo)) as n from (select distinct repo from files)), ow as (select query_id, arg_min(repo, path) as repo from targets group by query_id), mine as (select t.* from targets t join ow using (query_id) join rp on rp.repo = ow.repo where rp.n {'>' if held else '<='} 12),
 need as (select query_id, count(*) as need from mine group by all), ar as (select distinct w_g from fp), hits as (select fp.w_g, fp.query_id, count(*) filter (where fp.rank <= 10) as h10, count(*) filter (where fp.rank <= 5) as h5, count(*) filter (where fp.rank <= 1) as h1 from fp join mine using (query_id, path) group by all)
 select w_g, count(*) as n, round(avg((coalesce(h10, 0) = need)::int), 6) as success10, round(avg((coalesce(h5, 0) = need)::int), 6) as success5, round(avg((coalesce(h1, 0) = need)::int), 6) as success1 from need cross join ar left join hits using (w_g, query_id) group by w_g"""


@query("q1_graph_tune", _split_sql(False))
def _(spark, d):
    return split_success(spark, d, False)


HELD = f"select h.* from ({_split_sql(True)}) h where h.w_g = (select t.w_g from ({_split_sql(False)}) t order by success10 desc, success5 desc, success1 desc, w_g limit 1)"


@query("q1_graph_heldout", HELD)
def _(spark, d):
    """The weight chosen on the tuning repositories (lexicographic success@10, @5, @1; least weight on ties), on the held-out ones."""
    tuned = split_success(spark, d, False).agg(F.max_by("w_g", F.struct("success10", "success5", "success1", -F.col("w_g"))).alias("w_g"))
    return split_success(spark, d, True).join(tuned, "w_g", "left_semi")


# --- compositions outside the routes -------------------------------------------------------------


def pipelines(v: plan.Views, q) -> dict[str, plan.Pipeline]:
    """The four named compositions; each maps a batch of queries to (query_id, vid, rank), every step explicit."""
    at = v.units.select("unit_id", "text", plan.vid_of(F.col("path"), F.col("start")).alias("vid"))
    search = plan.Pipeline().then("dense", lambda x: plan.dense_list(v, x, 100).join(at, "unit_id").select("query_id", "vid", "rank"))
    one = v.units.sparkSession.createDataFrame([(1.0,)], "w_g double")
    fuse = search.then("expand and fuse", lambda x: rank.dense_graph_fusion(x, v.edges, one, 10, rank.KAPPA, 100).select("query_id", "vid", "rank"))

    def rerank(x):
        c = x.join(at.select("vid", "text"), "vid").join(q.select("query_id", F.col("text").alias("query_text")), "query_id")
        return rank.pointwise(c, "small", 30, 10, "vid").select("query_id", "vid", "rank")

    cut = lambda x: x.filter("rank <= 10")
    return {"dense": search.then("cut", cut), "dense-rerank": search.then("rerank", rerank), "dense-expand-fuse": fuse.then("cut", cut), "dense-expand-fuse-rerank": fuse.then("rerank", rerank)}


def _pipe_sql(name: str, ranked: str) -> str:
    return f"select '{name}' as pipeline, query_id, vid, rank::int as rank from {ranked} where rank <= 10"


SMALL_VID = _scorer_sql("small").replace("un.text", "l.text")
PIPES = f"""with {FUSED.replace(THIN, FULL)}, d1 as (select query_id, vid, rank from dv where rank <= 100), seed1 as (select * from d1 where rank <= 10), gh1 as (select s.query_id, hop.vid, min(s.rank) as best, count(*) as support from seed1 s join hop on hop.seed = s.vid group by all), gl1 as (select query_id, vid, row_number() over (partition by query_id order by best, support desc, vid)::int as rank from gh1),
 f1 as (select query_id, vid, round(coalesce(1.0::double / (60 + d1.rank), 0) + coalesce(1.0::double / (60 + gl1.rank), 0), 9) as score from d1 full join gl1 using (query_id, vid)), f2 as (select query_id, vid, row_number() over (partition by query_id order by score desc, vid) as rank from f1 qualify rank <= 100),
 lv as (select path||'#'||line as vid, text from l2), r1 as (select x.query_id, x.vid, row_number() over (partition by x.query_id order by round({SMALL_VID}, 6) desc, x.vid) as rank from d1 x join lv l using (vid) join q on q.query_id = x.query_id where x.rank <= 30), r2 as (select x.query_id, x.vid, row_number() over (partition by x.query_id order by round({SMALL_VID}, 6) desc, x.vid) as rank from f2 x join lv l using (vid) join q on q.query_id = x.query_id where x.rank <= 30) """


@query("p_pipelines", PIPES + " union all ".join(_pipe_sql(n, r) for n, r in (("dense", "d1"), ("dense-rerank", "r1"), ("dense-expand-fuse", "f2"), ("dense-expand-fuse-rerank", "r2"))))
def _(spark, d):
    v, q, out = views(spark, d, edges=True), full_queries(spark, d), None
    for name, p in pipelines(v, q).items():
        r = p(q).select(F.lit(name).alias("pipeline"), "query_id", "vid", "rank")
        out = r if out is None else out.unionByName(r)
    return out


BUDGET = 50


@query("q1_equal_budget", bm25_sql(THIN, UNITS_SQL, 100) + dense_sql(100) + f""", two as (select query_id, unit_id, 1.0::double / (60 + rank) as part from bm union all select query_id, unit_id, 1.0::double / (60 + rank) from dn), fs as (select query_id, unit_id, round(sum(part), 9) as score from two group by all), fused as (select *, row_number() over (partition by query_id order by score desc, unit_id)::int as rank from fs),
 arms as (select 'lexical' as arm, query_id, unit_id, rank from bm union all select 'dense', query_id, unit_id, rank from dn union all select 'hybrid', query_id, unit_id, rank from fused), cut as (select * from arms where rank <= {BUDGET}), fr0 as (select arm, query_id, path, min(rank) as first from cut join un on un.key = cut.unit_id group by all), fr as (select *, row_number() over (partition by arm, query_id order by first, path) as rank from fr0), {TARGETS}, need as (select query_id, count(*) as need from targets group by all), hit as (select arm, query_id, count(*) as hit from fr join targets using (query_id, path) where fr.rank <= 10 group by all), sz as (select arm, count(*) as candidates from cut group by arm)
 select arm, candidates, count(*) as n, round(avg(coalesce(hit, 0) / need), 6) as recall, round(avg((coalesce(hit, 0) = need)::int), 6) as success from need cross join sz left join hit using (arm, query_id) group by all""")
def _(spark, d):
    """Three arms that may hand on the same number of candidates, so that only their choice differs."""
    v, q, t = views(spark, d), thin_queries(spark, d), targets(spark, d)
    lex, den = kept(plan.lexical_list(v, q, 100)), kept(plan.dense_list(v, q, 100))
    cut = plan.equal_budget({"lexical": lex, "dense": den, "hybrid": rank.rrf([(lex, 1.0), (den, 1.0)], 200)}, BUDGET)
    size = cut.groupBy("arm").agg(F.count("*").alias("candidates"))
    return metrics.file_recall(_files_of(cut, v.units, ("arm",)), t, 10, ["arm"]).join(size, "arm").select("arm", "candidates", "n", "recall", "success")


CONTRASTS = [(w, k) for w in (0.5, 1.0) for k in (1, 3, 5, 10, 20)]


def graph_effects(spark, d):
    """query_id, repo, contrast, x: success with the graph list minus success without it, for ten contrasts (weight, k)."""
    t = targets(spark, d)
    w = spark.createDataFrame([(0.0,), (0.5,), (1.0,)], "w_g double")
    f = fused_vids(spark, d, (0.0, 0.5, 1.0), 100)
    first = f.withColumn("path", F.regexp_extract("vid", r"^(.*)#", 1)).groupBy("w_g", "query_id", "path").agg(F.min("rank").alias("first"))
    ranked = first.withColumn("rank", F.row_number().over(W.partitionBy("w_g", "query_id").orderBy("first", "path")))
    last = ranked.join(t.select("query_id", "path"), ["query_id", "path"]).groupBy("w_g", "query_id").agg(F.count("*").alias("found"), F.max("rank").alias("last"))
    need = t.groupBy("query_id").agg(F.count("*").alias("need"), F.min_by("repo", "path").alias("repo"))
    arms = need.crossJoin(F.broadcast(w)).join(last, ["w_g", "query_id"], "left").withColumn("whole", F.coalesce(F.col("found") == F.col("need"), F.lit(False)))
    wide = arms.groupBy("query_id", "repo").pivot("w_g", [0.0, 0.5, 1.0]).agg(F.first(F.when(F.col("whole"), F.col("last"))).alias("l"))
    ok = lambda w, k: F.coalesce((F.col(f"`{w}`") <= k).cast("double"), F.lit(0.0))
    return wide.select("query_id", "repo", F.explode(F.array(*[F.struct(F.lit(f"w{w}@{k}").alias("contrast"), (ok(w, k) - ok(0.0, k)).alias("x")) for w, k in CONTRASTS])).alias("e")).select("query_id", "repo", "e.contrast", "e.x")


def boot_sql(by: str, b: int, src: str) -> str:
    """CTEs sm (cluster sums) and rp (replicates) of a bootstrap of x by repository."""
    return f"""cl as (select repo, row_number() over (order by repo) - 1 as c from (select distinct repo from {src})), sm as (select {by}, cl.c, sum(x) as s, count(*) as n from {src} join cl using (repo) group by all), nc as (select count(*) as k from cl), dr as (select b, j, {num("b||'#'||j")} % k as c from (select unnest(range({b})) as b), (select unnest(range(1000)) as j), nc where j < k), rp as materialized (select {by}, b, sum(s) / sum(n) as theta from dr join sm using (c) group by all)"""


PAIRED = f"""with {FUSED}, fa as (select w_g, query_id, vid, score from fz where w_g in (0.5, 1.0) union all select 0.0::double, query_id, vid, round(1.0::double / (60 + rank), 9) from dv), fk as (select *, row_number() over (partition by w_g, query_id order by score desc, vid) as rank from fa qualify rank <= 100),
 fp0 as (select w_g, query_id, regexp_extract(vid, '^(.*)#', 1) as path, min(rank) as first from fk group by all), fp as (select *, row_number() over (partition by w_g, query_id order by first, path) as rank from fp0), {TARGETS}, need as (select query_id, count(*) as need, arg_min(repo, path) as repo from targets group by all),
 la as (select w_g, query_id, count(*) as found, max(rank) as last from fp join targets using (query_id, path) group by all), ok as (select n.query_id, n.repo, w.w_g, case when l.found = n.need then l.last end as last from need n cross join (select unnest([0.0, 0.5, 1.0])::double as w_g) w left join la l on l.query_id = n.query_id and l.w_g = w.w_g),
 pe as (select a.query_id, a.repo, 'w'||(case when a.w_g = 0.5 then '0.5' else '1.0' end)||'@'||k as contrast, coalesce((a.last <= k)::int, 0)::double - coalesce((z.last <= k)::int, 0)::double as x from ok a join ok z on z.query_id = a.query_id and z.w_g = 0 and a.w_g > 0, (select unnest([1, 3, 5, 10, 20]) as k)), {boot_sql('contrast', 20_000, 'pe')},
 bs as (select contrast, mean, sd from (select contrast, sum(s) / sum(n) as mean from sm group by contrast) join (select contrast, stddev_samp(theta) as sd from rp group by contrast) using (contrast)), mx as (select b, max(case when sd > 0 then abs(theta - mean) / sd else 0 end) as m from rp join bs using (contrast) group by b), ct as (select quantile_cont(m, 0.95) as cut from mx), qs as (select contrast, quantile_cont(theta, 0.025) as lo, quantile_cont(theta, 0.975) as hi from rp group by contrast)
 select contrast, round(mean, 6) as mean, round(lo, 6) as lower, round(hi, 6) as upper, round(mean - cut * sd, 6) as all_lower, round(mean + cut * sd, 6) as all_upper from bs join qs using (contrast), ct"""


@query("q1_graph_paired", PAIRED)
def _(spark, d):
    """Paired effects of the graph list, resampled 20,000 times by repository: pointwise and simultaneous 95 % intervals."""
    x = kept(graph_effects(spark, d))
    own = stats.bootstrap(spark, x, "repo", "x", ["contrast"], 20_000)
    all_ = stats.simultaneous(spark, x, "repo", "x", "contrast", 20_000).select("contrast", F.col("lower").alias("all_lower"), F.col("upper").alias("all_upper"))
    return own.join(all_, "contrast")
