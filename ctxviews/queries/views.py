"""Units, catalog identities, lexical, dense and structural views."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import digest, md5_number, tokens
from ctxviews.operators import dense, lexical, rows, structure, units
from ctxviews.plans.corpus import Corpus
from ctxviews.plans.store import few, kept
from ctxviews.queries import DECL, EDGES, FILES, L2, LINES, OCC, REFS, TOKEN, num, query, unit_id
from ctxviews.sources.tables import files, page_files, scope, snapshots, table


def l2_units(spark, sf_dir):
    return units.with_ids(units.level2(files(spark, sf_dir)), 2)


# --- units and catalog ---------------------------------------------------------------------


@query("u_units_l0", f"with {FILES} select path, 0 as level, 0 as start, (len(string_split(text, chr(10)))-1)::int as \"end\", sha256(text) as text_sha, {unit_id('path', 0, '0', '(len(string_split(text, chr(10)))-1)')} as unit_id from files")
def _(spark, d):
    return units.with_ids(units.level0(files(spark, d)), 0).select("path", "level", "start", "end", F.sha2("text", 256).alias("text_sha"), "unit_id")


L1_SQL = L2 + """, r0 as (select *, line - row_number() over (partition by path order by line) as run from l2),
 r1 as (select *, (row_number() over (partition by path, run order by line) - 1) // 4 as part from r0),
 l1 as (select repo, lang, path, run, part, min(line) as start, max(line) as "end", string_agg(text, chr(10) order by line) as text from r1 group by repo, lang, path, run, part)"""


@query("u_units_l1", f"with {L1_SQL} select path, 1 as level, start, \"end\", sha256(text) as text_sha from l1")
def _(spark, d):
    return units.level1(files(spark, d)).select("path", "level", "start", "end", F.sha2("text", 256).alias("text_sha"))


@query("u_units_l2", f"with {L2} select path, line as start, text, {unit_id('path', 2, 'line', 'line')} as unit_id from l2")
def _(spark, d):
    return l2_units(spark, d).select("path", "start", "text", "unit_id")


PAGE_FILES = "pf as (select page_id, regexp_extract(url, '^[a-z]+://([^?#]*)', 1) as path, coalesce(html,'') as text from pages)"


@query("u_units_pages", f"with {PAGE_FILES}, x as (select path, page_id, regexp_extract_all(text, '(?s)<(?:h1|p|li)\\b[^>]*>.*?</(?:h1|p|li)>') as e from pf), y as (select path, page_id, unnest(range(len(e)))::int as start, unnest(e) as raw from x) select path, page_id, start, regexp_extract(raw, '^<(h1|p|li)', 1) as ntype, regexp_replace(raw, '(?s)<[^>]*>', '', 'g') as text from y")
def _(spark, d):
    return units.page_units(page_files(spark, d)).select("path", "page_id", "start", "ntype", "text")


@query("u_symbols", f"with {DECL} select repo, lang, path, line, symbol from decl")
def _(spark, d):
    return structure.declarations(units.level2(files(spark, d)))


@query("u_enclosing", f"with {L1_SQL}, pos as (select path, (doc_id % 7)::int as line from files) select p.path, p.line, l1.start, l1.\"end\" from pos p join l1 on l1.path = p.path and p.line between l1.start and l1.\"end\"")
def _(spark, d):
    f = files(spark, d)
    return units.enclosing(f.select("path", (F.col("doc_id") % 7).cast("int").alias("line")), units.level1(f).select("path", "start", "end"))


@query("u_scope", f"with {FILES} select 'dense' as view, repo, lang, count(*) as n from files where doc_id not in (select doc_id from labels where toxic = 1) group by all union all select 'structural', repo, lang, count(*) from files group by all")
def _(spark, d):
    f, lab = files(spark, d), table(spark, d, "labels")
    parts = [scope(f, lab, v).groupBy("repo", "lang").agg(F.count("*").alias("n")).select(F.lit(v).alias("view"), "repo", "lang", "n") for v in ("dense", "structural")]
    return parts[0].unionByName(parts[1])


@query("u_identity", "select distinct source as repo, sha256(source||chr(31)||'0') as source_id, sha256(lang||chr(31)||'1'||chr(31)||'hash256'||chr(31)||'{}') as profile_id from documents")
def _(spark, d):
    from ctxviews.plans.catalog import profile_id, source_id

    f = table(spark, d, "documents")
    return f.select(F.col("source").alias("repo"), source_id(F.col("source"), F.lit("0")).alias("source_id"), profile_id(F.col("lang"), "1", "hash256", "{}").alias("profile_id")).distinct()


@query("u_alias", "with i as (select distinct source||'/'||lang||'#'||n as instance, sha256(source||chr(31)||'0') as source_id, sha256(lang||chr(31)||'1'||chr(31)||'hash256'||chr(31)||'{}') as profile_id from documents, (select unnest(['head','main','tag']) as n)) select *, min(instance) over (partition by source_id, profile_id) as canonical from i")
def _(spark, d):
    from ctxviews.plans.catalog import alias, profile_id, source_id

    f = table(spark, d, "documents").select("source", "lang").distinct().withColumn("n", F.explode(F.array(*map(F.lit, ("head", "main", "tag")))))
    return alias(f.select(F.concat("source", F.lit("/"), "lang", F.lit("#"), "n").alias("instance"), source_id(F.col("source"), F.lit("0")).alias("source_id"), profile_id(F.col("lang"), "1", "hash256", "{}").alias("profile_id")))


CAPS = [("lexical", "text_search"), ("dense", "semantic_search"), ("structural", "definition"), ("structural", "references"), ("structural", "neighbours")]


@query("u_capabilities", f"with {FILES}, s as (select distinct repo, lang from files), e as (select repo, lang, unnest(['lexical','dense','structural']) as view from s), st as (select *, case when {num('repo||lang||view')} % 10 = 0 then 'failed' else 'ok' end as status from e), cap(view, capability) as (values ('lexical','text_search'),('dense','semantic_search'),('structural','definition'),('structural','references'),('structural','neighbours')) select repo, lang, array_to_string(list_sort(list(capability)), ',') as capabilities from st join cap using (view) where status = 'ok' group by all")
def _(spark, d):
    from ctxviews.plans.catalog import capabilities

    s = files(spark, d).select("repo", "lang").distinct()
    e = s.select("repo", "lang", F.explode(F.array(*map(F.lit, ("lexical", "dense", "structural")))).alias("view"))
    e = e.withColumn("status", F.when(md5_number(F.concat("repo", "lang", "view")) % 10 == 0, "failed").otherwise("ok"))
    return capabilities(e, ["repo", "lang"]).withColumn("capabilities", F.concat_ws(",", "capabilities"))


@query("u_lag", "with h as (select user_id, count(*) filter (where event_type = 'purchase') as head, count(*) filter (where event_type = 'purchase' and ts <= (select min(ts) + (max(ts) - min(ts)) / 2 from events)) as built from events group by user_id) select user_id, head, built, head - built as lag from h")
def _(spark, d):
    from ctxviews.plans.catalog import lag

    e = table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    # half of the time span, in microseconds: exact on both sides
    mid = e.agg(F.min(F.unix_micros("ts")).alias("lo"), F.max(F.unix_micros("ts")).alias("hi")).select(F.expr("lo + (hi - lo) div 2").alias("mid"))
    p = F.col("event_type") == "purchase"
    x = e.crossJoin(F.broadcast(mid)).groupBy("user_id").agg(F.count_if(p).alias("head"), F.count_if(p & (F.unix_micros("ts") <= F.col("mid"))).alias("built"))
    return lag(x)


@query("u_digest", f"with {FILES} select repo, lang, count(*) as n, sum({num('path||chr(31)||sha256(text)')})::bigint as digest from files group by all")
def _(spark, d):
    from ctxviews.operators.versions import digest_of

    return digest_of(files(spark, d))


@query("w_snapshots", f"with {FILES}, s as (select repo, lang, count(*) as n_files, sum(len(string_split(text, chr(10))))::bigint as n_lines from files group by all) select *, ntile(4) over (order by n_files, repo, lang)::int as stratum from s")
def _(spark, d):
    return snapshots(files(spark, d))


# --- lexical -------------------------------------------------------------------------------


@query("x_postings", f"with {L2}, t0 as (select {unit_id('path', 2, 'line', 'line')} as unit_id, regexp_extract_all(lower(text), {TOKEN}) as ts from l2), t as (select unit_id, unnest(range(len(ts)))::int as pos, unnest(ts) as term from t0) select term, unit_id, count(*) as tf, array_to_string(list(pos order by pos), ',') as positions from t group by all")
def _(spark, d):
    return lexical.postings(l2_units(spark, d)).withColumn("positions", F.concat_ws(",", F.transform("positions", lambda x: x.cast("string"))))


def bm25_sql(queries: str, ctes: str, k: int) -> str:
    return f"""with {ctes}, q as ({queries}), u as (select {unit_id('path', 2, 'line', 'line')} as unit_id, path, regexp_extract_all(lower(text), {TOKEN}) as ts from l2),
 qt as (select distinct query_id, unnest(regexp_extract_all(lower(text), {TOKEN})) as term from q),
 tf as (select unit_id, term, count(*) as tf, any_value(dl) as dl from (select unit_id, unnest(ts) as term, len(ts) as dl from u) group by unit_id, term),
 st as (select count(*) as n, avg(len(ts)) as avgdl from u), df as (select term, count(*) as df from tf group by term),
 sc as (select query_id, unit_id, round(sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / avgdl))), 6) as score from qt join tf using (term) join df using (term), st group by all),
 bm as (select *, row_number() over (partition by query_id order by score desc, unit_id)::int as rank from sc qualify rank <= {k})"""


THIN = f"select item_id::varchar as query_id, string_agg(t, ' ' order by i) as text from (select item_id, unnest(range(len(ts))) as i, unnest(ts) as t from (select item_id, regexp_extract_all(lower(text), {TOKEN}) as ts from benchmark)) where {num('item_id||chr(31)||t')} % 4 = 0 group by item_id"
FULL = "select item_id::varchar as query_id, text from benchmark"


def thin_queries(spark, d):
    """Benchmark queries that keep about every fourth token, by hash."""
    t = table(spark, d, "benchmark").select(F.col("item_id").cast("string").alias("query_id"), F.posexplode(tokens(F.col("text"))).alias("i", "t"))
    t = t.filter(md5_number(F.concat_ws("\x1f", "query_id", "t")) % 4 == 0)
    return t.groupBy("query_id").agg(F.concat_ws(" ", F.transform(F.array_sort(F.collect_list(F.struct("i", "t"))), lambda s: s["t"])).alias("text"))


def full_queries(spark, d):
    return table(spark, d, "benchmark").select(F.col("item_id").cast("string").alias("query_id"), "text")


@query("x_bm25", bm25_sql(FULL, L2, 10) + " select query_id, unit_id, score, rank from bm")
def _(spark, d):
    return lexical.bm25(full_queries(spark, d), Corpus(spark, d).lexical(), 10)


@query("x_bm25_thin", bm25_sql(THIN, L2, 10) + " select query_id, unit_id, score, rank from bm")
def _(spark, d):
    return lexical.bm25(thin_queries(spark, d), Corpus(spark, d).lexical(), 10)


PATTERNS = "p as (select item_id as pattern_id, text as pattern from benchmark)"


@query("x_trigram_substring", f"with {FILES}, {PATTERNS} select pattern_id, path from p join files on contains(files.text, p.pattern)")
def _(spark, d):
    f = files(spark, d)
    p = table(spark, d, "benchmark").select(F.col("item_id").alias("pattern_id"), F.col("text").alias("pattern"))
    g = p.select(F.explode(lexical.grams(F.col("pattern"))).alias("gram")).distinct()
    return lexical.substring(p, f, lexical.trigrams(f).join(g, "gram", "left_semi"))


@query("x_regex", f"with {LINES} select path, line, text from ln where regexp_matches(text, 'Lic[a-z]+ .*[0-9]\\.[0-9]')")
def _(spark, d):
    return lexical.regex(files(spark, d), r"Lic[a-z]+ .*[0-9]\.[0-9]", "Lic")


@query("x_normalized", f"with {LINES} select path, line as start, substr(text, 1, 80) as snippet, null::double as score from ln where regexp_matches(text, 'Lic[a-z]+ .*[0-9]\\.[0-9]')")
def _(spark, d):
    return lexical.normalize(lexical.regex(files(spark, d), r"Lic[a-z]+ .*[0-9]\.[0-9]", "Lic"))


@query("x_delta", f"with {L2}, t0 as (select {unit_id('path', 2, 'line', 'line')} as unit_id, regexp_extract_all(lower(text || case when doc_id % 5 = 0 then ' edited' else '' end), {TOKEN}) as ts from l2 where doc_id % 7 <> 3), t as (select unit_id, unnest(ts) as term from t0) select term, unit_id, count(*) as tf from t group by all")
def _(spark, d):
    u = l2_units(spark, d)
    touched = (F.col("doc_id") % 5 == 0) | (F.col("doc_id") % 7 == 3)
    added = u.filter((F.col("doc_id") % 5 == 0) & (F.col("doc_id") % 7 != 3)).withColumn("text", F.concat("text", F.lit(" edited")))
    return lexical.delta(rows.count(u, tokens(F.col("text"))), u.filter(touched), added).select("term", "unit_id", "tf")


# --- dense ---------------------------------------------------------------------------------


def token_features(x: str) -> str:
    return f"regexp_extract_all(lower({x}), {TOKEN})"


def bigram_features(x: str) -> str:
    t = token_features(x)
    return f"({t} || list_transform(range(1, len({t})), lambda i: {t}[i]||' '||{t}[i+1]))"


def char_features(x: str) -> str:
    return f"list_transform(range(1, greatest(length(lower({x})) - 2, 1) + 1), lambda i: substr(lower({x}), i, 3))"


def encode_sql(dim: int, src: str, name: str, idf_from: str, feat=token_features) -> str:
    """CTEs {name}: key, bucket, w for the rows (key, text) of src, with idf over idf_from."""
    h = num("f")
    return f""", {name}_df as (select f, ln(1 + (select count(*) from {idf_from}) / count(*)) as idf from (select distinct key, unnest({feat('text')}) as f from {idf_from}) group by f),
 {name}_w as (select key, {h} % {dim} as bucket, sum(case when ({h} >> 16) % 2 = 0 then 1.0::double else -1.0::double end * tf * idf) as w from (select key, f, count(*) as tf from (select key, unnest({feat('text')}) as f from {src}) group by all) join {name}_df using (f) group by all),
 {name} as (select key, bucket, w / sqrt(sum(w * w) over (partition by key)) as w from {name}_w where abs(w) > 1e-9)"""


UNITS_SQL = L2 + f", un as (select {unit_id('path', 2, 'line', 'line')} as key, path, line, text from l2)"


@query("d_encode", f"with {UNITS_SQL}{encode_sql(256, 'un', 'v', 'un')} select key as unit_id, bucket, round(w, 6) as w from v")
def _(spark, d):
    u, e = l2_units(spark, d), dense.ENCODERS[2]
    v = dense.vectors(u, e, kept(dense.document_frequency(u, e))).select("unit_id", F.explode(F.arrays_zip(F.col("f").alias("bucket"), "w")).alias("x"))
    return v.select("unit_id", "x.bucket", F.round("x.w", 6).alias("w"))


FLAT = "q as (select * from embeddings where vec_id % 10 = 0), s as (select q.vec_id as query_id, v.vec_id, round(list_dot_product(q.embedding::double[], v.embedding::double[]), 6) as score from q, embeddings v where q.vec_id <> v.vec_id), flat as (select *, row_number() over (partition by query_id order by score desc, vec_id)::int as rank from s qualify rank <= 10)"


@query("q2_flat_topk", f"with {FLAT} select query_id, vec_id, score, rank from flat")
def _(spark, d):
    v = table(spark, d, "embeddings")
    return dense.search_flat(v.filter("vec_id % 10 = 0"), v, 10)


def _recall(found, flat, by):
    hit = found.join(flat.select("query_id", "vec_id"), ["query_id", "vec_id"]).groupBy(by).agg(F.count("*").alias("hits"))
    return hit.crossJoin(flat.agg(F.count("*").alias("n"))).select(by, F.round(F.col("hits") / F.col("n"), 6).alias("neighbor_recall"))


def ivf_recall(spark, d):
    """Neighbor Recall@10 for each probe fraction."""
    v = table(spark, d, "embeddings").select("vec_id", "embedding")
    q = v.filter("vec_id % 10 = 0")
    lists = max(1, round(v.count() ** 0.5))
    c, listed = dense.build_ivf(spark, v, lists)
    return _recall(dense.search_ivf(spark, q, c, listed, 10), dense.search_flat(q, v, 10), "fraction")


@query("q2_ivf_recall")
def _(spark, d):
    return ivf_recall(spark, d)


@query("q2_ivf_exhaustive", f"with {FLAT} select query_id, vec_id, rank from flat")
def _(spark, d):
    v = table(spark, d, "embeddings").select("vec_id", "embedding")
    c, listed = dense.build_ivf(spark, v, max(1, round(v.count() ** 0.5)), rounds=3)
    return dense.search_ivf(spark, v.filter("vec_id % 10 = 0"), c, listed, 10, (1.0,)).select("query_id", "vec_id", "rank")


def hnsw_recall(spark, d):
    v = table(spark, d, "embeddings").select("vec_id", "embedding")
    q = v.filter("vec_id % 10 = 0")
    return _recall(dense.search_hnsw(q, v, 10), dense.search_flat(q, v, 10), "ef")


@query("q2_hnsw_recall")
def _(spark, d):
    return hnsw_recall(spark, d)


@query("q2_flat_by_snapshot", "with q as (select * from embeddings where vec_id % 10 = 0), s as (select q.vec_id as query_id, v.vec_id, round(list_dot_product(q.embedding::double[], v.embedding::double[]), 6) as score from q join embeddings v on q.label = v.label and q.vec_id <> v.vec_id) select *, row_number() over (partition by query_id order by score desc, vec_id)::int as rank from s qualify rank <= 10")
def _(spark, d):
    v = table(spark, d, "embeddings")
    return dense.search_flat(v.filter("vec_id % 10 = 0"), v, 10, "label")


@query("d_content_keys", f"with {L2} select sha256('hash256'||chr(31)||text) as content_key, count(*) as n from l2 group by all")
def _(spark, d):
    return l2_units(spark, d).select(dense.content_key("hash256").alias("content_key")).groupBy("content_key").agg(F.count("*").alias("n"))


@query("d_side", f"with {UNITS_SQL} select key as unit_id, path, line as start, line as \"end\", sha256('hash256'||chr(31)||text) as content_key from un")
def _(spark, d):
    return l2_units(spark, d).select("unit_id", "path", "start", "end", dense.content_key("hash256").alias("content_key"))


# --- structure -------------------------------------------------------------------------------


@query("g_contain", f"with {L1_SQL} select distinct repo as src, repo||'/'||lang as dst from files union all select repo||'/'||lang, path from files union all select path, path||'@'||start from l1 union all select path||'@'||start, path||'#'||unnest(range(start, \"end\" + 1)) from l1")
def _(spark, d):
    return structure.contain(files(spark, d))


def occ(spark, d):
    return structure.occurrences(units.level2(files(spark, d)))


@query("g_occurrences", f"with {OCC} select repo, lang, path, line, col, symbol, role from occ")
def _(spark, d):
    return occ(spark, d)


@query("g_references", f"with {REFS} select path, line, col, symbol, def_path, def_line from refs")
def _(spark, d):
    return structure.references(occ(spark, d)).select("path", "line", "col", "symbol", "def_path", "def_line")


@query("g_edges", f"with {EDGES} select src, dst, etype, anchor_file, anchor_line, anchor_col from edges")
def _(spark, d):
    return structure.edges(occ(spark, d)).drop("repo", "lang")


@query("g_type_use", f"with {REFS}, r0 as (select *, line - row_number() over (partition by path order by line) as run from l2), r1 as (select *, (row_number() over (partition by path, run order by line) - 1) // 4 as part from r0), l1 as (select path, run, part, min(line) as s, max(line) as e from r1 group by all) select r.path, r.line, r.col, r.def_path, l1.s as run_start from refs r join l1 on l1.path = r.def_path and r.def_line between l1.s and l1.e")
def _(spark, d):
    f = files(spark, d)
    return structure.type_uses(occ(spark, d), units.level1(f))


@query("g_external", f"with {PAGE_FILES}, h as (select path as src, regexp_extract(path, '^([^/]*)', 1) as repo, regexp_extract_all(text, 'href=\"([^\"]*)\"', 1) as hs from pf), e as (select src, repo, unnest(range(len(hs)))::int as anchor, unnest(hs) as href from h), t as (select src, anchor, case when starts_with(href, '/') then repo||href else href end as dst from e) select src, dst, anchor, case when dst in (select path from pf) then 'file' else 'external' end as kind from t")
def _(spark, d):
    return structure.page_imports(page_files(spark, d))


@query("g_at", f"with {OCC}, pos as (select path, (doc_id % 5)::int as line, (doc_id % 9)::int as col from files) select p.path, p.line, p.col, o.symbol, case when o.symbol is not null then 'occurrence' when l.line is not null then 'enclosing' else 'none' end as granularity from pos p left join occ o on o.path = p.path and o.line = p.line and o.col = p.col left join l2 l on l.path = p.path and l.line = p.line")
def _(spark, d):
    f = files(spark, d)
    pos = f.select("path", (F.col("doc_id") % 5).cast("int").alias("line"), (F.col("doc_id") % 9).cast("int").alias("col"))
    return structure.at(pos, occ(spark, d), units.level2(f))


def seeds(e, kind="reference"):
    return e.filter(F.col("etype") == kind).select(F.col("src").alias("seed")).distinct()


ANCHORS = """, an as (select *, row_number() over (partition by repo, lang order by path, line, col) - 1 as at0, count(*) over (partition by repo, lang) as n from occ where role = 2),
 seeds as (select distinct path||'#'||line as seed from an where n <= 5 or list_contains([n // 10, 3 * n // 10, 5 * n // 10, 7 * n // 10, 9 * n // 10], at0))"""


@query("g_khop", f"with recursive {EDGES}{ANCHORS}, st as (select distinct src as a, dst as b from edges where etype = 'reference' union select dst, src from edges where etype = 'reference'), k(seed, node, hop) as (select seed, seed, 0 from seeds union select k.seed, st.b, k.hop + 1 from k join st on st.a = k.node where k.hop < 2) select seed, node, min(hop)::int as hop from k group by all")
def _(spark, d):
    """Two steps around the lines of the navigation requests (five anchors of each snapshot)."""
    from ctxviews.operators import navigate

    c = Corpus(spark, d)
    anchors = navigate.requests(c.occurrences()).select(F.concat("path", F.lit("#"), F.col("line").cast("string")).alias("seed")).distinct()
    return structure.neighbours(anchors, c.edges(), 2)


@query("g_dependencies", f"with recursive {EDGES}, sd as (select distinct src as seed from edges where etype = 'import'), st as (select distinct src as a, dst as b from edges where etype = 'import'), k(seed, node, hop) as (select seed, seed, 0 from sd union select k.seed, st.b, k.hop + 1 from k join st on st.a = k.node where k.hop < 2) select seed, node, min(hop)::int as hop from k group by all")
def _(spark, d):
    e = structure.imports(files(spark, d), few, kept)
    return structure.dependencies(e.nexts.select("repo", "lang", F.col("node").alias("seed")), e, 2, kept)


@query("g_route", f"with recursive {EDGES}, st as (select distinct src as a, dst as b from edges), im as (select distinct src, dst from edges where etype = 'import'), pr as (select distinct e1.src as a, e2.dst as b from im e1 join im e2 on e1.dst = e2.src), k(seed, node, hop) as (select distinct a, a, 0 from pr union select k.seed, st.b, k.hop + 1 from k join st on st.a = k.node where k.hop < 3), m as (select seed, node, min(hop)::int as hops from k group by all) select pr.a, pr.b, m.hops from pr left join m on m.seed = pr.a and m.node = pr.b")
def _(spark, d):
    """References join lines and imports files: only if a file is named like a line, routes need both kinds."""
    s = structure.imports(files(spark, d), few, kept)
    if not structure.has_lines(s):
        return structure.import_routes(s, 2, 3)
    e = Corpus(spark, d).edges()
    imp = e.filter("etype = 'import'").select("src", "dst").distinct()
    pairs = imp.select(F.col("src").alias("a"), F.col("dst").alias("m")).join(imp.select(F.col("src").alias("m"), F.col("dst").alias("b")), "m").select("a", "b").distinct()
    return structure.route(kept(pairs), e, 3, kept)


@query("g_facts", f"with {EDGES}, v as (select path||chr(31)||line||chr(31)||symbol as payload from decl), e as (select repo||chr(31)||lang||chr(31)||src||chr(31)||dst||chr(31)||etype||chr(31)||anchor_file||chr(31)||anchor_line||chr(31)||anchor_col as payload from edges) select 'vertex' as tag, payload, count(*) as mult from v group by payload union all select 'edge', payload, count(*) from e group by payload")
def _(spark, d):
    v = structure.declarations(units.level2(files(spark, d))).select("path", F.col("line").cast("string").alias("line"), "symbol")
    return structure.facts(v, structure.edges(occ(spark, d)))


REL = """select 'r'||n_regionkey as src, 'n'||n_nationkey as dst, 'contain' as etype from nation union all select 'n'||c_nationkey, 'c'||c_custkey, 'contain' from customer
 union all select 'c'||o_custkey, 'o'||o_orderkey, 'contain' from o union all select 'o'||l_orderkey, 'l'||l_orderkey||':'||l_linenumber, 'contain' from li
 union all select 'l'||l_orderkey||':'||l_linenumber, 'p'||l_partkey, 'reference' from li union all select 'l'||l_orderkey||':'||l_linenumber, 's'||l_suppkey, 'reference' from li
 union all select 's'||s_suppkey, 'n'||s_nationkey, 'import' from supplier"""


def rel_tables(spark, d):
    return {n: table(spark, d, n) for n in ("nation", "customer", "orders", "lineitem", "supplier")}


@query("g_relational", f"with o as (select * from orders), li as (select * from lineitem where l_orderkey in (select o_orderkey from o)), g as ({REL}) select etype, count(*) as n, sum({num('src||chr(31)||dst')})::bigint as digest from g group by etype")
def _(spark, d):
    g = structure.relational_graph(rel_tables(spark, d))
    return g.groupBy("etype").agg(F.count("*").alias("n"), F.sum(md5_number(F.concat_ws("\x1f", "src", "dst"))).alias("digest"))


@query("g_relational_delta", f"with mo as (select strftime(o_orderdate, '%Y-%m') as m, count(*) from orders group by all order by m), w as (select m from mo limit 1 offset 12), o as (select * from orders where strftime(o_orderdate, '%Y-%m') = (select m from w)), li as (select * from lineitem where l_orderkey in (select o_orderkey from o)) select 'c'||o_custkey as src, 'o'||o_orderkey as dst, 'contain' as etype from o union all select 'o'||l_orderkey, 'l'||l_orderkey||':'||l_linenumber, 'contain' from li union all select 'l'||l_orderkey||':'||l_linenumber, 'p'||l_partkey, 'reference' from li union all select 'l'||l_orderkey||':'||l_linenumber, 's'||l_suppkey, 'reference' from li")
def _(spark, d):
    t = rel_tables(spark, d)
    months = [r.m for r in t["orders"].select(F.date_format("o_orderdate", "yyyy-MM").alias("m")).distinct().orderBy("m").limit(13).collect()]
    new, old = structure.relational_graph(t, months[12]), structure.relational_graph(t, months[11])
    return new.exceptAll(old)
