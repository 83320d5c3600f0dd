"""The relational surface around the views, and the batch twins of the streams."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import md5_number, tokens
from ctxviews.queries import FILES, TOKEN, num, query
from ctxviews.sources.tables import files, page_files, table
from ctxviews.streaming import feeds


@query("op_scan_filter", "select o_orderkey, o_custkey, o_totalprice from orders where o_orderstatus = 'F' and o_totalprice > 200000")
def _(spark, d):
    return table(spark, d, "orders").filter((F.col("o_orderstatus") == "F") & (F.col("o_totalprice") > 200000)).select("o_orderkey", "o_custkey", "o_totalprice")


@query("op_filter", "select l_orderkey, l_linenumber from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01' and l_discount between 0.05 and 0.07 and l_quantity < 24 and l_returnflag in ('A','N')")
def _(spark, d):
    c = F.col
    return table(spark, d, "lineitem").filter((c("l_shipdate") >= "1995-01-01") & (c("l_shipdate") < "1996-01-01") & c("l_discount").between(0.05, 0.07) & (c("l_quantity") < 24) & c("l_returnflag").isin("A", "N")).select("l_orderkey", "l_linenumber")


@query("op_join_broadcast", "select s_nationkey, p_brand, count(*) as n, round(sum(l_quantity), 2) as qty from lineitem join part on p_partkey = l_partkey join supplier on s_suppkey = l_suppkey group by all")
def _(spark, d):
    li = table(spark, d, "lineitem").select("l_partkey", "l_suppkey", "l_quantity")
    s = table(spark, d, "supplier").select("s_suppkey", "s_nationkey")  # below the threshold Spark broadcasts it, by its size
    return li.join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(table(spark, d, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).groupBy("s_nationkey", "p_brand").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"))


@query("op_join_merge", "select o_orderpriority, count(*) as n, round(sum(l_extendedprice), 2) as total from orders join lineitem on o_orderkey = l_orderkey group by all")
def _(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_orderpriority")
    li = table(spark, d, "lineitem").select("l_orderkey", "l_extendedprice")
    return o.hint("merge").join(li, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


@query("op_join_outer", "select c_custkey, o_orderkey from customer full join orders on c_custkey = o_custkey")
def _(spark, d):
    c = table(spark, d, "customer").select("c_custkey")
    o = table(spark, d, "orders").select("o_orderkey", "o_custkey")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey"), "full").select("c_custkey", "o_orderkey")


@query("op_semi", "select doc_id from documents where doc_id in (select doc_id from labels where quality = 1)")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels").filter("quality = 1").select("doc_id"), "doc_id", "left_semi")


@query("op_anti", "select doc_id from documents where doc_id not in (select doc_id from labels)")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id").join(table(spark, d, "labels").select("doc_id"), "doc_id", "left_anti")


@query("op_theta", "select n_nationkey, count(*) as n from nation join supplier on s_acctbal > n_nationkey * 300 group by all")
def _(spark, d):
    n = F.broadcast(table(spark, d, "nation").select("n_nationkey"))  # 25 rows at every scale
    return table(spark, d, "supplier").join(n, F.col("s_acctbal") > F.col("n_nationkey") * 300).groupBy("n_nationkey").agg(F.count("*").alias("n"))


@query("op_range_join", "with iv as (select user_id, ts as a, ts + interval 2 hour as b from events where event_type = 'signup') select e.event_id, iv.user_id, iv.a as started from events e join iv on iv.user_id = e.user_id and e.ts > iv.a and e.ts <= iv.b")
def _(spark, d):
    e = table(spark, d, "events")
    bin_ = lambda c: F.date_trunc("hour", c)
    iv = e.filter("event_type = 'signup'").select(F.col("user_id").alias("u"), F.col("ts").alias("a"), (F.col("ts") + F.expr("interval 2 hours")).alias("b"))
    iv = iv.withColumn("bin", F.explode(F.array(bin_(F.col("a")), bin_(F.col("a") + F.expr("interval 1 hour")), bin_(F.col("a") + F.expr("interval 2 hours")))))
    p = e.select("event_id", "user_id", "ts", bin_(F.col("ts")).alias("bin"))
    return p.join(iv, (p.user_id == iv.u) & (p.bin == iv.bin) & (F.col("ts") > F.col("a")) & (F.col("ts") <= F.col("b"))).select("event_id", F.col("u").alias("user_id"), F.col("a").alias("started"))


@query("op_asof", "select v.event_id, v.user_id, (select max(p.ts) from events p where p.user_id = v.user_id and p.event_type = 'purchase' and p.ts <= v.ts) as built from events v where v.event_type = 'view'")
def _(spark, d):
    e = table(spark, d, "events").filter("event_type in ('view', 'purchase')").select("event_id", "user_id", "ts", "event_type")
    w = W.partitionBy("user_id").orderBy("ts").rangeBetween(W.unboundedPreceding, W.currentRow)
    return e.withColumn("built", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(w)).filter("event_type = 'view'").select("event_id", "user_id", "built")


@query("op_agg", f"select source, count(*) as n, sum(len(regexp_extract_all(lower(coalesce(text,'')), {TOKEN})))::bigint as tokens, max(n_chars) as longest from documents group by source")
def _(spark, d):
    return table(spark, d, "documents").groupBy("source").agg(F.count("*").alias("n"), F.sum(F.size(tokens(F.coalesce("text", F.lit(""))))).alias("tokens"), F.max("n_chars").alias("longest"))


@query("op_distinct", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by all")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers"))


GS = "select event_type, strftime(ts, '%Y-%m-%d') as day, count(*) as n, round(sum(value), 4) as total from events group by "


def _events(spark, d):
    return table(spark, d, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd"))




def _two():
    return F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")


@query("op_rollup", GS + "rollup (event_type, day)")
def _(spark, d):
    return _events(spark, d).rollup("event_type", "day").agg(*_two())


@query("op_cube", GS + "cube (event_type, day)")
def _(spark, d):
    return _events(spark, d).cube("event_type", "day").agg(*_two())


@query("op_grouping_sets", GS + "grouping sets ((event_type), (day))")
def _(spark, d):
    return _events(spark, d).groupingSets([["event_type"], ["day"]], "event_type", "day").agg(*_two())


@query("op_window_rank", "select o_orderkey, row_number() over w::int as rn, rank() over w2::int as rk, dense_rank() over w2::int as dr, ntile(4) over w::int as nt from orders window w as (partition by o_custkey order by o_totalprice desc, o_orderkey), w2 as (partition by o_custkey order by o_orderpriority)")
def _(spark, d):
    w = W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    w2 = W.partitionBy("o_custkey").orderBy("o_orderpriority")
    return table(spark, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w2).alias("rk"), F.dense_rank().over(w2).alias("dr"), F.ntile(4).over(w).alias("nt"))


@query("op_window_frame", "select event_id, lag(value) over w as before, lead(value) over w as after, round(sum(value) over (w rows between 3 preceding and current row), 6) as moving, first_value(event_type) over w as first_type from events window w as (partition by user_id order by ts, event_id)")
def _(spark, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return table(spark, d, "events").select("event_id", F.lag("value").over(w).alias("before"), F.lead("value").over(w).alias("after"), F.round(F.sum("value").over(w.rowsBetween(-3, 0)), 6).alias("moving"), F.first("event_type").over(w).alias("first_type"))


@query("op_topk", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
def _(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("op_group_topk", "select l_returnflag, l_orderkey, l_linenumber, row_number() over (partition by l_returnflag order by l_extendedprice desc, l_orderkey, l_linenumber)::int as rn from lineitem qualify rn <= 5")
def _(spark, d):
    w = W.partitionBy("l_returnflag").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber")
    return table(spark, d, "lineitem").select("l_returnflag", "l_orderkey", "l_linenumber", F.row_number().over(w).alias("rn")).filter("rn <= 5")


@query("op_setops", "(select l_partkey as k from lineitem where l_quantity < 10 intersect all select l_partkey from lineitem where l_quantity > 40) union all (select p_partkey from part except select l_partkey from lineitem)")
def _(spark, d):
    li, p = table(spark, d, "lineitem"), table(spark, d, "part")
    a = li.filter("l_quantity < 10").select(F.col("l_partkey").alias("k")).intersectAll(li.filter("l_quantity > 40").select("l_partkey"))
    return a.union(p.select("p_partkey").subtract(li.select("l_partkey")))


@query("op_strings", "select doc_id, lower(substr(text, 1, 20)) as head, len(string_split(text, chr(10))) as lines, levenshtein(doc_id::varchar, source) as lev, md5(coalesce(text, '')) as m from documents")
def _(spark, d):
    t = F.col("text")
    return table(spark, d, "documents").select("doc_id", F.lower(F.substring(t, 1, 20)).alias("head"), F.size(F.split(t, "\n", -1)).cast("long").alias("lines"), F.levenshtein(F.col("doc_id").cast("string"), "source").cast("long").alias("lev"), F.md5(F.coalesce(t, F.lit(""))).alias("m"))


@query("op_dates", "select strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as month, count(*) as n, min(datediff('day', date_trunc('month', o_orderdate), o_orderdate)) as first_day from orders group by all")
def _(spark, d):
    m = F.date_trunc("month", "o_orderdate")
    return table(spark, d, "orders").groupBy(F.date_format(m, "yyyy-MM-dd").alias("month")).agg(F.count("*").alias("n"), F.min(F.datediff("o_orderdate", m)).cast("long").alias("first_day"))


@query("op_math", "select l_linestatus, round(ln(sum(l_quantity)), 6) as lg, round(quantile_cont(l_discount, 0.9), 6) as p90, round(sqrt(avg(l_tax)), 6) as rt, round(stddev_samp(l_quantity), 6) as sd from lineitem group by all")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy("l_linestatus").agg(F.round(F.log(F.sum("l_quantity")), 6).alias("lg"), F.round(F.percentile("l_discount", 0.9), 6).alias("p90"), F.round(F.sqrt(F.avg("l_tax")), 6).alias("rt"), F.round(F.stddev_samp("l_quantity"), 6).alias("sd"))


@query("op_arrays", "select vec_id, len(embedding)::int as dim, round(list_sum(list_transform(embedding, lambda x: x::double * x::double)), 6) as norm2, len(list_filter(embedding, lambda x: x > 0))::int as positive from embeddings")
def _(spark, d):
    e = F.col("embedding")
    return table(spark, d, "embeddings").select("vec_id", F.size(e).alias("dim"), F.round(F.aggregate(F.transform(e, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x), 6).alias("norm2"), F.size(F.filter(e, lambda x: x > 0)).alias("positive"))


@query("op_maps", "select user_id, array_to_string(list(event_type||'='||n order by event_type), ',') as counts from (select user_id, event_type, count(*) as n from events group by all) group by user_id")
def _(spark, d):
    g = table(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    m = g.groupBy("user_id").agg(F.map_from_entries(F.array_sort(F.collect_list(F.struct("event_type", "n")))).alias("m"))
    return m.select("user_id", F.concat_ws(",", F.transform(F.map_entries("m"), lambda x: F.concat(x["key"], F.lit("="), x["value"].cast("string")))).alias("counts"))


@query("op_json", "select event_type, sum(json_extract(props, '$.k')::bigint)::bigint as k from events group by all")
def _(spark, d):
    return table(spark, d, "events").groupBy("event_type").agg(F.sum(F.from_json("props", "k bigint")["k"]).alias("k"))


@query("op_sketches")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_quantity", 0.5).alias("median"))


@query("op_sample", f"select doc_id from documents where {num('doc_id::varchar')} % 10 = 0")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id").filter(md5_number(F.col("doc_id").cast("string")) % 10 == 0)


@query("op_exists", "select item_id from benchmark b where exists (select 1 from documents d where contains(d.text, b.text))")
def _(spark, d):
    from ctxviews.operators import lexical
    from ctxviews.plans.corpus import Corpus

    c, b = Corpus(spark, d), table(spark, d, "benchmark")
    hit = lexical.holding(b.select(F.col("item_id").alias("query_id"), "text"), c.units(0), c.lexical(0)).select(F.col("query_id").alias("item_id"))
    return b.select("item_id").join(hit, "item_id", "left_semi")


@query("op_scalar_subquery", "select o_orderkey from orders where o_totalprice > 1.5 * (select avg(o_totalprice) from orders)")
def _(spark, d):
    o = table(spark, d, "orders").select("o_orderkey", "o_totalprice")
    return o.crossJoin(F.broadcast(o.agg(F.avg("o_totalprice").alias("a")))).filter("o_totalprice > 1.5 * a").select("o_orderkey")


@query("op_pivot", "select user_id, count(*) filter (where event_type = 'click') as click, count(*) filter (where event_type = 'error') as error from events group by user_id")
def _(spark, d):
    return table(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "error"]).agg(F.count("event_id")).na.fill(0)


@query("op_roundtrip", f"with {FILES} select lang, count(*) as n, count(distinct path) as paths from files group by lang")
def _(spark, d):
    """A partitioned write, read back with a pruned scan of what was written."""
    import uuid

    from ctxviews.plans.store import shared_dir

    path = f"{shared_dir(spark)}/roundtrip-{uuid.uuid4().hex}"
    files(spark, d).select("path", "lang").write.partitionBy("lang").parquet(path)
    return spark.read.parquet(path).groupBy("lang").agg(F.count("*").alias("n"), F.countDistinct("path").alias("paths"))


PAGES_SQL = "with pf as (select page_id, regexp_extract(url, '^[a-z]+://([^?#]*)', 1) as path, coalesce(html,'') as text from pages) select page_id, len(regexp_extract_all(text, '<(h1|p|li)\\b'))::bigint as leaves, len(regexp_extract_all(text, 'href=\"'))::bigint as links from pf"


@query("op_udtf_pages", PAGES_SQL)
def _(spark, d):
    """An Arrow UDTF that parses pages, joined laterally."""
    from ctxviews.functions.udtf import page_counts

    p = page_files(spark, d).select("page_id", "text")
    spark.udtf.register("ctx_page_counts", page_counts())
    p.createOrReplaceTempView("ctx_page_files")
    return spark.sql("select page_id, leaves, links from ctx_page_files, lateral ctx_page_counts(text)")


# --- batch twins of the streams ------------------------------------------------------------------


def _ev(spark, d):
    return table(spark, d, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("st_tumble", "select event_type, epoch(time_bucket(interval 1 hour, ts))::bigint as start, count(*) as n, round(sum(value), 4) as cost from events group by all")
def _(spark, d):
    return feeds.tumbling(_ev(spark, d))


@query("st_slide", "select event_type, epoch(w)::bigint as start, count(*) as n from (select event_type, ts, unnest([time_bucket(interval 15 minute, ts) - interval 45 minute, time_bucket(interval 15 minute, ts) - interval 30 minute, time_bucket(interval 15 minute, ts) - interval 15 minute, time_bucket(interval 15 minute, ts)]) as w from events) group by all")
def _(spark, d):
    return feeds.sliding(_ev(spark, d))


@query("st_session", "with a as (select user_id, ts, case when ts - lag(ts) over w < interval 30 minute then 0 else 1 end as brk from events window w as (partition by user_id order by ts)), b as (select *, sum(brk) over (partition by user_id order by ts rows unbounded preceding) as s from a) select user_id, floor(epoch(min(ts)))::bigint as start, count(*) as n from b group by user_id, s")
def _(spark, d):
    return feeds.sessions(_ev(spark, d))


@query("st_dedup", "select event_id, user_id from (select event_id, user_id from events group by all)")
def _(spark, d):
    return feeds.deduplicated(_ev(spark, d).union(_ev(spark, d).limit(50)))


@query("st_join", "select c.event_id as click, s.event_id as signup from events c join events s on s.user_id = c.user_id and c.event_type = 'click' and s.event_type = 'signup' and c.ts >= s.ts and c.ts <= s.ts + interval 1 hour")
def _(spark, d):
    return feeds.clicks_after_signup(_ev(spark, d), _ev(spark, d))


@query("st_late", "with x as (select *, max(ts) over (order by event_id rows between unbounded preceding and 1 preceding) as seen from events) select count(*) as n, count(*) filter (where seen is not null and ts < seen - interval 30 minute) as late from x")
def _(spark, d):
    return feeds.late(_ev(spark, d))


@query("st_lag", "select user_id, count(*) filter (where event_type = 'purchase') as head, count(*) filter (where event_type = 'purchase' and ts <= vt) as built from (select *, max(case when event_type = 'view' then ts end) over (partition by user_id) as vt from events) group by user_id")
def _(spark, d):
    return feeds.lag(_ev(spark, d))
