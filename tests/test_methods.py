"""Worked examples and invariants of the methods."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from ctxviews.operators import costs, delivery, dense, lexical, maintain, metrics, navigate, rank, stats, structure, units, versions
from ctxviews.plans import catalog, plan, session, tools, trace
from ctxviews.queries import upkeep, views
from ctxviews.sources.tables import files, table
from ctxviews.streaming import feeds

DATA = "/root/testdata/sf0.001"


def rows(df, *cols):
    return sorted(tuple(r) for r in df.select(*cols).collect())


def test_fusion_example(spark):
    d = spark.createDataFrame([("q", "a", 1), ("q", "b", 2)], "query_id string, vid string, rank int")
    g = spark.createDataFrame([("q", "b", 1), ("q", "c", 2)], "query_id string, vid string, rank int")
    out = rank.rrf([(d, 1.0), (g, 0.5)], 10, "vid").orderBy("rank").collect()
    assert [r.vid for r in out] == ["b", "a", "c"]
    assert out[0].score == pytest.approx(1 / 62 + 0.5 / 61, abs=1e-8) and out[2].score == pytest.approx(0.5 / 62, abs=1e-8)


def test_zero_weight_keeps_dense_order(spark):
    d = spark.createDataFrame([("q", "a#1", 1), ("q", "b#1", 2), ("q", "c#1", 3)], "query_id string, vid string, rank int")
    e = spark.createDataFrame([("c#1", "a#1", "reference")], "src string, dst string, etype string")
    w = spark.createDataFrame([(0.0,)], "w_g double")
    assert [r.vid for r in rank.dense_graph_fusion(d, e, w).orderBy("rank").collect()] == ["a#1", "b#1", "c#1"]


def test_success_needs_all_targets(spark):
    ranked = spark.createDataFrame([("q", "a", 1), ("q", "x", 2)], "query_id string, path string, rank int")
    t = spark.createDataFrame([("q", "a"), ("q", "b")], "query_id string, path string")
    r = metrics.file_recall(ranked, t, 10).first()
    assert (r.recall, r.success) == (0.5, 0.0)


def test_speedup_example(spark):
    g = spark.range(1).select(costs.speedup(F.lit(60.0), F.lit(6.0), F.lit(10.0)).alias("five"), costs.speedup(F.lit(60.0), F.lit(6.0), F.lit(10.0), 1).alias("one")).first()
    assert (g.five, g.one) == (7.5, 3.75)


def test_lifecycle_example(spark):
    c = spark.createDataFrame([("s", 116.7, 7.40, 0.727, 20)], "snapshot string, b double, l double, s double, n int")
    r = {x.q: x for x in costs.project(c, spark).collect()}
    assert round(r[20].resident, 2) == 6.24 and round(r[20].isolated, 2) == 13.27
    assert r[1].resident == r[1].isolated


def test_pareto(spark):
    p = spark.createDataFrame([("p", 1, 0.5), ("p", 2, 0.7), ("p", 3, 0.6), ("p", 4, 0.9)], "panel string, cost int, quality double")
    assert [r.cost for r in metrics.pareto(p, "cost", "quality", ["panel"]).orderBy("cost").collect()] == [1, 2, 4]


def test_bootstrap_of_constant_is_a_point(spark):
    d = spark.createDataFrame([(f"r{i % 4}", 0.25) for i in range(40)], "repo string, x double")
    r = stats.bootstrap(spark, d, "repo", "x", [], 100).first()
    assert r.lower == r.mean == r.upper == 0.25


def test_retention_accounting(spark):
    """Eager charges every observation again; compact replaces history by the seed after the first read."""
    long = "word " * 60
    conv = [(1, 0, "system", "s " * 10), (1, 1, "user", "q " * 20), (1, 2, "assistant", long), (1, 3, "user", "o " * 30), (1, 4, "assistant", "c " * 5), (1, 5, "user", "o " * 30), (1, 6, "assistant", "c " * 5)]
    df = spark.createDataFrame(conv, "conv_id long, turn long, role string, text string")
    block = spark.createDataFrame([(1, 100)], "traj long, tokens long")
    got = {r.policy: r for r in delivery.replay_tokens(df, block).collect()}
    grep = [30, 30 + 60 + 30, 30 + 60 + 30 + 5 + 30]
    out = 60 + 5 + 5
    assert got["grep"].tokens == sum(grep) + out and got["eager"].tokens == sum(grep) + 300 + out
    # latest read (30), first 600 characters of the completion (60 words) and the read's path (turn, /, 3)
    seed = 30 + 60 + 3
    assert got["compact"].tokens == 130 + (30 + seed) + (30 + seed + 5 + 30) + out


def test_diff_round_trip_and_earliest_hunk():
    rng = np.random.default_rng(3)
    for _ in range(300):
        a = [str(x) for x in rng.integers(0, 4, rng.integers(0, 9))]
        b = [str(x) for x in rng.integers(0, 4, rng.integers(0, 9))]
        h = versions.diff(a, b)
        assert versions.apply(h, a, b) == b
        assert h == sorted(h)
    assert versions.diff(list("xaaay"), list("xaay")) == [(1, 1, 1, 0)]


def test_repair_example_counts(spark):
    """One symbol goes, the next shifts with two rebased anchors, one body changes, one stays, one comes."""
    c = [("r", "l", "f", s, 1, k, o, n) for s, k, o, n in [("gone", "deleted", 0, None), ("shift", "shifted", 4, 2), ("body", "affected", 6, 4), ("same", "unchanged", 8, 8), ("come", "added", None, 10)]]
    classes = spark.createDataFrame(c, "repo string, lang string, path string, symbol string, ordinal int, class string, old_line int, new_line int")
    u = [("r", "l", "f", 2, "x", "rebased"), ("r", "l", "f", 3, "y", "rebased"), ("r", "l", "f", 4, "k", "kept"), ("r", "l", "f", 5, "n", "new"), ("r", "l", "f", 10, "m", "new")]
    uses = spark.createDataFrame(u, "repo string, lang string, path string, line int, symbol string, state string")
    r = maintain.request_counts(classes, uses).first()
    assert (r.file_refs, r.file_defs, r.symbol_refs, r.symbol_defs) == (4, 5, 1, 4)
    assert round(1 - (r.symbol_refs + r.symbol_defs) / (r.file_refs + r.file_defs), 3) == 0.444


def test_closure_equals_rebuild(spark):
    m = upkeep.graph_match(spark, DATA).collect()
    assert m and all(r.closure_match for r in m)


def test_units_slice_back(spark):
    f = files(spark, DATA)
    u = units.level1(f).join(f.select("path", F.split("text", "\n", -1).alias("ls")), "path")
    assert u.filter(F.concat_ws("\n", F.slice("ls", F.col("start") + 1, F.col("end") - F.col("start") + 1)) != F.col("text")).count() == 0


def test_ann_against_flat(spark):
    v = table(spark, DATA, "embeddings").select("vec_id", "embedding")
    q = v.filter("vec_id % 50 = 0")
    flat = rows(dense.search_flat(q, v, 10), "query_id", "vec_id", "rank")
    x = np.array([r.embedding for r in q.orderBy("vec_id").collect()])
    ids = np.array([r.vec_id for r in q.orderBy("vec_id").collect()])
    assert rows(dense.search_blocks(spark, x, ids, v, 10, block=4), "query_id", "vec_id", "rank") == flat
    c, listed = dense.build_ivf(spark, v, 12, 3)
    assert rows(dense.search_ivf(spark, q, c, listed, 10, (1.0,)), "query_id", "vec_id", "rank") == flat
    wide = dense.search_hnsw(q, v, 10, (600,), shards=2)
    hit = len(set(rows(wide, "query_id", "vec_id")) & {x[:2] for x in flat})
    assert hit >= 0.98 * len(flat)


def test_delta_without_change_encodes_nothing(spark):
    u = views.l2_units(spark, DATA)
    assert dense.delta(u, u, "hash256").filter("action = 'encode'").count() == 0
    assert dense.index_action(1, 10) == "mutate" and dense.index_action(3, 10) == "rebuild" and dense.index_action(0, 0) == "rebuild"


def test_plan_legality():
    caps = {"text_search", "semantic_search", "references"}
    assert plan.RankedPlan("D", expand=True).validate(caps)
    for bad in (plan.RankedPlan("A", expand=True), plan.RankedPlan("A", 10, 20, "small"), plan.RankedPlan("E"), plan.RankedPlan("B", k_pre=5)):
        with pytest.raises(ValueError):
            bad.validate(caps)
    with pytest.raises(catalog.ViewUnavailable):
        plan.RankedPlan("B").validate({"text_search"})


def test_rerank_stays_within_cut(spark):
    c = spark.createDataFrame([("q", "alpha beta", f"u{i}", f"alpha {i}", i) for i in range(1, 21)], "query_id string, query_text string, unit_id string, text string, rank int")
    for s in rank.SCORERS:
        got = rank.pointwise(c, s, 5, 5)
        assert {r.unit_id for r in got.collect()} == {f"u{i}" for i in range(1, 6)}


def test_scorer_sits_above_the_cut(spark):
    c = spark.createDataFrame([("q", "a", "u", "a", 1)], "query_id string, query_text string, unit_id string, text string, rank int")
    p = rank.pointwise(c, "small", 5, 5)._jdf.queryExecution().optimizedPlan().toString()
    assert p.index("Window") < p.rindex("rank") and "<= 5" in p


def test_scan_is_pruned_and_pushed(spark):
    from ctxviews import registry

    p = registry.QUERIES["op_scan_filter"](spark, DATA)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(o_orderstatus)" in p and "o_orderdate" not in p.split("ReadSchema")[1].splitlines()[0]


def test_navigation_limits_and_normal_form(spark):
    f = files(spark, DATA)
    occ = structure.occurrences(units.level2(f))
    r = navigate.requests(occ)
    s = navigate.static(r, occ)
    assert s.filter((F.col("capability") == "definition") & (F.size("locs") > 8)).count() == 0
    assert s.filter(F.col("locs") != F.array_distinct("locs")).count() == 0
    assert s.filter(F.size("locs") == 0).count() == 0


def test_catalog_lifecycle(spark, tmp_path):
    def ok(location):
        spark.range(3).write.parquet(location)
        return {"backend": "lines"}

    def broken(location):
        raise catalog.BuildPreparationMissing("no preparation")

    entries = catalog.materialize(str(tmp_path), "v1", {"lexical": ok, "structural": broken, "dense": ok})
    assert [e.status for e in entries] == ["ok", "failed", "ok"]
    handles, warnings = catalog.open_views(spark, str(tmp_path), "v1", ["lexical"], head="v2")
    assert handles["lexical"].count() == 3 and warnings
    with pytest.raises(catalog.ViewUnavailable):
        catalog.open_views(spark, str(tmp_path), "v1", ["structural"])
    with pytest.raises(catalog.ViewUnavailable):
        session.connect(spark, catalog=(str(tmp_path), "v9", ["lexical"]))
    with pytest.raises(ValueError):
        session.connect(spark)
    again = session.connect(spark, repo=(str(tmp_path), "v1", {"lexical": broken}))  # cached: the builder is not called
    assert set(again.handles) == {"lexical", "dense"}
    entries[0].schema_version = 99
    catalog.publish(str(tmp_path), "v1", entries)
    with pytest.raises(catalog.ViewSchemaMismatch):
        catalog.open_views(spark, str(tmp_path), "v1", ["lexical"])


def test_backends_and_tools(spark):
    assert catalog.BackendRegistry.pick("pages", "graph") == "href"
    with pytest.raises(catalog.BuildPreparationMissing):
        catalog.BackendRegistry.pick("benchmark", "graph")
    assert tools.required_views(["bm25_search", "definition"]) == {"lexical", "structural"}
    assert tools.guard(["bm25_search", "route"], {"text_search"}, {"text_search"}) == (["bm25_search"], ["bm25_search answers from a stale view"])
    f = files(spark, DATA)
    u = views.l2_units(spark, DATA)
    occ = structure.occurrences(units.level2(f))
    tools.register(spark, u, occ, structure.edges(occ))
    s = occ.filter("role = 1").orderBy("path", "line").first()
    assert spark.sql(f"select * from ctx_definition('{s.symbol}')").filter(F.col("path") == s.path).count() >= 1
    assert tools.search(spark, u, u.orderBy("unit_id").first().text, 3).count() == 3


def test_view_data_source(spark, tmp_path):
    import json

    from ctxviews.sources.datasource import ViewDataSource

    spark.dataSource.register(ViewDataSource)
    spark.range(6).select(F.col("id").alias("n"), (F.col("id") % 3).cast("int").alias("level")).write.partitionBy("level").parquet(str(tmp_path / "v"))
    (tmp_path / "v/_view.json").write_text(json.dumps({"schema": "n long, level int"}))
    v = spark.read.format("ctxview").option("location", str(tmp_path / "v")).load()
    assert rows(v, "n", "level") == [(i, i % 3) for i in range(6)]
    assert rows(v.filter("level = 1"), "n") == [(1,), (4,)]


def test_trace(spark, tmp_path):
    t = trace.Trace("s")
    t.add("open", "lexical")
    t.append(spark, str(tmp_path / "t"))
    t.add("call", provider="static", prompt=3, completion=1)
    t.append(spark, str(tmp_path / "t"))
    assert spark.read.parquet(str(tmp_path / "t")).agg(F.sum("prompt_tokens")).first()[0] == 3
    assert rows(spark.read.parquet(str(tmp_path / "t")), "seq", "event") == [(0, "open"), (1, "call")]


def test_lexical_delta_is_rebuild(spark):
    u = views.l2_units(spark, DATA).select("unit_id", "text").dropDuplicates(["unit_id"])
    gone = u.filter("substr(unit_id, 1, 1) = 'a'")
    got = lexical.delta(lexical.postings(u), gone, gone.withColumn("text", F.lit("alpha beta")))
    want = lexical.postings(u.join(gone, "unit_id", "left_anti").select("unit_id", "text").unionByName(gone.withColumn("text", F.lit("alpha beta")).select("unit_id", "text")))
    assert got.select("term", "unit_id", "tf").exceptAll(want.select("term", "unit_id", "tf")).count() == 0


@pytest.mark.parametrize("name", ["tumbling", "sliding", "sessions"])
def test_stream_equals_batch(spark, tmp_path, name):
    e = table(spark, DATA, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    (e.coalesce(1) if name == "sessions" else e.repartitionByRange(3, "ts")).write.parquet(str(tmp_path / "in"))  # files follow time: nothing is late
    f = getattr(feeds, name)
    s = feeds.stream(spark, str(tmp_path / "in"), e.schema)
    got = feeds.drain(f(s), f"drained_{name}", "complete")
    want = f(e)
    assert rows(got, *[c for c in want.columns if c != "cost"]) == rows(want, *[c for c in want.columns if c != "cost"])


def test_lag_stream_equals_batch(spark, tmp_path):
    e = table(spark, DATA, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    cuts = e.select(F.percentile(F.unix_micros("ts"), F.array(F.lit(0.3), F.lit(0.7)))).first()[0]
    for lo, hi in ((None, cuts[0]), (cuts[0], cuts[1]), (cuts[1], None)):  # one file after the other, as time goes
        at = F.unix_micros("ts")
        part = e.filter((at > lo if lo else F.lit(True)) & (at <= hi if hi else F.lit(True)))
        part.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    out = feeds.drain(feeds.lag_stream(feeds.stream(spark, str(tmp_path / "in"), e.schema)), "drained_lag", "update")
    last = out.filter("not ended").groupBy("user_id").agg(F.max("head").alias("head"), F.max("built").alias("built"))
    assert rows(last, "user_id", "head", "built") == rows(feeds.lag(e).na.fill(0), "user_id", "head", "built")


def test_incremental_stream_is_idempotent(spark, tmp_path):
    e = table(spark, DATA, "events").select("event_id", "event_type")
    e.repartition(2).write.parquet(str(tmp_path / "in"))
    seen = []
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    feeds.maintain(s, lambda b, i: seen.append((i, b.count())), str(tmp_path / "ck")).awaitTermination()
    n = len(seen)
    feeds.maintain(s, lambda b, i: seen.append((i, b.count())), str(tmp_path / "ck")).awaitTermination()
    assert len(seen) == n and sum(c for _, c in seen) == e.count()


# --- stored views and block search ---------------------------------------------------------------


def test_views_are_built_once_and_follow_the_tables(spark, tmp_path):
    from ctxviews.plans import store

    spark.range(5).write.parquet(str(tmp_path / "t.parquet"))
    calls = []

    def build():
        calls.append(1)
        return spark.read.parquet(str(tmp_path / "t.parquet")).withColumn("x", F.col("id") * 2)

    for _ in range(3):
        assert store.stored(spark, str(tmp_path), "twice", build, ("t",)).count() == 5
    assert len(calls) == 1
    spark.range(3).write.mode("append").parquet(str(tmp_path / "t.parquet"))
    assert store.stored(spark, str(tmp_path), "twice", build, ("t",)).count() == 8 and len(calls) == 2


@pytest.mark.parametrize("dense_to", [0, 5000])
def test_block_search_equals_brute_force(spark, monkeypatch, dense_to):
    from ctxviews.operators import lists

    monkeypatch.setattr(lists, "DENSE", dense_to)
    monkeypatch.setattr(lists, "UNITS", 16)
    rng = np.random.default_rng(1)
    units_, queries = {}, {}
    for store, n in ((units_, 150), (queries, 12)):
        for i in range(n):
            fs = rng.choice(40, rng.integers(0, 6), replace=False)
            store[f"k{i:03d}"] = {f"f{f}": float(rng.integers(-3, 4)) for f in fs}
    u = spark.createDataFrame([(k, list(v), list(v.values())) for k, v in units_.items()], "unit_id string, f array<string>, w array<double>").repartition(3)
    q = spark.createDataFrame([(k, f, w) for k, v in queries.items() for f, w in v.items()], "query_id string, f string, w double")
    want = []
    for qk, qv in queries.items():
        found = sorted((-sum(w * uv[f] for f, w in qv.items() if f in uv), uk) for uk, uv in units_.items() if set(uv) & set(qv))
        want += [(qk, uk, -s + 0.0, i + 1) for i, (s, uk) in enumerate(found[:7])]
    got = [(r.query_id, r.unit_id, r.score + 0.0, r["rank"]) for r in lists.search(u, q, 7).collect()]
    assert sorted(got) == sorted(want)


def test_passages_by_rare_inner_token(spark):
    u = spark.createDataFrame([("a", "xone two three fourx"), ("b", "one, two  three four"), ("c", "two"), ("d", None), ("e", "")], "unit_id string, text string")
    p = spark.createDataFrame([("1", "one two three four"), ("2", "two  three"), ("3", "one two nowhere three"), ("4", "two"), ("5", None)], "query_id string, text string")
    assert rows(lexical.holding(p, u, lexical.index(u)), "query_id", "unit_id") == [("1", "a"), ("2", "b"), ("4", "a"), ("4", "b"), ("4", "c")]


def test_long_files_are_diffed_in_linear_space():
    rng = np.random.default_rng(0)
    a = [f"line {i}" if i % 3 else "same" for i in range(6000)]
    b = list(a)
    for i in sorted(rng.choice(6000, 60, replace=False), reverse=True):
        b[i : i + 1] = [] if i % 2 else ["new", "new"]
    h = versions.diff(a, b)
    assert versions.apply(h, a, b) == b and len(h) <= 120
    assert versions.apply(versions.diff(["x"] * 1500, ["y"] * 1500), ["x"] * 1500, ["y"] * 1500) == ["y"] * 1500


# --- maintenance -------------------------------------------------------------------------------------


def _files(spark, texts):
    return spark.createDataFrame([("r@1", "en", p, t.split("\n")) for p, t in texts.items()], "repo string, lang string, path string, lines array<string>")


def test_patches_read_only_what_changed(spark):
    """The patch's tokens come from changed files; the closure equals a rebuild, vertices and imports included."""
    old = {"a": "alpha uses gamma\nbeta calls alpha", "b": "delta calls beta\ngamma sees delta", "c": "omega alone"}
    new = {"a": "other line here\nalpha uses gamma\nbeta calls omega", "b": old["b"], "d": "alpha again beta"}
    t = maintain.Transition.of(_files(spark, old), _files(spark, new))
    assert {r.path for r in t.fresh.collect()} == {"a", "d"}
    want = maintain.facts(maintain.rebuild(_files(spark, new)))
    got = maintain.facts(maintain.repair(t, True))
    assert rows(got, "tag", "payload") == rows(want, "tag", "payload")
    assert {r.tag for r in want.collect()} == {"file", "symbol", "reference", "import"}


def test_invisible_symbols_stay_on_unedited_lines(spark):
    old = _files(spark, {"a": "alpha one\nbeta two\ngamma three"})
    new = _files(spark, {"a": "zero first\nalpha one\nbeta changed\ngamma three"})
    t = maintain.Transition.of(old, new)
    listed = spark.createDataFrame([("r@1", "en", "a", 0, "zero")], "repo string, lang string, path string, line int, symbol string")
    assert rows(maintain.vertices(t, listed), "line", "symbol") == [(0, "zero"), (1, "alpha"), (3, "gamma")]


def test_facts_of_one_symbol_mix_actions(spark):
    old = _files(spark, {"a": "alpha\nbeta\nuser alpha beta\nlast alpha"})
    new = _files(spark, {"a": "alpha\nuser alpha beta gamma\nlast alpha\ngamma"})
    t = maintain.Transition.of(old, new)
    got = maintain.fact_actions(t.old.refs, maintain.rebuild(new).refs, t)
    assert rows(got, "symbol", "action") == [("alpha", "added"), ("alpha", "changed"), ("alpha", "deleted"), ("beta", "deleted"), ("gamma", "added")]


def test_graph_maintainer_follows_a_stream_and_survives_a_repeat(spark, tmp_path):
    start = {"a": "alpha uses beta\nbeta calls alpha", "b": "gamma sees alpha"}
    m = feeds.GraphMaintainer(spark, str(tmp_path / "graph"))
    m.start(_files(spark, start))
    batches = [{"a": "alpha uses beta\nnew line\nbeta calls gamma"}, {"b": None, "c": "delta calls alpha beta"}]
    schema = "repo string, lang string, path string, lines array<string>"
    for i, b in enumerate(batches):
        edits = [("r@1", "en", p, x.split("\n") if x is not None else None) for p, x in b.items()]
        spark.createDataFrame(edits, schema).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        s = spark.readStream.schema(schema).parquet(str(tmp_path / "in"))
        feeds.maintain(s, m.apply, str(tmp_path / "ck")).awaitTermination()
        if i == 0:  # a crash after the patch and before its mark
            m.apply(spark.createDataFrame(edits, schema), 0)
    now = {"a": batches[0]["a"], "c": batches[1]["c"]}
    texts, g = m.read(2)
    assert {r.path for r in texts.collect()} == set(now)
    assert rows(maintain.facts(g), "tag", "payload") == rows(maintain.facts(maintain.rebuild(_files(spark, now))), "tag", "payload")
    with pytest.raises(ValueError):
        m.read(9)


def test_arms_against_the_rebuild(spark):
    """Replay after a reload agrees wherever the graph matches; the vector index replays its top ten exactly."""
    from ctxviews.queries import QUERIES

    m = {(r.repo, r.lang): r for r in upkeep.graph_match(spark, DATA).collect()}
    for r in QUERIES["q4_replay"](spark, DATA).collect():
        if r.arm == "closure" or m[r.repo, r.lang].symbol_match:
            assert r.agreement == 1
    v = QUERIES["q4_vector_match"](spark, DATA).collect()
    assert v and all(r.identities and r.vectors and r.ordered and r.sets for r in v)
    assert all((r["index"] == "rebuild") == (r.encoded > dense.REBUILD_SHARE) for r in v)


# --- navigation, delivery, costs --------------------------------------------------------------------


def test_enclosing_node_answers_where_there_is_no_occurrence(spark):
    occ = spark.createDataFrame([("r", "l", "p", 0, 0, "alpha", 1), ("r", "l", "p", 3, 0, "beta", 1), ("r", "l", "q", 0, 2, "alpha", 2)], "repo string, lang string, path string, line int, col int, symbol string, role int")
    reqs = spark.createDataFrame([("1", "r", "l", "definition", "p", 2, 5), ("2", "r", "l", "definition", "q", 0, 2), ("3", "r", "l", "definition", "q", 0, 7)], "req_id string, repo string, lang string, capability string, path string, line int, col int")
    got = {r.req_id: (r.locs, r.granularity, r.version) for r in navigate.static(reqs, occ, "v7").collect()}
    assert got == {"1": (["p:0"], "enclosing", "v7"), "2": (["p:0"], "occurrence", "v7"), "3": ([], "none", "v7")}


def test_answer_recall_takes_five_distinct_spans(spark):
    span = "array<struct<path: string, start: int, end: int>>"
    many = [("p", 1, 1)] * 4 + [("p", i, i) for i in range(2, 6)] + [("q", 0, 9)]
    t = spark.createDataFrame([("1", "a", "grep", 1, many), ("2", "a", "grep", 1, [("q", 0, 9)]), ("3", "a", "grep", 1, [])], f"query_id string, agent string, policy string, k int, spans {span}")
    want = spark.createDataFrame([("1", "p", 5, 8), ("1", "q", 4, 4), ("2", "q", 4, 4), ("3", "q", 4, 4)], "query_id string, path string, start int, end int")
    assert rows(delivery.answer_recall(t, want), "query_id", "recall") == [("1", 0.5), ("2", 1.0), ("3", 0.0)]


def test_turns_are_counted_by_invocation(spark):
    conv = [(1, 2 * i, "user", "x") for i in range(20)] + [(1, 2 * i + 1, "assistant", "y") for i in range(20)] + [(1, 100, "system", "late")]
    m = delivery.messages(spark.createDataFrame(conv, "conv_id long, turn long, role string, text string"))
    assert m.filter("role = 'completion'").count() == delivery.MAX_TURNS and m.agg(F.max("turn")).first()[0] == 31


def test_amortization_needs_a_saving(spark):
    c = spark.createDataFrame([("flat", 6.0, 0.9), ("ivf", 900.0, 0.2), ("hnsw", 2000.0, 1.0)], "family string, build_ms double, search_ms double")
    assert rows(costs.amortize(c), "family", "searches") == [("hnsw", None), ("ivf", 1278)]


def test_qualified_fastest(spark):
    c = spark.createDataFrame([("ivf", "0.1", 0.88, 0.1), ("ivf", "0.25", 0.96, 0.2), ("ivf", "0.5", 0.99, 0.4), ("hnsw", "16", 0.9, 0.1)], "family string, config string, overlap double, ms double")
    assert rows(metrics.qualified_fastest(c, 0.95), "family", "config") == [("ivf", "0.25")]


def test_index_cells_against_brute_force(spark):
    from ctxviews.plans import measure

    v = table(spark, DATA, "embeddings").filter("label < 3")
    got = measure.index_cells(v, "label", 3).collect()
    assert {r.family for r in got} == {"flat", "ivf", "hnsw"} and len({r["index"] for r in got}) == 3
    assert all(r.neighbor_recall == 1 for r in got if r.family == "flat" or r.config == "1.0")
    assert all(r.search_ms > 0 and r.build_ms >= 0 and r.bytes > 0 for r in got)


def test_compositions_and_budgets(spark):
    from ctxviews.queries import plans as plan_queries

    v, q = plan_queries.views(spark, DATA, edges=True), views.full_queries(spark, DATA).limit(4)
    p = plan_queries.pipelines(v, q)
    assert [n for n, _ in p["dense-expand-fuse-rerank"].steps] == ["dense", "expand and fuse", "rerank"]
    dense_top = rows(p["dense"](q), "query_id", "vid", "rank")
    assert len(dense_top) == 40
    lst = plan.dense_list(v, q, 50)
    cut = plan.equal_budget({"a": lst, "b": lst}, 7)
    assert {r["count"] for r in cut.groupBy("arm", "query_id").count().collect()} == {7}


def test_builders_fail_without_their_preparation(spark, tmp_path):
    u = spark.createDataFrame([("u", "text")], "unit_id string, text string")
    b = {"lexical": catalog.builder("lexical", u, lambda x: x), "structural": catalog.builder("structural", u, lambda x: x), "dense": catalog.builder("dense", None, lambda x: x)}
    got = {e.view: e for e in catalog.materialize(str(tmp_path), "v", b)}
    assert got["lexical"].status == "ok" and got["structural"].status == got["dense"].status == "failed"
    assert "BuildPreparationMissing" in got["structural"].error and "unit_id" in got["dense"].error


def test_nine_tools_return_one_shape(spark):
    from ctxviews.plans.corpus import Corpus

    c = Corpus(spark, DATA)
    v, o = c.views(edges=True), c.occurrences()
    box = tools.Toolbox(v, o, entries=[catalog.Entry("lexical", "ok")])
    s = o.filter("role = 1").orderBy("path", "line").first()
    e = v.edges.filter("etype = 'reference' and src <> dst").orderBy("src", "dst").first()
    some = v.units.orderBy("unit_id").first().text
    asked = {"bm25_search": some, "semantic_search": some, "regex_search": "[a-z]+", "trigram_search": some[:20], "definition": s.symbol, "references": s.symbol, "dependencies": e.src, "route": e.src, "catalog": ""}
    assert set(asked) == set(tools.NEEDS)
    for name, text in asked.items():
        got = box.call(name, text, 3, to=e.dst)
        assert got.columns == ["path", "start", "snippet", "score"] and got.count() >= 1, name
    assert tools.Toolbox(v, o, compact=True).call("definition", s.symbol).filter("snippet is not null").count() == 0
    with pytest.raises(catalog.ViewUnavailable):
        tools.Toolbox(v, o, frozenset({"text_search"})).call("route", e.src, to=e.dst)


def test_units_are_counted_and_weighed_in_their_rows(spark):
    """No token is shuffled: plans have no exchange; rare terms that are not sent to every task get their weights by join."""
    from ctxviews.functions.text import tokens
    from ctxviews.operators import dense, lexical, lists, rows

    texts = ["a b a", "", "b c d", "d e é f", "a a a z", "...", "c y y x"] * 3 + ["once", "q q r"]
    u = spark.createDataFrame([(str(i), t) for i, t in enumerate(texts)], "unit_id string, text string").repartition(3)
    plans = [lexical.postings(u), rows.count(u, tokens(F.col("text")))]
    for e in (dense.ENCODERS[0], dense.Encoder("two", 4, "bigram"), dense.Encoder("char", 16, "char")):
        idf = dense.document_frequency(u, e)
        want = {(r.unit_id, r.bucket): r.w for r in dense.encode(u, e, idf).collect()}
        for most in (None, 3, 0):
            v = rows.weigh(rows.count(u, dense.features(F.col("text"), e)), idf, e.dim, most=most)
            got = {(r.unit_id, f): w for r in v.collect() for f, w in zip(r.f, r.w, strict=True)}
            assert got.keys() == want.keys() and all(abs(got[x] - want[x]) < 1e-12 for x in want)
        plans.append(dense.vectors(u, e, idf))
    for p in plans:
        assert p._jdf.queryExecution().executedPlan().toString().count("Exchange ") <= 1  # repartition(3)
    counts = rows.count(u, tokens(F.col("text")))
    gone = u.filter("unit_id % 2 = 0")
    come = gone.withColumn("text", F.lit("alpha a a"))
    a = lexical.delta(counts, gone, come)
    b = lexical.delta(lexical.postings(u), gone, come).select("term", "unit_id", "tf")
    assert sorted(a.collect()) == sorted(b.collect())
    assert lists.Best(2, 1).all()[0].tolist() == []


def test_search_keeps_the_best_of_a_task_over_its_batches(spark, monkeypatch):
    """One task sends k rows a query, however many batches it reads."""
    import random

    from ctxviews.operators import lists

    r = random.Random(5)
    u = {f"u{i:05}": {r.randrange(6): r.choice([-1.0, 1.0, 2.0]) for _ in range(2)} for i in range(9000)}
    q = {f"q{i}": {r.randrange(7): r.choice([-1.0, 1.0]) for _ in range(2)} for i in range(5)}
    v = spark.createDataFrame([(k, sorted(x), [x[f] for f in sorted(x)]) for k, x in u.items()], "unit_id string, f array<bigint>, w array<double>").coalesce(1)
    asked = spark.createDataFrame([(k, f, w) for k, x in q.items() for f, w in x.items()], "query_id string, f bigint, w double")
    found = lists.search(v, asked, 4)
    want = []
    for name, x in q.items():
        s = sorted((-sum(w * y[f] for f, w in x.items() if f in y), k) for k, y in u.items() if x.keys() & y.keys())[:4]
        want += [(name, k, -t, i + 1) for i, (t, k) in enumerate(s)]
    assert sorted(map(tuple, found.collect())) == sorted(want)
    monkeypatch.setattr(lists, "HELD", 0)
    assert sorted(map(tuple, lists.search(v, asked, 4).collect())) == sorted(want)
    b = lists.Best(1, 2)
    import numpy as np
    import pyarrow as pa

    for i in range(9000):
        b.add(np.array([0, 0]), pa.array([f"a{i}", f"b{i}"]), np.array([0, 1]), np.array([i / 7, i / 9]))
    assert [b.all()[1].tolist(), sum(len(x[0]) for x in b.new)] == [["a8999", "a8998"], 2]


def test_route_takes_open_pairs_only(spark):
    """Distances by brute force; the surroundings of a start are not made for pairs that are found earlier."""
    import random

    r = random.Random(3)
    edges = {(f"n{r.randrange(14)}", f"n{r.randrange(14)}") for _ in range(22)}
    e = spark.createDataFrame([(a, b, r.choice(["reference", "import"])) for a, b in edges] + [("n1", "n2", "other")], "src string, dst string, etype string")
    nodes = [f"n{i}" for i in range(15)]
    want = {}
    for a in nodes:
        front, at = {a}, {a: 0}
        for h in range(1, 5):
            front = {y for x, y in edges if x in front} - at.keys()
            at |= dict.fromkeys(front, h)
        want |= {(a, b): at.get(b) for b in nodes}
    pairs = spark.createDataFrame(list(want), "a string, b string")
    made = []

    def keep(df):
        made.append(df.cache())
        return made[-1]

    for most in (0, 1, 2, 3, 4):
        got = {(x.a, x.b): x.hops for x in structure.route(pairs, e, most, keep).collect()}
        assert got == {p: h if h is not None and h <= most else None for p, h in want.items()}
    made.clear()
    one = spark.createDataFrame([("n0", next(b for a, b in edges if a == "n0"))], "a string, b string") if any(a == "n0" for a, _ in edges) else pairs.limit(1)
    assert structure.route(one, e, 3, keep).first().hops is not None
    assert max(x.count() for x in made[1:]) <= 1


def test_ledger_of_many_sessions_goes_on(spark, tmp_path):
    rows = [(s, i, e) for s in ("a", "b") for i, e in enumerate("xyz")]
    df = spark.createDataFrame(rows, "session string, t int, event string").selectExpr("*", "string(null) view", "string(null) provider", "1L prompt_tokens", "0L completion_tokens")
    path = f"{tmp_path}/ledger"
    trace.extend(df.filter("t < 1 or session = 'b'"), path, "t")
    trace.extend(df.filter("t >= 1 and session = 'a'"), path, "t")
    got = sorted((x.session, x.seq, x.event) for x in spark.read.parquet(path).collect())
    assert got == [(s, i, e) for s, i, e in rows]


@pytest.mark.parametrize("name", ["c_trace", "p_legality", "q3_latency_summary", "u_backends", "u_tools"])
def test_contracts_read_a_given_table(spark, name):
    from ctxviews import registry

    assert any("/root/testdata/sf0.001/" in f for f in registry.QUERIES[name](spark, "/root/testdata/sf0.001").inputFiles()) or name == "c_trace"


def test_edges_of_lines_are_those_of_the_whole_graph(spark):
    """Edges derived for some lines equal the stored graph's at these lines, with how often each is there; route D stores no graph."""
    from ctxviews.plans import store
    from ctxviews.plans.corpus import Corpus
    from ctxviews.queries import plans as plan_queries

    u = Corpus(spark, DATA).units()
    some = u.filter(F.pmod(F.xxhash64("unit_id"), F.lit(7)) == 0).select("path", "start")
    ends = some.select(F.concat("path", F.lit("#"), F.col("start").cast("string")).alias("v")).collect()
    ends = {r.v for r in ends}
    cols = ["repo", "lang", "src", "dst", "anchor_file", "anchor_line", "anchor_col"]
    touch = lambda df: [r for r in rows(df.filter("etype = 'reference' and src <> dst"), *cols) if {r[2], r[3]} & ends]
    want = touch(structure.edges(structure.occurrences(u)))
    assert len(want) > 50
    assert touch(structure.incident(u, some)) == want
    assert touch(plan.edges_of_lines(u, some)) == want
    store._known.clear()
    del store.LEDGER[:]
    assert plan_queries.plan.graph_seeded(plan_queries.views(spark, DATA, None), views.full_queries(spark, DATA), 10, 10).count() > 0
    assert not {x["view"] for x in store.LEDGER} & {"occurrences", "references", "edges"}


def test_texts_stay_where_they_lie(spark):
    """Passages are found, and ranked units get their paths, without a shuffle of terms or texts."""
    from ctxviews.plans import store
    from ctxviews.plans.corpus import Corpus

    c = Corpus(spark, DATA)
    found = lexical.holding(views.full_queries(spark, DATA), c.units(), c.lexical(), store.few)
    assert rows(found, "query_id", "unit_id") == rows(lexical.holding(views.full_queries(spark, DATA), c.units(), c.lexical()), "query_id", "unit_id")
    plain = found._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" not in plain and "hashpartitioning" not in plain


def test_encoders_share_one_pass(spark, monkeypatch):
    """Lists of several encoders come from one reading of the units and equal each encoder's own; blocks do not mix encoders."""
    from ctxviews.operators import lists
    from ctxviews.plans.corpus import Corpus
    from ctxviews.queries import plans as plan_queries

    c, q = Corpus(spark, DATA), views.thin_queries(spark, DATA).limit(9)
    for level, block in ((2, 1024), (0, 4)):
        monkeypatch.setattr(lists, "BLOCK", block)
        together = plan.dense_lists(c.views(level=level), q, dense.ENCODERS, 20)
        assert together._jdf.queryExecution().executedPlan().toString().count("MapInArrow") <= 2
        for e in dense.ENCODERS:
            own = plan.dense_list(c.views(e, level=level), q, 20)
            assert rows(together.filter(F.col("encoder") == e.name), "query_id", "unit_id", "score", "rank") == rows(own, "query_id", "unit_id", "score", "rank")
    none = spark.createDataFrame([], "query_id string, path string")
    ranked = spark.createDataFrame([("hash64", "q", "p", 1)], "encoder string, query_id string, path string, rank int")
    got = {r.encoder: (r.n, r.recall) for r in plan_queries.recall_by_encoder(ranked, none, dense.ENCODERS).collect()}
    assert got == {e.name: (0, None) for e in dense.ENCODERS}


def test_occurrences_shuffle_no_token(spark):
    from ctxviews.plans import store
    from ctxviews.plans.corpus import Corpus

    u = Corpus(spark, DATA).units()
    cols = ["repo", "lang", "path", "line", "col", "symbol", "role"]
    got = structure.occurrences(u, store.few)
    plain = got._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning" not in plain and "SortMergeJoin" not in plain
    assert rows(got, *cols) == rows(structure.occurrences(u), *cols)


def test_requests_of_a_snapshot_need_its_occurrences_only(spark):
    from ctxviews.plans.corpus import Corpus

    o = Corpus(spark, DATA).occurrences()
    r = navigate.requests(o)
    one = r.select("repo", "lang").distinct().orderBy("repo", "lang").limit(1)
    by = ["repo", "lang"]
    two = r.join(one, by, "left_semi").filter("capability = 'definition'").orderBy("req_id").limit(2)
    assert rows(navigate.requests(o.join(one, by, "left_semi")), "req_id", "symbol") == rows(r.join(one, by, "left_semi"), "req_id", "symbol")
    few = o.join(two.select(*by, "symbol").distinct(), [*by, "symbol"], "left_semi")
    assert rows(navigate.static(two, few), "req_id", "locs") == rows(navigate.static(two, o), "req_id", "locs")


def test_whole_files_are_not_stored_again(spark):
    """Level-0 units are read from the base table; passages are found in them as in a stored copy."""
    from ctxviews.plans import store
    from ctxviews.plans.corpus import Corpus

    c = Corpus(spark, DATA)
    assert all("documents.parquet" in x for x in c.units(0).inputFiles())
    copy = store.kept(units.with_ids(units.level0(files(spark, DATA)), 0))
    assert rows(c.units(0), "unit_id", "path", "end") == rows(copy, "unit_id", "path", "end")
    found = lexical.holding(views.full_queries(spark, DATA), c.units(0), c.lexical(0), store.few)
    assert found.count() > 0 and rows(found, "query_id", "unit_id") == rows(lexical.holding(views.full_queries(spark, DATA), copy, lexical.index(copy)), "query_id", "unit_id")


def test_timed_builds_leave_nothing_behind(spark):
    from ctxviews.plans import measure, store

    folders = lambda: {p.name for p in Path(store.shared_dir(spark).removeprefix("file:")).glob("ctxviews-kept-*")}
    before, listed = folders(), list(store._written)
    made = measure.build_costs(spark, DATA, dense.ENCODERS[:2], (1.0,))
    assert [(e, level) for e, level, *_ in made] == [("hash64", 0), ("hash128", 0), ("hash64", 2), ("hash128", 2)]
    assert all(size > 0 and took > 0 for *_, took, size in made)
    assert folders() == before and store._written == listed


def test_routes_without_texts_store_no_units(spark, tmp_path):
    import shutil

    from ctxviews.plans import store
    from ctxviews.registry import QUERIES

    d = f"{tmp_path}/own"
    shutil.copytree("/root/testdata/sf0.001", d)
    before = len(store.LEDGER)
    rows = sorted(map(tuple, QUERIES["p_route_c"](spark, d).collect()))
    assert {x["view"] for x in store.LEDGER[before:]} == {"lexical-2-counts", "lexical-2-stats", "lexical-2-terms"}
    QUERIES["p_compose"](spark, d).count()  # has the stored units
    assert "units-2" in {x["view"] for x in store.LEDGER[before:]}
    assert rows == sorted(map(tuple, QUERIES["p_route_c"](spark, "/root/testdata/sf0.001").collect()))


def test_imports_are_those_of_all_edges(spark):
    f = files(spark, DATA)
    want = structure.edges(structure.occurrences(units.level2(f))).filter("etype = 'import'").select("repo", "lang", "src", "dst").distinct()
    s = structure.imports(f)
    got = s.nexts.select("repo", "lang", F.col("node").alias("src"), F.explode("nexts").alias("code")).join(s.names.withColumnRenamed("node", "dst"), ["repo", "lang", "code"])
    assert rows(got, "repo", "lang", "src", "dst") == rows(want, "repo", "lang", "src", "dst")


def test_dependencies_store_import_steps_only(spark, tmp_path, monkeypatch):
    from ctxviews import registry
    from ctxviews.plans import store

    monkeypatch.setattr(store, "_known", {})
    before = len(store.LEDGER)
    assert registry.QUERIES["g_dependencies"](spark, DATA).count() > 0
    assert {x["view"] for x in store.LEDGER[before:]}.isdisjoint({"units-2", "occurrences", "references", "edges"})


def test_steps_by_blocks_and_columns_give_the_same_nodes(spark, monkeypatch):
    """A graph with a ring, a hub and a dead end, in two snapshots, by the frontier joins and by bit rows of 64 columns."""
    from ctxviews.operators import closure
    from ctxviews.plans.store import kept

    pairs = [(f"n{i}", f"n{(i * 7 + 3) % 200}") for i in range(200)] + [(f"n{i}", "hub") for i in range(0, 200, 3)] + [("hub", f"n{i}") for i in range(90)] + [("n5", "end")]
    e = spark.createDataFrame([(r, "en", r + a, r + b, "import") for r in ("x", "y") for a, b in pairs if a != b], "repo string, lang string, src string, dst string, etype string")
    asked, s = e.select("repo", "lang", F.col("src").alias("seed")).distinct(), closure.steps_of(e, kept)
    monkeypatch.setattr(closure, "STARTS", 64)
    for bits in (closure.BITS, 64):  # 64: a range of columns at a time
        monkeypatch.setattr(closure, "BITS", bits)
        for depth in (1, 3):
            want = structure.neighbours(asked.select("seed"), e, depth, ("import",), "out")
            assert rows(structure.dependencies(asked, s, depth), "seed", "node", "hop") == rows(want, "seed", "node", "hop")


def test_import_routes_are_routes(spark, monkeypatch):
    """Pairs that two steps join, on a small graph: there and back, direct ones, and those at two steps; three steps' pairs need up to three."""
    from ctxviews import registry
    from ctxviews.operators import closure
    from ctxviews.plans import store

    e = spark.createDataFrame([("r", "en", a, b, "import") for a, b in ["ab", "ba", "bc", "ac", "cd", "de", "ea"]], "repo string, lang string, src string, dst string, etype string")
    s = closure.steps_of(e, store.kept)
    one = e.select(F.col("src").alias("a"), F.col("dst").alias("b"))
    pairs = one
    for steps in (2, 3):
        pairs = pairs.withColumnRenamed("b", "m").join(one.withColumnRenamed("a", "m"), "m").select("a", "b").distinct()
        for most in (1, 3):
            assert sorted(map(repr, structure.import_routes(s, steps, most).collect())) == sorted(map(repr, structure.route(pairs, e, most).select("a", "b", "hops").collect()))
    assert not structure.has_lines(s)
    assert structure.has_lines(closure.steps_of(e.withColumn("dst", F.concat("dst", F.lit("#1")))))
    monkeypatch.setattr(store, "_known", {})
    before = len(store.LEDGER)
    assert registry.QUERIES["g_route"](spark, DATA).count() > 0
    assert {x["view"] for x in store.LEDGER[before:]}.isdisjoint({"units-2", "occurrences", "references", "edges"})


def test_pairs_above_a_score_are_those_of_the_whole_product():
    """Scores at the bound, just below it and far from it; large weights, too."""
    from ctxviews.operators import lists

    r = np.random.default_rng(3)
    for scale in (1.0, 1e5, 1e30):
        rows_ = [(i, f, float(w) * scale) for i in range(40) for f, w in zip(r.choice(64, 12, False).tolist(), r.normal(size=12), strict=True)]
        block = lists.Block([f"q{i}" for i in range(40)], rows_)
        u = np.repeat(np.arange(500), 10)
        t = np.concatenate([r.choice(len(block.names), 10, False) for _ in range(500)])
        v = r.normal(size=5000)
        s = lists.six(block.score(t, u, v, 500))
        least = np.sort(s, axis=1)[:, -5]
        q, x, got = block.above(t, u, v, 500, least - 1e-9 * scale)
        assert list(zip(q, x, strict=True)) == list(zip(*np.nonzero(s >= (least - 1e-9 * scale)[:, None]), strict=True))
        assert np.allclose(got, s[q, x], rtol=1e-12, atol=1.1e-6)
        assert block.short.dtype == np.float32 and block.short.shape == block.matrix.shape
