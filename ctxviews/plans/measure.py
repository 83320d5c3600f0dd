"""Measured costs: builds, index cells, request latencies, maintenance arms, lifecycle.

Seconds differ from run to run, so nothing here has a fixed expected value; the
definitions (medians, conditions, quantiles, projections) are those of the operators
that take these rows.  Small serving handles are timed inside one task, where no
scheduler stands between two calls; builds and patches are timed as Spark jobs.
"""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxviews.functions.ship import ship
from ctxviews.operators import dense, lists, maintain, metrics, navigate, units, versions
from ctxviews.plans import store
from ctxviews.plans.corpus import Corpus
from ctxviews.sources.tables import files

WARM, REPEATS = 10, 100
EMPTY = ["object", "object", "object", "int32", "float64", "float64", "float64", "int64", "bool"]
FRACTIONS, EFS = dense.PROBES, (16, 32, 64, 128)
CELL = "index string, family string, config string, vectors int, neighbor_recall double, build_ms double, search_ms double, bytes long"


def _timed(f, times: int, warm: int) -> float:
    """Median milliseconds of f(i) after warm-up calls."""
    took = []
    for i in range(warm + times):
        began = time.perf_counter()
        f(i)
        if i >= warm:
            took.append((time.perf_counter() - began) * 1000)
    return float(np.median(took))


def _top(s: np.ndarray, ids: np.ndarray, k: int) -> list[int]:
    n = min(k, len(s))
    near = np.argpartition(-s, n - 1)[:n]
    return ids[near[np.lexsort((ids[near], -s[near]))]].tolist()


def cell_rows(name: str, ids: np.ndarray, x: np.ndarray, k: int = 10, repeats: int = REPEATS, warm: int = WARM, queries: np.ndarray | None = None, judge=None) -> list[tuple]:
    """One row for each configuration of Flat, IVF and HNSW over one index.

    queries: by default the index's own vectors whose id ends in 0.  judge: what a row says besides,
    from the lists that the configuration found.
    """
    own = np.flatnonzero(ids % 10 == 0) if queries is None else None
    q = x[own] if own is not None else queries
    out: list[tuple] = []
    if not len(x) or not len(q):
        return out

    def left_out(s, i):
        if own is not None:
            s[own[i]] = -np.inf
        return s

    began = time.perf_counter()
    flat_x = np.ascontiguousarray(x)
    flat_ms = (time.perf_counter() - began) * 1000
    flat = lambda i: _top(left_out(flat_x @ q[i % len(q)], i % len(q)), ids, k)
    truth = [set(flat(i)) for i in range(len(q))]
    more = lambda got: () if judge is None else (judge(got),)
    share = lambda got: float(np.mean([len(set(g) & t) / max(1, len(t)) for g, t in zip(got, truth, strict=True)]))
    out.append((name, "flat", "-", len(x), 1.0, flat_ms, _timed(flat, repeats, warm), x.nbytes, *more([flat(i) for i in range(len(q))])))

    began = time.perf_counter()
    m = max(1, round(len(x) ** 0.5))
    c = x[np.random.default_rng(0).permutation(len(x))[:m]].copy()
    for _ in range(10):
        at = (x @ c.T).argmax(1)
        for j in range(m):
            if (at == j).any():
                v = x[at == j].sum(0)
                c[j] = v / max(1e-12, float(np.linalg.norm(v)))
    at = (x @ c.T).argmax(1)
    members = [np.flatnonzero(at == j) for j in range(m)]
    stored = [np.ascontiguousarray(x[w]) for w in members]
    ivf_ms = (time.perf_counter() - began) * 1000

    def probe(i, width):
        i %= len(q)
        near = np.argsort(-(c @ q[i]), kind="stable")[:width]
        rows = np.concatenate([members[j] for j in near])
        s = np.concatenate([stored[j] @ q[i] for j in near])
        if own is not None:
            s[rows == own[i]] = -np.inf
        return _top(s, ids[rows], k) if len(s) else []

    for f in FRACTIONS:
        width = max(1, int(np.ceil(f * m)))
        got = [probe(i, width) for i in range(len(q))]
        out.append((name, "ivf", str(f), len(x), share(got), ivf_ms, _timed(lambda i, w=width: probe(i, w), repeats, warm), x.nbytes + c.nbytes + 8 * len(x), *more(got)))

    began = time.perf_counter()
    g = dense.Layered(ids, x)
    hnsw_ms = (time.perf_counter() - began) * 1000
    links = sum(len(layer) for node in g.links for layer in node)
    walk = lambda i, ef: [v for v, _ in g.search(q[i % len(q)], k + 1, ef) if own is None or v != ids[own[i % len(q)]]][:k]
    for ef in EFS:
        got = [walk(i, ef) for i in range(len(q))]
        out.append((name, "hnsw", str(ef), len(x), share(got), hnsw_ms, _timed(lambda i, e=ef: walk(i, e), repeats, warm), x.nbytes + 8 * links, *more(got)))
    return out


def index_cells(vectors: DataFrame, group: str, repeats: int = REPEATS) -> DataFrame:
    """CELL rows of one index for each value of `group` (vec_id, embedding); an index fits one task, as it is served."""

    ship(vectors.sparkSession)

    def run(pdf):
        import pandas as pd

        x = np.stack(pdf["embedding"]).astype(np.float64)
        return pd.DataFrame(cell_rows(str(pdf[group].iloc[0]), pdf["vec_id"].to_numpy(), x, 10, repeats), columns=[c.split()[0] for c in CELL.split(", ")])

    return vectors.select(group, "vec_id", "embedding").groupBy(group).applyInPandas(run, CELL)


def family_means(cells: DataFrame) -> DataFrame:
    """family, config, overlap, ms, build_ms, bytes: means over indexes."""
    return cells.groupBy("family", "config").agg(F.round(F.avg("neighbor_recall"), 6).alias("overlap"), F.avg("search_ms").alias("ms"), F.avg("build_ms").alias("build_ms"), F.avg("bytes").alias("bytes"))


def line_cells(spark: SparkSession, sf_dir: str, targets: DataFrame, queries: DataFrame, dim: int = 256) -> DataFrame:
    """The second vector set: each snapshot's lines under a hashed encoder, searched for the queries that have a
    target there.  CELL rows with `kept`: whether the target files among the first ten lines are Flat's, for each cell."""
    ship(spark)
    e = next(x for x in dense.ENCODERS if x.dim == dim)
    c = Corpus(spark, sf_dir)
    u = c.units().select("unit_id", "repo", "lang", "path")
    v = c.vectors(e).join(u, "unit_id").select(F.concat_ws("/", "repo", "lang").alias("index"), "path", "f", "w")
    qv = lists.grouped(dense.encode(queries.withColumnRenamed("query_id", "unit_id"), e, c.idf(e))).withColumnRenamed("unit_id", "query_id")
    need = targets.groupBy("query_id", F.concat_ws("/", "repo", "lang").alias("index")).agg(F.collect_set("path").alias("targets"))
    asked = qv.join(need, "query_id").select("index", "query_id", "f", "w", "targets")

    def matrix(pdf):
        x = np.zeros((len(pdf), dim))
        for i, (f, w) in enumerate(zip(pdf["f"], pdf["w"], strict=True)):
            x[i, np.asarray(f, np.int64)] = w
        return x

    def run(key, left, right):
        import pandas as pd

        columns = [*(c.split()[0] for c in CELL.split(", ")), "kept"]
        if not len(left) or not len(right):
            return pd.DataFrame({c: pd.Series([], dtype=t) for c, t in zip(columns, EMPTY, strict=True)})
        left = left.sort_values("path", kind="stable")
        x, q, ids = matrix(left), matrix(right), np.arange(len(left), dtype=np.int64)
        paths = left["path"].to_numpy()
        want = [set(t) for t in right["targets"]]
        found = lambda got: [len({paths[i] for i in g} & w) for g, w in zip(got, want, strict=True)]
        flat = found([_top(x @ y, ids, 10) for y in q])
        return pd.DataFrame(cell_rows(key[0], ids, x, 10, 5, 1, q, lambda got: found(got) == flat), columns=columns)

    return v.groupBy("index").cogroup(asked.groupBy("index")).applyInPandas(run, CELL + ", kept boolean")


def query_latency(spark: SparkSession, sf_dir: str, queries: DataFrame, encoders=tuple(dense.ENCODERS), repeats: int = 5) -> DataFrame:
    """encoder, index, query, millis: exact search of one query at a time on each snapshot's resident vectors, for each encoder."""
    ship(spark)
    c, out = Corpus(spark, sf_dir), None
    u = c.units().select("unit_id", "repo", "lang")
    for e in encoders:
        qv = lists.grouped(dense.encode(queries.withColumnRenamed("query_id", "unit_id"), e, c.idf(e))).withColumnRenamed("unit_id", "query_id")
        shared = spark.sparkContext.broadcast([(r.query_id, list(r.f), list(r.w)) for r in qv.collect()])  # a batch of queries

        def timed(pdf, e=e, shared=shared):
            import pandas as pd

            x = np.zeros((len(pdf), e.dim))
            for i, (f, w) in enumerate(zip(pdf["f"], pdf["w"], strict=True)):
                x[i, np.asarray(f, np.int64)] = w
            ids, rows = np.arange(len(x)), []
            for name, f, w in shared.value:
                q = np.zeros(e.dim)
                q[np.asarray(f, np.int64)] = w
                rows.append((e.name, pdf["index"].iloc[0], name, _timed(lambda i, q=q: _top(x @ q, ids, 10), repeats, 2)))
            return pd.DataFrame(rows, columns=["encoder", "index", "query", "millis"])

        by = c.vectors(e).join(u, "unit_id").select(F.concat_ws("/", "repo", "lang").alias("index"), "f", "w").groupBy("index")
        part = by.applyInPandas(_plain(timed), "encoder string, index string, query string, millis double")
        out = part if out is None else out.unionByName(part)
    return out


def _plain(f):
    """f with one parameter, as grouped functions are told apart by their number of parameters."""
    return lambda pdf: f(pdf)


def navigation_timings(reqs: DataFrame, occ: DataFrame, l2: DataFrame, repeats: int = 10) -> DataFrame:
    """req_id, provider, repetition, millis: each request answered from a resident index of its snapshot and by
    cutting the snapshot's current text into tokens at request time, in one task for each snapshot."""
    texts = l2.select("repo", "lang", F.struct("path", F.col("start").alias("line"), "text").alias("t")).groupBy("repo", "lang").agg(F.collect_list("t").alias("ts"))
    index = occ.select("repo", "lang", F.struct("path", "line", "col", "symbol", "role").alias("o")).groupBy("repo", "lang").agg(F.collect_list("o").alias("os"))
    asked = reqs.select("repo", "lang", F.struct("req_id", "capability", "path", "line", "col", "symbol").alias("r")).groupBy("repo", "lang").agg(F.collect_list("r").alias("rs"))
    rows = asked.join(index, ["repo", "lang"]).join(texts, ["repo", "lang"])

    def run(batches):
        import re

        import pandas as pd

        word = re.compile(r"[^\W_]+")
        for pdf in batches:
            for own, os_, ts in zip(pdf["rs"], pdf["os"], pdf["ts"], strict=True):
                by: dict[str, list] = {}
                for o in os_:
                    by.setdefault(o["symbol"], []).append((o["path"], o["line"], o["role"]))
                for places in by.values():
                    places.sort()

                def static(r, by=by):
                    found = by.get(r["symbol"], ())
                    if r["capability"] == "definition":
                        found = sorted((p for p in found if p[2] == 1), key=lambda p: (p[0] != r["path"] or p[1] > r["line"], -p[1] if p[0] == r["path"] else 0, p))[:8]
                    return sorted({p[:2] for p in found[:40]})

                def live(r, ts=ts):
                    found = []
                    for t in ts:
                        for at, w in enumerate(word.findall(t["text"])):
                            if w.lower() == r["symbol"] and (r["capability"] == "references" or at == 0):
                                found.append((t["path"], t["line"]))
                    return sorted(set(found))[: 8 if r["capability"] == "definition" else 40]

                out = []
                for r in own:
                    for name, f in (("static", static), ("live", live)):
                        for n in range(repeats):
                            began = time.perf_counter()
                            f(r)
                            out.append((r["req_id"], name, n, (time.perf_counter() - began) * 1000))
                yield pd.DataFrame(out, columns=["req_id", "provider", "repetition", "millis"])

    return rows.mapInPandas(run, "req_id string, provider string, repetition int, millis double")


def build_costs(spark: SparkSession, sf_dir: str, encoders=tuple(dense.ENCODERS[::2]), parts: tuple[float, ...] = (0.25, 0.5, 1.0)) -> list[tuple]:
    """(encoder, level, kloc, seconds, bytes) of fresh dense builds over growing sets of snapshots, by level.

    A build that has been timed and weighed is dropped, so only one is on disk at a time.
    """
    f = files(spark, sf_dir)
    place = F.pmod(F.xxhash64("repo", "lang"), F.lit(1000)) / 1000.0
    out = []
    for part in parts:
        own = store.kept(f.filter(place < part))
        kloc = (own.agg(F.sum(F.size(F.split("text", "\n")))).first()[0] or 0) / 1000
        for level, cut in ((0, units.level0), (2, units.level2)):
            for e in encoders:
                began = time.perf_counter()
                u = units.with_ids(cut(own), level)
                idf = store.kept(dense.document_frequency(u, e))
                made = store.kept(dense.vectors(u, e, idf))
                took = time.perf_counter() - began
                out.append((e.name, level, float(kloc), took, store.size_of(spark, store.path_of(made))))
                store.drop(made, idf)
        store.drop(own)
    return out


def maintenance_arms(spark: SparkSession, old: DataFrame, new: DataFrame) -> list[tuple]:
    """(arm, seconds) of writing the target's graph by rebuild and by each patch, from the same stored old graph."""
    graph = maintain.rebuild(old, store.kept)
    graph.imports = store.kept(graph.imports)

    def written(g: maintain.Graph) -> None:
        for df in (g.decl, g.refs, g.imports):
            df.write.format("noop").mode("overwrite").save()

    arms = {"rebuild": lambda: written(maintain.rebuild(new, store.kept))}
    for name, arm in maintain.ARMS.items():
        arms[name] = lambda arm=arm: written(arm(maintain.Transition.of(old, new, graph, store.kept), store.kept))
    out = []
    for name, f in arms.items():
        began = time.perf_counter()
        f()
        out.append((name, time.perf_counter() - began))
    return out


def lifecycle(spark: SparkSession, sf_dir: str, ranked: DataFrame, definitions: DataFrame) -> dict:
    """b, l, s, n: seconds to build the views (as recorded), to open them, and to serve a session's requests."""
    c = Corpus(spark, sf_dir)
    v = c.views()
    built = sum(x["seconds"] for x in store.LEDGER if x["view"].startswith(("units-2", "lexical-2", "idf-token-2", "vectors-hash256", "occurrences")))
    began = time.perf_counter()
    for df in (v.units, v.vectors, v.lexical.terms, c.occurrences()):
        spark.read.parquet(*df.inputFiles()).schema  # noqa: B018
    opened = time.perf_counter() - began
    from ctxviews.plans import plan

    began = time.perf_counter()
    n = plan.lexical_list(v, ranked, 10).count() + plan.dense_list(v, ranked, 10).count()
    asked = store.few(definitions.select("repo", "lang", "symbol").distinct())
    n_def = navigate.static(definitions, c.occurrences().join(asked, ["repo", "lang", "symbol"], "left_semi")).count()
    served = time.perf_counter() - began
    return {"b": built, "l": opened, "s": served, "ranked_rows": n, "definitions": n_def}


def small_commits(spark: SparkSession, sf_dir: str, every: int = 50) -> tuple[DataFrame, DataFrame]:
    """(old, new) files of every repository after one commit that edits about one file in `every`."""
    v = store.stored(spark, sf_dir, f"commit-{every}", lambda: versions.evolve(files(spark, sf_dir), 1, every, whole=True))
    return v.filter("step = 0").drop("step"), v.filter("step = 1").drop("step")


def conditional(timings: DataFrame, matched: DataFrame) -> DataFrame:
    """Latency of requests on which both providers agree."""
    return metrics.conditional_latency(timings.join(matched, "req_id", "left_semi"))
