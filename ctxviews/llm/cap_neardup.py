"""Embedding near-duplicates with spherical-cap filters.

Filters are the directions of structured random product codes: after a random
rotation a vector is cut into BLOCKS blocks, each block has WORDS random code
words, and every combination of code words is a filter.  List decoding finds all
filters whose inner product with a vector exceeds a threshold (and the LEAST best
ones if fewer do, for vectors that lie far from all code words) without trying all
combinations.  The number of code words grows with the number of vectors, so that a
filter holds GROUP random vectors on average.  Vectors that share a filter are
compared; a pair is counted only at the least filter it shares, so each is
verified once.  TABLES independent codes raise recall.

Equal vectors form a class that is compared once.  A filter with more than BLOCK
classes is worked on in pairs of blocks.  Groups return link counts and a
spanning forest of their links, never all pairs.

Vectors that are null, empty, zero or hold null or non-finite components link
with nothing; vectors of different lengths never link.  Repeated rows are vectors of
their own.  A row without an id has its class's component and is not kept.

Of random pairs in 64 dimensions 0.99 and more are found at every cosine from 0.95 up
(16 code words, tests/llm/test_cap_bands.py).
"""

from __future__ import annotations

from functools import lru_cache
from statistics import NormalDist

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import components, keep, release, ship, small

BLOCKS, WORDS, TABLES = 4, 16, 3
#: Filters that a random vector exceeds in each table, on average, and at least.
EXPECTED = LEAST = 4
GROUP = 64
BLOCK = 3000
GROUP_ROWS = 20_000


def code_words_for(n: int) -> int:
    """Code words of a block for n vectors: WORDS at least, more where filters would hold over GROUP vectors."""
    return max(WORDS, int(np.ceil((n * EXPECTED / GROUP) ** (1 / BLOCKS))))


@lru_cache(maxsize=32)
def code(dim: int, t: int, words: int = WORDS) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray], float]:
    """(rotation, dimensions of each block, code words of each block, threshold)."""
    rng = np.random.default_rng([dim, t, words])
    rotation, _ = np.linalg.qr(rng.normal(size=(dim, dim)))
    parts = np.array_split(np.arange(dim), min(BLOCKS, dim))
    code_words = []
    for p in parts:
        w = rng.normal(size=(words, len(p)))
        code_words.append(w / np.linalg.norm(w, axis=1, keepdims=True) / np.sqrt(len(parts)))
    z = NormalDist().inv_cdf(1 - EXPECTED / words ** len(parts))
    return rotation, parts, code_words, z / np.sqrt(dim)


def decode(x: np.ndarray, words: int = WORDS) -> list[np.ndarray]:
    """Sorted filter numbers of each unit vector, over all tables."""
    n, dim = x.shape
    out: list[list[np.ndarray]] = [[] for _ in range(n)]
    for t in range(TABLES):
        rotation, parts, code_words, level = code(dim, t, words)
        y = x @ rotation
        inner = [y[:, p] @ w.T for p, w in zip(parts, code_words, strict=True)]
        # The best codes only use the best words of each block: LEAST of them give the vector's own level.
        best = np.zeros((n, 1))
        for i in inner:
            best = (best[:, :, None] + np.sort(i, 1)[:, None, -LEAST:]).reshape(n, -1)
        own = np.minimum(level, np.sort(best, 1)[:, -min(LEAST, best.shape[1])] - 1e-12)
        rest = np.concatenate([np.cumsum([i.max(1) for i in inner][::-1], 0)[::-1], np.zeros((1, n))])
        rows, score, number = np.arange(n), np.zeros(n), np.zeros(n, np.int64)
        for k, i in enumerate(inner):  # a partial code lives while its best end can reach the level
            s = score[:, None] + i[rows]
            r, w = np.nonzero(s + rest[k + 1][rows][:, None] >= own[rows][:, None])
            rows, score, number = rows[r], s[r, w], number[r] * words + w
        order = np.lexsort((number, rows))
        rows, number = rows[order], number[order]
        for i, f in zip(*(np.unique(rows), np.split(number, np.flatnonzero(np.diff(rows)) + 1)), strict=True):
            out[i].append((dim << 48) + (t << 40) + f)
    return [np.concatenate(f) for f in out]


def links(x: np.ndarray, y: np.ndarray, fx: list[np.ndarray], fy: list[np.ndarray], least: float, here: int, same: bool) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (of x, of y) with cosine >= least whose least common filter is `here`."""
    near = x @ y.T >= least
    if same:
        near = np.triu(near, 1)
    a, b = np.nonzero(near)
    if len(a) > 256:
        before = np.unique(np.concatenate([f[f < here] for f in (*fx, *fy)]))
        if len(before):
            def marks(lists):
                m = np.zeros((len(lists), len(before)), np.float32)
                for i, f in enumerate(lists):
                    m[i, np.searchsorted(before, f[f < here])] = 1
                return m

            mx = marks(fx)
            first = mx @ (mx if same else marks(fy)).T == 0
            ok = first[a, b]
            a, b = a[ok], b[ok]
    elif len(a):
        ok = [np.intersect1d(fx[i], fy[j], assume_unique=True)[0] == here for i, j in zip(a.tolist(), b.tolist(), strict=True)]
        a, b = a[ok], b[ok]
    return a, b


def forest(a: np.ndarray, b: np.ndarray) -> list[int]:
    """Numbers of pairs that join all that the pairs join."""
    up: dict[int, int] = {}

    def root(v: int) -> int:
        while up.setdefault(v, v) != v:
            up[v] = up[up[v]]
            v = up[v]
        return v

    out = []
    for k, (i, j) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
        i, j = root(i), root(j)
        if i != j:
            up[i] = j
            out.append(k)
    return out


def near_duplicates(vectors: DataFrame, spark: SparkSession, least: float = 0.95, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """id_col, n_links, component_id, kept for every row."""
    ship(spark)
    v = F.col("v")
    rows = vectors.select(vectors[id_col].alias("id"), vectors[vector_col].cast("array<double>").alias("v"))
    good = v.isNotNull() & F.expr("size(v) > 0 and not exists(v, c -> c is null or isnan(c) or abs(c) = double('Infinity')) and exists(v, c -> c <> 0)")
    rows = rows.withColumn("good", F.coalesce(good, F.lit(False))).withColumn("h1", F.xxhash64("v")).withColumn("h2", F.hash("v"))
    classes = keep(rows.filter("good").groupBy("h1", "h2").agg(F.min("id").cast("long").alias("rep"), F.count("*").alias("size"), F.first("v").alias("v")), spark)

    words = code_words_for(classes.count())

    def filters(batches):
        import pandas as pd

        for pdf in batches:
            raw = pdf["v"].tolist()
            dims = np.array([len(r) for r in raw])
            for d in np.unique(dims):
                at = np.flatnonzero(dims == d)
                for k in range(0, len(at), 512):
                    own = at[k : k + 512]
                    x = np.array([raw[i] for i in own], np.float64)
                    x /= np.abs(x).max(1, keepdims=True)
                    x /= np.linalg.norm(x, axis=1, keepdims=True)
                    lists = decode(x, words)
                    n = [len(f) for f in lists]
                    rep, size = pdf["rep"].to_numpy()[own], pdf["size"].to_numpy()[own]
                    which = np.repeat(np.arange(len(own)), n)
                    unit = [r.tobytes() for r in x]
                    mine = [f.astype("<i8").tobytes() for f in lists]
                    yield pd.DataFrame({"f": np.concatenate(lists), "rep": rep[which], "size": size[which], "x": [unit[w] for w in which], "own": [mine[w] for w in which]})

    listed = keep(classes.mapInPandas(filters, "f long, rep long, size long, x binary, own binary"), spark)
    counts = keep(listed.groupBy("f").agg(F.count("*").alias("m")).filter("m > 1"), spark)
    total = counts.agg(F.sum("m")).first()[0] or 0
    groups = max(1, total // GROUP_ROWS)
    placed = listed.join(small(counts, spark), "f")
    nb = F.ceil(F.col("m") / BLOCK).cast("int")
    placed = placed.withColumn("nb", nb).withColumn("block", F.pmod(F.xxhash64("rep"), F.col("nb")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    placed = placed.withColumn("bi", F.least("block", "other")).withColumn("bj", F.greatest("block", "other"))
    placed = placed.withColumn("g", F.when(F.col("nb") == 1, F.pmod(F.xxhash64("f"), F.lit(groups))).otherwise(F.xxhash64("f", "bi", "bj")))

    def compare(pdf):
        import pandas as pd

        out = []
        for (f, bi, bj), part in pdf.groupby(["f", "bi", "bj"], sort=False):
            if len(part) < 2:
                continue
            x = np.stack([np.frombuffer(r) for r in part["x"]])
            own = [np.frombuffer(r, "<i8") for r in part["own"]]
            rep, size = part["rep"].to_numpy(), part["size"].to_numpy()
            if bi == bj:
                p = q = np.arange(len(part))
            else:
                side = part["block"].to_numpy() == bi
                p, q = np.flatnonzero(side), np.flatnonzero(~side)
            if not len(p) or not len(q):
                continue
            a, b = links(x[p], x[q], [own[i] for i in p], [own[i] for i in q], least, f, bi == bj)
            if not len(a):
                continue
            a, b = p[a], q[b]
            n = np.bincount(a, size[b], len(part)) + np.bincount(b, size[a], len(part))
            at = np.flatnonzero(n)
            out.append(pd.DataFrame({"a": rep[at], "b": -1, "n": n[at].astype(np.int64)}))
            k = forest(a, b)
            out.append(pd.DataFrame({"a": rep[a[k]], "b": rep[b[k]], "n": 0}))
        return pd.concat(out) if out else pd.DataFrame({"a": [], "b": [], "n": []})

    found = keep(placed.groupBy("g").applyInPandas(compare, "a long, b long, n long"), spark)
    release(spark, listed, counts)
    linked = found.filter("n > 0").groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("n"))
    comp = components(found.filter("n = 0").select(F.col("a").alias("src"), F.col("b").alias("dst")), spark).withColumnRenamed("node", "rep")
    done = classes.select("h1", "h2", "rep", "size").join(linked, "rep", "left").join(comp, "rep", "left")
    done = done.select("h1", "h2", F.lit(True).alias("good"), (F.coalesce("n", F.lit(0)) + F.col("size") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component_id"))
    out = rows.drop("v").join(done, ["h1", "h2", "good"], "left")
    own = F.coalesce("component_id", F.col("id").cast("long"))
    return out.select(F.col("id").alias(id_col), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), own.alias("component_id"), F.coalesce(F.col("id") == own, F.lit(False)).alias("kept"))
