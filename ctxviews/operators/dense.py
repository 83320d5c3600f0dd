"""The dense view: encoders, exact and approximate search, content-addressed deltas.

Encoders are signed feature hashes of tokens weighted by tf and idf; a vector is
kept sparse as (unit, bucket, weight) rows of length one, so encoding and inner
products are groupings and joins that never leave the JVM.  Dense arrays (the
`embeddings` table, stored indexes) are searched in Arrow blocks.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.ship import ship
from ctxviews.functions.text import digest, md5_number, tokens
from ctxviews.operators import lists, rows
from ctxviews.operators.lexical import top


@dataclass(frozen=True)
class Encoder:
    name: str
    dim: int
    features: str = "token"  # token, bigram (tokens and pairs) or char (3-grams)


#: Five encoders of growing dimension.
ENCODERS = [Encoder("hash64", 64), Encoder("hash128", 128), Encoder("hash256", 256), Encoder("hash512", 512), Encoder("hash1024", 1024)]


def features(c: Column, e: Encoder) -> Column:
    t = tokens(c)
    if e.features == "bigram":
        return F.concat(t, F.zip_with(F.slice(t, 1, F.greatest(F.size(t) - 1, F.lit(0))), F.slice(t, 2, F.greatest(F.size(t) - 1, F.lit(0))), lambda a, b: F.concat_ws(" ", a, b)))
    if e.features == "char":
        low = F.lower(c)
        return F.transform(F.sequence(F.lit(1), F.greatest(F.length(low) - 2, F.lit(1))), lambda i: low.substr(i, F.lit(3)))
    return t


def document_frequency(u: DataFrame, e: Encoder) -> DataFrame:
    """feature, idf over units."""
    n = u.agg(F.count("*").alias("n"))
    df = u.select(F.explode(F.array_distinct(features(F.col("text"), e))).alias("f")).groupBy("f").agg(F.count("*").alias("df"))
    return df.crossJoin(F.broadcast(n)).select("f", F.log(1 + F.col("n") / F.col("df")).alias("idf"))


def vectors(u: DataFrame, e: Encoder, idf: DataFrame, key: str = "unit_id") -> DataFrame:
    """key, f, w: the vectors of a corpus as lists, in its rows; idf has every feature of u."""
    return rows.weigh(rows.count(u, features(F.col("text"), e), key), idf, e.dim, key)


def encode(u: DataFrame, e: Encoder, idf: DataFrame, key: str = "unit_id") -> DataFrame:
    """key, bucket, w: unit vectors in sparse form; features without an idf weigh nothing.

    For batches of queries, whose features meet the idf in a join; a corpus goes through `vectors`.
    """
    tf = u.select(key, F.explode(features(F.col("text"), e)).alias("f")).groupBy(key, "f").agg(F.count("*").alias("tf"))
    h = md5_number(F.col("f"))
    sign = F.when(F.shiftright(h, 16) % 2 == 0, 1.0).otherwise(-1.0)
    w = tf.join(idf, "f").groupBy(key, (h % e.dim).alias("bucket")).agg(F.sum(sign * F.col("tf") * F.col("idf")).alias("w"))
    norm = F.sqrt(F.sum(F.col("w") * F.col("w")).over(W.partitionBy(key)))
    return w.withColumn("norm", norm).filter("norm > 0 and abs(w) > 1e-9").select(key, "bucket", (F.col("w") / F.col("norm")).alias("w"))


def search_sparse(q: DataFrame, vectors: DataFrame, k: int, key: str = "unit_id") -> DataFrame:
    """query_id, key, score, rank: exact inner products of sparse vectors, rows (key, bucket, w) or
    stored lists (key, f, w)."""
    stored = vectors if "f" in vectors.columns else lists.grouped(vectors, key)
    return lists.search(stored, q.select("query_id", F.col("bucket").alias("f"), "w"), k, key)


# --- dense arrays ----------------------------------------------------------------------------


def _double(c: str) -> Column:
    return F.transform(F.col(c), lambda x: x.cast("double"))


def dot(a: str, b: str) -> Column:
    return F.aggregate(F.zip_with(F.col(a), F.col(b), lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def search_flat(q: DataFrame, vectors: DataFrame, k: int, group: str | None = None) -> DataFrame:
    """query_id, vec_id, score, rank by exact inner product, itself left out; with `group` only inside it.

    A group has features of its own, so rows of other groups share none.
    """
    place = F.sequence(F.lit(0), F.size("embedding") - 1)
    f = place if group is None else F.transform(place, lambda i: F.concat_ws("|", F.col(group).cast("string"), i.cast("string")))
    rows = vectors.filter("size(embedding) > 0").select("vec_id", f.alias("f"), _double("embedding").alias("w"))
    asked = q.filter("size(embedding) > 0").select(F.col("vec_id").cast("string").alias("query_id"), F.explode(F.arrays_zip(f.alias("f"), _double("embedding").alias("w"))).alias("x")).select("query_id", "x.f", "x.w")
    found = lists.search(rows, asked, k + 1, "vec_id").withColumn("query_id", F.col("query_id").cast("long"))
    return top(found.filter("query_id <> vec_id").drop("rank"), k, "vec_id")


def search_blocks(spark: SparkSession, queries: np.ndarray, ids: np.ndarray, vectors: DataFrame, k: int, block: int = 1024) -> DataFrame:
    """The same search for many queries as matrix products over Arrow batches: each batch keeps its own k
    best, so a shuffle carries k rows for each (query, batch).  Queries go in broadcast blocks of bounded size."""
    out = None
    for a in range(0, len(ids), block):
        shared = spark.sparkContext.broadcast((queries[a : a + block].astype(np.float64), ids[a : a + block]))

        def run(batches, shared=shared):
            import pandas as pd

            q, own = shared.value
            for pdf in batches:
                x = np.stack(pdf["embedding"]).astype(np.float64)
                v = pdf["vec_id"].to_numpy()
                s = np.round(q @ x.T, 6)
                s[own[:, None] == v[None]] = -np.inf
                n = min(k, s.shape[1])
                order = np.lexsort((np.broadcast_to(v, s.shape), -s), axis=1)[:, :n]
                yield pd.DataFrame({"query_id": np.repeat(own, n), "vec_id": v[order].ravel(), "score": np.take_along_axis(s, order, 1).ravel()}).query("score > -2")

        part = vectors.select("vec_id", "embedding").mapInPandas(run, "query_id long, vec_id long, score double")
        out = part if out is None else out.unionByName(part)
    return top(out, k, "vec_id")


# --- inverted lists ----------------------------------------------------------------------------

PROBES = (0.01, 0.02, 0.05, 0.1, 0.25, 0.5, 1.0)


def build_ivf(spark: SparkSession, vectors: DataFrame, lists: int, rounds: int = 10) -> tuple[np.ndarray, DataFrame]:
    """(centroids, vectors with list_id).  Spherical Lloyd rounds: the driver holds `lists` centroids only."""
    seeds = vectors.orderBy(F.md5(F.col("vec_id").cast("string"))).limit(lists).select("embedding").collect()
    c = np.array([r.embedding for r in seeds], np.float64)

    def assign(c: np.ndarray) -> DataFrame:
        shared = spark.sparkContext.broadcast(c)

        def run(batches):
            for pdf in batches:
                x = np.stack(pdf["embedding"]).astype(np.float64)
                yield pdf.assign(list_id=(x @ shared.value.T).argmax(1))

        return vectors.mapInPandas(run, ", ".join(f"`{n}` {k}" for n, k in vectors.dtypes) + ", list_id int")

    for _ in range(rounds):
        dim = c.shape[1]
        sums = assign(c).groupBy("list_id").agg(F.array(*[F.sum(F.col("embedding")[i].cast("double")) for i in range(dim)]).alias("s")).collect()
        new = c.copy()
        for r in sums:
            s = np.array(r.s)
            new[r.list_id] = s / max(1e-12, np.linalg.norm(s))
        if np.allclose(new, c, atol=1e-9):
            break
        c = new
    return c, assign(c)


def search_ivf(spark: SparkSession, q: DataFrame, centroids: np.ndarray, listed: DataFrame, k: int, fractions: tuple[float, ...] = PROBES, block: int = 1024) -> DataFrame:
    """fraction, query_id, vec_id, score, rank: the lists nearest to a query, max(1, ceil(fraction x lists)) of them.

    Queries go in blocks; what is shared are their vectors and the places of the lists in
    their orders.  A batch of listed vectors keeps its own k best for each fraction.
    """
    n, out = len(centroids), None
    widths = [(f, max(1, int(np.ceil(f * n)))) for f in fractions]
    asked = q.select("vec_id", "embedding").orderBy("vec_id").collect()  # a batch of queries
    for a in range(0, max(1, len(asked)), block):
        own = np.array([r.vec_id for r in asked[a : a + block]], np.int64)
        x = np.array([r.embedding for r in asked[a : a + block]], np.float64).reshape(len(own), -1)
        place = np.argsort(np.argsort(-(x @ centroids.T), axis=1, kind="stable"), axis=1).astype(np.int32) if len(own) else np.zeros((0, n), np.int32)
        shared = spark.sparkContext.broadcast((own, x, place))

        def run(batches, shared=shared):
            import pandas as pd

            own, x, place = shared.value
            for pdf in batches:
                if not len(pdf) or not len(own):
                    continue
                v = pdf["vec_id"].to_numpy()
                s = np.floor(x @ np.stack(pdf["embedding"]).astype(np.float64).T * 1e6 + 0.5) / 1e6
                s[own[:, None] == v[None]] = -np.inf
                near = place[:, pdf["list_id"].to_numpy()]
                for f, width in widths:
                    t = np.where(near < width, s, -np.inf)
                    m = min(k, len(v))
                    order = np.lexsort((np.broadcast_to(v, t.shape), -t), axis=1)[:, :m]
                    score = np.take_along_axis(t, order, 1).ravel()
                    ok = score > -np.inf
                    yield pd.DataFrame({"fraction": f, "query_id": np.repeat(own, m)[ok], "vec_id": v[order].ravel()[ok], "score": score[ok]})

        part = listed.select("vec_id", "embedding", "list_id").mapInPandas(run, "fraction double, query_id long, vec_id long, score double")
        out = part if out is None else out.unionByName(part)
    w = W.partitionBy("fraction", "query_id").orderBy(F.desc("score"), "vec_id")
    return out.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


# --- layered graphs ------------------------------------------------------------------------------


class Layered:
    """A navigable small-world graph with layers, for one shard of vectors (inner product)."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, m: int = 32, construction: int = 200):
        import hashlib

        order = np.argsort(ids, kind="stable")
        self.ids, self.x, self.m = ids[order], x[order], m
        u = np.array([(int(hashlib.md5(str(i).encode()).hexdigest()[:8], 16) + 1) / 2**32 for i in self.ids.tolist()])
        self.level = np.floor(-np.log(u) / np.log(m)).astype(int)
        self.links: list[list[list[int]]] = [[[] for _ in range(v + 1)] for v in self.level]
        self.entry = 0
        for i in range(1, len(self.ids)):
            self._insert(i, construction)
            if self.level[i] > self.level[self.entry]:
                self.entry = i

    def _near(self, q: np.ndarray, start: int, ef: int, layer: int) -> list[tuple[float, int]]:
        """About ef best nodes of a layer, best first."""
        import heapq

        s = float(self.x[start] @ q)
        seen, open_, best = {start}, [(-s, start)], [(s, start)]
        while open_:
            d, v = heapq.heappop(open_)
            if -d < best[0][0] and len(best) >= ef:
                break
            new = [w for w in self.links[v][layer] if w not in seen]
            if not new:
                continue
            seen.update(new)
            for t, w in zip((self.x[new] @ q).tolist(), new, strict=True):
                if len(best) < ef or t > best[0][0]:
                    heapq.heappush(open_, (-t, w))
                    heapq.heappush(best, (t, w))
                    if len(best) > ef:
                        heapq.heappop(best)
        return sorted(best, key=lambda b: (-b[0], b[1]))

    def _choose(self, cand: list[tuple[float, int]], most: int) -> list[int]:
        """Neighbours in different directions: one nearer to a chosen neighbour than to the node waits."""
        out: list[int] = []
        late: list[int] = []
        for s, v in cand:
            if len(out) >= most:
                break
            (out if not out or float((self.x[out] @ self.x[v]).max()) < s else late).append(v)
        return out + late[: most - len(out)]

    def _insert(self, i: int, construction: int) -> None:
        at = self.entry
        for layer in range(self.level[at], self.level[i], -1):
            at = self._near(self.x[i], at, 1, layer)[0][1]
        for layer in range(min(self.level[i], self.level[self.entry]), -1, -1):
            found = self._near(self.x[i], at, construction, layer)
            most = 2 * self.m if layer == 0 else self.m
            mine = self._choose(found, self.m)
            self.links[i][layer] = list(mine)
            for v in mine:
                other = self.links[v][layer]
                other.append(i)
                if len(other) > most:
                    s = self.x[other] @ self.x[v]
                    o = np.argsort(-s, kind="stable")
                    self.links[v][layer] = self._choose([(float(s[j]), other[j]) for j in o], most)
            at = found[0][1]

    def search(self, q: np.ndarray, k: int, ef: int) -> list[tuple[int, float]]:
        if not len(self.ids):
            return []
        at = self.entry
        for layer in range(self.level[at], 0, -1):
            at = self._near(q, at, 1, layer)[0][1]
        return [(int(self.ids[v]), s) for s, v in self._near(q, at, max(ef, k), 0)[:k]]


def _bound(f, shared):
    return lambda pdf: f(shared, pdf)


#: Vectors of a graph at most, on average; queries that one search task holds.
SHARD, ASKED = 50_000, 4096


def search_hnsw(q: DataFrame, vectors: DataFrame, k: int, efs: tuple[int, ...] = (16, 32, 64, 128), shards: int | None = None, m: int = 32, construction: int = 200) -> DataFrame:
    """ef, query_id, vec_id, score, rank: a graph for each shard of about SHARD vectors, searched where it is
    built, merged by rank.  Queries are a batch; more than ASKED go in several passes."""
    spark = vectors.sparkSession
    ship(spark)
    shards = shards or max(1, -(-vectors.count() // SHARD))
    asked = q.select("vec_id", "embedding").orderBy("vec_id").collect()
    shard = F.pmod(md5_number(F.col("vec_id").cast("string")), F.lit(shards))
    dealt, found = vectors.select("vec_id", "embedding", shard.alias("shard")), None
    for a in range(0, max(1, len(asked)), ASKED):
        shared = spark.sparkContext.broadcast([(int(r.vec_id), list(r.embedding)) for r in asked[a : a + ASKED]])

        def run(shared, pdf):
            import pandas as pd

            g = Layered(pdf["vec_id"].to_numpy(), np.stack(pdf["embedding"]).astype(np.float64), m, construction)
            rows = [(ef, i, v, round(s, 6)) for i, x in shared.value for ef in efs for v, s in g.search(np.array(x, np.float64), k + 1, ef) if v != i]
            return pd.DataFrame(rows, columns=["ef", "query_id", "vec_id", "score"])

        part = dealt.groupBy("shard").applyInPandas(_bound(run, shared), "ef int, query_id long, vec_id long, score double")
        found = part if found is None else found.unionByName(part)
    w = W.partitionBy("ef", "query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


# --- deltas ----------------------------------------------------------------------------------------

REBUILD_SHARE = 0.2


def content_key(profile: str) -> Column:
    return digest(F.lit(profile), F.col("text"))


def delta(old: DataFrame, new_units: DataFrame, profile: str) -> DataFrame:
    """New units with action reuse or encode: a unit whose content key is stored keeps its vector."""
    stored = old.select(content_key(profile).alias("content_key")).distinct().withColumn("stored", F.lit(True))
    keyed = new_units.withColumn("content_key", content_key(profile))
    return keyed.join(stored, "content_key", "left").withColumn("action", F.when(F.col("stored"), "reuse").otherwise("encode")).drop("stored")


def update(index: DataFrame, keys: DataFrame, vectors: DataFrame) -> DataFrame:
    """The index (unit_id, content_key, f, w) changed in place: rows of units that went or changed leave, units of
    `keys` (unit_id, content_key) that are new or changed come with their vectors (content_key, f, w)."""
    stay = index.join(keys, ["unit_id", "content_key"], "left_semi")
    come = keys.join(index.select("unit_id", "content_key"), ["unit_id", "content_key"], "left_anti").join(vectors, "content_key")
    return stay.select("unit_id", "content_key", "f", "w").unionByName(come.select("unit_id", "content_key", "f", "w"))


def index_action(changed: int, total: int, threshold: float = REBUILD_SHARE) -> str:
    """Small deltas change the index in place, large ones rebuild it."""
    return "rebuild" if total == 0 or changed / total > threshold else "mutate"
