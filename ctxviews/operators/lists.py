"""Exact best-k search by sparse inner products, for batches of queries over an index kept by unit.

An index row holds all features and weights of one unit, so a unit's score is whole
where its row lies: each task keeps its own k best for each query, and a shuffle
carries k rows for each (query, task), not one for each pair that shares a feature.  The relational form - join by feature, group by (query, unit) - moves nearly
all pairs as soon as queries hold frequent words.

Queries come in blocks of bounded size: BLOCK queries share one matrix, BLOCKS blocks
(fewer if k is large, see HELD) one scan of the index.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from ctxviews.functions.ship import ship

BLOCK, BLOCKS = 1024, 16
#: Best rows that a task holds for the queries of one scan, if one block does not need more.
HELD = 1 << 18
#: Units scored together, and features up to which a block becomes a dense matrix.
UNITS, DENSE = 2048, 2048


def grouped(vectors: DataFrame, key: str = "unit_id", feature: str = "bucket", weight: str = "w") -> DataFrame:
    """key, f, w: rows (key, feature, weight) as one row for each unit, features in order."""
    both = F.array_sort(F.collect_list(F.struct(F.col(feature).alias("f"), F.col(weight).cast("double").alias("w"))))
    return vectors.groupBy(key).agg(both.alias("x")).select(key, F.col("x.f").alias("f"), F.col("x.w").alias("w"))


class Block:
    """Queries by feature: a dense matrix if there are few features, else the queries of each feature."""

    def __init__(self, ids: list[str], rows: list[tuple[int, object, float]]):
        names = sorted({f for _, f, _ in rows})
        self.ids, self.names = ids, names
        at = {f: i for i, f in enumerate(names)}
        q = np.array([r[0] for r in rows], np.int64)
        t = np.array([at[r[1]] for r in rows], np.int64)
        w = np.array([r[2] for r in rows], np.float64)
        order = np.argsort(t, kind="stable")
        self.edge = np.searchsorted(t[order], np.arange(len(names) + 1))
        self.q, self.w = q[order], w[order]
        self.matrix = None
        if len(names) <= DENSE:
            self.matrix = np.zeros((len(ids), len(names)))
            self.matrix[q, t] = w
            self.short, self.norm = self.matrix.astype(np.float32), np.sqrt((self.matrix**2).sum(axis=1))

    def score(self, t: np.ndarray, u: np.ndarray, v: np.ndarray, n: int) -> np.ndarray:
        """Inner products with units whose features t (of unit u) weigh v."""
        if self.matrix is not None:
            m = np.zeros((len(self.names), n))
            m[t, u] = v
            return self.matrix @ m
        s = np.zeros((len(self.ids), n))
        for at, w, x in self._each(t, u, v):
            s[at] += w[:, None] * x
        return s

    def above(self, t: np.ndarray, u: np.ndarray, v: np.ndarray, n: int, least: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, unit, score to six digits) of pairs that score at least `least` of the query.

        A product in single precision leaves out pairs that are below by more than its error can be; the others are scored in double.
        """
        if self.matrix is None:
            s = six(self.score(t, u, v, n))
            q, u = np.nonzero(s >= least[:, None])
            return q, u, s[q, u]
        m = np.zeros((n, len(self.names)))
        m[u, t] = v
        off = self.norm * np.sqrt((m**2).sum(axis=1).max()) * (len(self.names) + 4) * 2.0**-23
        with np.errstate(over="ignore", invalid="ignore"):
            s = self.short @ m.astype(np.float32).T
        q, u = np.nonzero(~(s < (least - off * 2 - 1e-6 - np.abs(least) * 2.0**-23).astype(np.float32)[:, None]))
        s = np.concatenate([np.zeros(0), *(six(np.einsum("ij,ij->i", self.matrix[q[a : a + 4096]], m[u[a : a + 4096]])) for a in range(0, len(q), 4096))])
        has = s >= least[q]
        return q[has], u[has], s[has]

    def shared(self, t: np.ndarray, u: np.ndarray, n: int) -> np.ndarray:
        """Whether a query and a unit have a feature in common."""
        s = np.zeros((len(self.ids), n), bool)
        for at, _, _ in self._each(t, u, np.zeros(len(t))):
            s[at] = True
        return s

    def _each(self, t: np.ndarray, u: np.ndarray, v: np.ndarray):
        order = np.argsort(t, kind="stable")
        t, u, v = t[order], u[order], v[order]
        cut = np.flatnonzero(np.diff(t, prepend=-1))
        for a, b in zip(cut, np.append(cut[1:], len(t)), strict=True):
            x, y = self.edge[t[a]], self.edge[t[a] + 1]
            yield np.ix_(self.q[x:y], u[a:b]), self.w[x:y], v[a:b]


def six(s: np.ndarray) -> np.ndarray:
    return np.floor(s * 1e6 + 0.5) / 1e6


def best(s: np.ndarray, shared, place: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(query, unit) numbers of each query's k best units among those it shares a feature with; ties by place.

    shared() is asked only if a query's k-th score is not positive: a unit without a shared feature scores 0.
    """
    n = s.shape[1]
    least = np.partition(s, n - k, axis=1)[:, n - k] if n > k else np.full(len(s), -np.inf)
    if (least <= 0).any():
        s[~shared()] = -np.inf
        least = np.partition(s, n - k, axis=1)[:, n - k] if n > k else least
    q, u = np.nonzero((s >= least[:, None]) & (s > -np.inf))
    order = np.lexsort((place[u], -s[q, u], q))
    q, u = q[order], u[order]
    rank = np.arange(len(q)) - np.searchsorted(q, q, "left")
    return q[rank < k], u[rank < k]


class Best:
    """The k best (unit, score) of each of n queries over any number of batches; ties go by unit."""

    def __init__(self, n: int, k: int):
        self.k, self.least, self.rows, self.new = k, np.full(n, -np.inf), 0, []

    def add(self, q: np.ndarray, names, u: np.ndarray, s: np.ndarray) -> None:
        """Scores s of queries q with the units u of the Arrow array names."""
        has = np.flatnonzero(s >= self.least[q])
        if not len(has):
            return
        self.new.append((q[has], np.array(names.take(u[has]).to_pylist(), dtype=object), s[has]))
        self.rows += len(has)
        if self.rows > self.k * len(self.least) + 8192:
            self.all()

    def all(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(query, unit, score) of what is held, cut to k for each query."""
        import pandas as pd

        if not self.new:
            return np.zeros(0, np.int64), np.zeros(0, object), np.zeros(0)
        d = pd.DataFrame({c: np.concatenate([x[i] for x in self.new]) for i, c in enumerate("qus")})
        d = d.sort_values(["q", "s", "u"], ascending=[True, False, True])
        d = d[d.groupby("q").cumcount() < self.k]
        full = d.groupby("q")["s"].agg(["size", "min"])
        full = full[full["size"] == self.k]
        self.least[full.index.to_numpy()] = full["min"].to_numpy()
        self.new, self.rows = [(d["q"].to_numpy(), d["u"].to_numpy(), d["s"].to_numpy())], 0
        return self.new[0]


def search(vectors: DataFrame, queries: DataFrame, k: int, key: str = "unit_id") -> DataFrame:
    """query_id, key, score, rank: vectors (key, f array, w array) against queries (query_id, f, w).

    Scores are rounded to six digits; ties go by key.  Units that share no feature with a
    query are not among its best.  A query's features must be distinct.  Queries of
    different parts (a column of that name) share no block: their features have nothing in common.
    """
    spark = vectors.sparkSession
    ship(spark)
    part_of = F.col("part") if "part" in queries.columns else F.lit(0)
    rows = queries.select("query_id", "f", "w", part_of.alias("part")).filter("w is not null and f is not null").collect()
    owners: dict = {}
    for r in rows:
        owners.setdefault(r.part, set()).add(r.query_id)
    blocks = [own[b : b + BLOCK] for own in (sorted(owners[p]) for p in sorted(owners)) for b in range(0, len(own), BLOCK)]
    kind, unit = dict(vectors.dtypes)[key], to_arrow_type(vectors.schema[key].dataType)
    out = None
    scans: list[list] = [[]]
    for own in blocks:
        if scans[-1] and (len(scans[-1]) == BLOCKS or (sum(map(len, scans[-1])) + len(own)) * k > HELD):
            scans.append([])
        scans[-1].append(own)
    for batch in scans:
        at = {q: (b, i) for b, own in enumerate(batch) for i, q in enumerate(own)}
        parts: list[list] = [[] for _ in batch]
        for r in rows:
            if (place := at.get(r.query_id)) is not None:
                parts[place[0]].append((place[1], r.f, r.w))
        shared = spark.sparkContext.broadcast([Block(own, p) for own, p in zip(batch, parts, strict=True)])

        def run(batches, shared=shared):
            import pyarrow as pa
            import pyarrow.compute as pc

            held = [Best(len(block.ids), k) for block in shared.value]
            for rb in batches:
                for first in range(0, rb.num_rows, UNITS):
                    own = rb.slice(first, UNITS)
                    names, f = own.column(0), own.column(1)
                    at_row = np.repeat(np.arange(own.num_rows), pc.fill_null(pc.list_value_length(f), 0).to_numpy(zero_copy_only=False))
                    flat, v = f.flatten(), own.column(2).flatten().to_numpy(zero_copy_only=False)
                    place = np.argsort(np.argsort(names.to_numpy(zero_copy_only=False), kind="stable"), kind="stable")
                    for block, mine in zip(shared.value, held, strict=True):
                        t = pc.fill_null(pc.index_in(flat, value_set=pa.array(block.names, flat.type)), -1).to_numpy(zero_copy_only=False)
                        has = t >= 0
                        if not has.any():
                            continue
                        t, at_unit = t[has], at_row[has]
                        if (mine.least > 0).all():
                            q, u, s = block.above(t, at_unit, v[has], own.num_rows, mine.least)
                            mine.add(q, names, u, s)
                            continue
                        s = six(block.score(t, at_unit, v[has], own.num_rows))
                        q, u = best(s, lambda b=block, x=t, y=at_unit, n=own.num_rows: b.shared(x, y, n), place, k)
                        mine.add(q, names, u, s[q, u])
            for block, mine in zip(shared.value, held, strict=True):
                q, u, s = mine.all()
                yield pa.RecordBatch.from_arrays([pa.array([block.ids[i] for i in q.tolist()], pa.string()), pa.array(u.tolist(), unit), pa.array(s, pa.float64())], ["query_id", key, "score"])

        part = vectors.select(key, "f", "w").mapInArrow(run, f"query_id string, `{key}` {kind}, score double")
        out = part if out is None else out.unionByName(part)
    w = W.partitionBy("query_id").orderBy(F.desc("score"), key)
    return out.select("query_id", key, F.round("score", 6).alias("score")).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
