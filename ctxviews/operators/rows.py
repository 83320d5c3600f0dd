"""Kernels that stay inside a row: a unit's features are counted, listed and weighed where its text lies.

A grouping by (unit, feature) would send every token with its unit's key through a
shuffle, several times the text; nothing here is sent but, for corpora of very many
terms, the rare ones (see weigh).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ctxviews.functions.ship import ship
from ctxviews.functions.text import tokens

#: Terms whose weights every task gets, the most frequent ones first; rarer terms meet theirs in a join.
HEAD = 3 << 20


#: Values of lists that a kernel takes at once, if its rows are not longer.
VALUES = 1 << 18


def _parts(batches, values: int = VALUES):
    """The batches in slices of about so many list values (column 1): a batch of long texts does not fill a worker."""
    import pyarrow.compute as pc

    for rb in batches:
        upto = np.cumsum(pc.fill_null(pc.list_value_length(rb.column(1)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
        a = 0
        while a < rb.num_rows:
            b = max(a + 1, int(np.searchsorted(upto, (upto[a - 1] if a else 0) + values, "right")))
            yield rb.slice(a, b - a)
            a = b


def _codes(lists):
    """(row of each value, code of each value, distinct values in order, values of each row) of an Arrow list column."""
    import pyarrow as pa
    import pyarrow.compute as pc

    size = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    flat = lists.flatten().dictionary_encode()
    if isinstance(flat, pa.ChunkedArray):
        flat = flat.combine_chunks()
    order = pc.sort_indices(flat.dictionary).to_numpy()
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    return np.repeat(np.arange(len(size)), size), place[flat.indices.to_numpy()], flat.dictionary.take(pa.array(order)), size


def _listed(n: int, row: np.ndarray, values):
    """One list for each of n rows from values sorted by row."""
    import pyarrow as pa

    return pa.ListArray.from_arrays(pa.array(np.searchsorted(row, np.arange(n + 1)), pa.int32()), values)


def count(u: DataFrame, features: Column, key: str = "unit_id") -> DataFrame:
    """key, dl, f, tf of every unit: its number of features, the distinct ones in order, how often each is there."""
    ship(u.sparkSession)

    def run(batches):
        import pyarrow as pa

        for rb in _parts(batches):
            row, code, words, size = _codes(rb.column(1))
            both, tf = np.unique(row * len(words) + code, return_counts=True)
            row, code = np.divmod(both, max(1, len(words)))
            made = [rb.column(0), pa.array(size), _listed(len(size), row, words.take(pa.array(code))), _listed(len(size), row, pa.array(tf.astype(np.int64)))]
            yield pa.RecordBatch.from_arrays(made, [key, "dl", "f", "tf"])

    return u.select(key, features.alias("f")).mapInArrow(run, f"`{key}` {dict(u.dtypes)[key]}, dl long, f array<string>, tf array<long>")


def post(u: DataFrame, features: Column, key: str = "unit_id") -> DataFrame:
    """term, key, tf, positions: one row for each distinct feature of a unit."""
    ship(u.sparkSession)

    def run(batches):
        import pyarrow as pa

        for rb in _parts(batches):
            row, code, words, size = _codes(rb.column(1))
            at = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size)
            both = row * len(words) + code
            order = np.argsort(both, kind="stable")
            first = np.flatnonzero(np.diff(both[order], prepend=-1))
            tf = np.diff(first, append=len(order))
            row, code = np.divmod(both[order][first], max(1, len(words)))
            places = pa.ListArray.from_arrays(pa.array(np.append(first, len(order)), pa.int32()), pa.array(at[order].astype(np.int32)))
            yield pa.RecordBatch.from_arrays([words.take(pa.array(code)), rb.column(0).take(pa.array(row)), pa.array(tf.astype(np.int64)), places], ["term", key, "tf", "positions"])

    return u.select(key, features.alias("f")).mapInArrow(run, f"term string, `{key}` {dict(u.dtypes)[key]}, tf long, positions array<int>")


def first_uses(f: DataFrame, least: int) -> DataFrame:
    """repo, lang, path, symbols: the tokens of at least `least` characters that a file has within a line before it has them at a line's head."""
    ship(f.sparkSession)

    def run(batches):
        import pyarrow as pa
        import pyarrow.compute as pc

        for rb in _parts(batches, VALUES // 16):
            lines, n_lines = rb.column(1).flatten(), pc.list_value_length(rb.column(1)).to_numpy()
            row, code, words, size = _codes(lines)
            head = np.zeros(len(row), bool)
            head[(np.cumsum(size) - size)[size > 0]] = True
            both, first = np.unique(np.repeat(np.arange(rb.num_rows), n_lines)[row] * len(words) + code, return_index=True)
            file, code = np.divmod(both, max(1, len(words)))
            has = ~head[first] & (pc.utf8_length(words).to_numpy() >= least)[code]
            made = _listed(rb.num_rows, file[has], words.take(pa.array(code[has])))
            yield pa.RecordBatch.from_arrays([rb.column(0), made, rb.column(2), rb.column(3)], ["path", "symbols", "repo", "lang"])

    by_line = F.transform(F.split("text", "\n", -1), tokens)
    return f.select("path", by_line.alias("lines"), "repo", "lang").mapInArrow(run, "path string, symbols array<string>, repo string, lang string")


def _hash(words) -> np.ndarray:
    import pandas as pd

    return pd.util.hash_array(np.array(words.to_pylist(), dtype=object), categorize=False)


class Head:
    """Weights of terms by 64-bit hash; a found term is compared as text, so no other term gets its weight."""

    def __init__(self, names, weights: np.ndarray):
        import pyarrow as pa

        h = _hash(names)
        order = np.argsort(h, kind="stable")
        self.hash, self.weights, self.names = h[order], weights[order], names.take(pa.array(order))
        same = np.flatnonzero(np.diff(self.hash) == 0)
        again = np.unique(np.append(same, same + 1))
        self.clash = {self.names[int(i)].as_py(): float(self.weights[i]) for i in again}

    def find(self, words) -> np.ndarray:
        """The weight of each word, nan if it is not here."""
        import pyarrow as pa
        import pyarrow.compute as pc

        out = np.full(len(words), np.nan)
        if not len(words) or not len(self.hash):
            return out
        h = _hash(words)
        at = np.minimum(np.searchsorted(self.hash, h), len(self.hash) - 1)
        has = np.flatnonzero(self.hash[at] == h)
        same = pc.equal(self.names.take(pa.array(at[has])), words.take(pa.array(has))).to_numpy(zero_copy_only=False)
        out[has[same]] = self.weights[at[has[same]]]
        if self.clash:
            for i in has.tolist():
                if (w := self.clash.get(words[i].as_py())) is not None:
                    out[i] = w
        return out


class Known:
    """Hash and weight of words that a task has met, so that a frequent word is looked up once."""

    MOST = 1 << 19

    def __init__(self, head: Head):
        self.head, self.at, self.h, self.w = head, {}, np.zeros(0, np.int64), np.zeros(0)

    def of(self, words) -> tuple[np.ndarray, np.ndarray]:
        """(hash, weight) of distinct words, nan for weights that the head has not."""
        import hashlib

        import pyarrow as pa

        if len(self.at) > self.MOST:
            self.at, self.h, self.w = {}, np.zeros(0, np.int64), np.zeros(0)
        text = words.to_pylist()
        at = np.fromiter((self.at.get(x, -1) for x in text), np.int64, len(text))
        new = np.flatnonzero(at < 0)
        if len(new):
            at[new] = len(self.h) + np.arange(len(new))
            own = [text[i] for i in new.tolist()]
            self.at.update(zip(own, at[new].tolist(), strict=True))
            self.h = np.append(self.h, np.frombuffer(b"".join([hashlib.md5(x.encode()).digest()[:4] for x in own]), ">u4").astype(np.int64))
            self.w = np.append(self.w, self.head.find(words.take(pa.array(new))))
        return self.h[at], self.w[at]


def starts(dims: tuple[int, ...]) -> list[int]:
    """The first bucket of each dimension, if their vectors lie one after another."""
    return [sum(dims[:i]) for i in range(len(dims))]


def weigh(counts: DataFrame, idf: DataFrame, dim: int | tuple[int, ...], key: str = "unit_id", most: int | None = None) -> DataFrame:
    """key, f, w: unit vectors of counted units (key, f, tf) by signed feature hashing, buckets in order.

    Several dimensions give their vectors one after another in a row; the buckets of each come after those of
    the dimensions before it (see starts).

    idf: f, idf of every feature of the units.  The `most` terms of least idf go to every task.  If all others
    have one idf (terms of one unit), they need no list; else each goes to its unit through a join, and a
    unit's counts meet what came for it in another.
    """
    import pyarrow as pa

    spark = counts.sparkSession
    ship(spark)
    dims = (dim,) if isinstance(dim, int) else tuple(dim)
    most = HEAD if most is None else most
    seen = sorted((r.idf, r.n) for r in idf.groupBy("idf").agg(F.count("*").alias("n")).collect())  # one row for each document frequency
    total, cut = 0, -1.0
    for x, n in seen[:-1]:
        total += n
        if total > most:
            break
        cut = x
    rest = [x for x, _ in seen if x > cut]
    table = idf.filter(F.col("idf") <= F.lit(float(cut))).select("f", "idf").toArrow().combine_chunks()
    column = lambda c, kind: table.column(c).cast(kind).combine_chunks() if table.num_rows else pa.array([], kind)
    shared = spark.sparkContext.broadcast(Head(column("f", pa.string()), column("idf", pa.float64()).to_numpy()))
    one = rest[0] if len(rest) == 1 else float("nan")

    def rare(batches):
        for rb in _parts(batches):
            row, code, words, _ = _codes(rb.column(1))
            far = np.flatnonzero(np.isnan(shared.value.find(words))[code])
            yield pa.RecordBatch.from_arrays([rb.column(0).take(pa.array(row[far])), words.take(pa.array(code[far]))], [key, "f"])

    def run(batches):
        known = Known(shared.value)
        for rb in _parts(batches, VALUES // len(dims)):
            row, code, words, size = _codes(rb.column(1))
            tf = rb.column(2).flatten().to_numpy()
            h, w = known.of(words)
            if rb.num_columns > 3:
                come = dict(zip(rb.column(3).flatten().to_pylist(), rb.column(4).flatten().to_pylist(), strict=True))
                for i in np.flatnonzero(np.isnan(w)).tolist():
                    w[i] = come.get(words[i].as_py(), 0.0)
            w = np.where(np.isnan(w), one, w)
            h, signed, made = h[code], np.where((h[code] >> 16) % 2 == 0, 1.0, -1.0) * tf * w[code], []
            for dim, start in zip(dims, starts(dims), strict=True):
                both, where = np.unique(row * dim + h % dim, return_inverse=True)
                x = np.bincount(where, signed, len(both))
                of, bucket = np.divmod(both, dim)
                norm = np.sqrt(np.bincount(of, x * x, len(size)))[of]
                ok = (norm > 0) & (np.abs(x) > 1e-9)
                made.append((of[ok], start + bucket[ok], x[ok] / norm[ok]))
            row, bucket, x = (np.concatenate(c) for c in zip(*made, strict=True))
            if len(dims) > 1:
                order = np.argsort(row, kind="stable")
                row, bucket, x = row[order], bucket[order], x[order]
            own, at = np.unique(row, return_inverse=True)
            made = [rb.column(0).take(pa.array(own)), _listed(len(own), at, pa.array(bucket)), _listed(len(own), at, pa.array(x))]
            yield pa.RecordBatch.from_arrays(made, [key, "f", "w"])

    kind = dict(counts.dtypes)[key]
    rows = counts.select(key, "f", "tf")
    if len(rest) > 1:
        far = idf.filter(F.col("idf") > F.lit(float(cut))).select("f", "idf")
        come = rows.mapInArrow(rare, f"`{key}` {kind}, f string").join(far, "f").groupBy(key).agg(F.collect_list(F.struct("f", "idf")).alias("x"))
        rows = rows.join(come.select(key, F.col("x.f").alias("xf"), F.col("x.idf").alias("xw")), key, "left")
    return rows.mapInArrow(run, f"`{key}` {kind}, f array<long>, w array<double>")
