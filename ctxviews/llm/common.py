"""Helpers shared by the training-data operators: scratch tables, vectorised
text kernels, bounded samples and connected components."""

from __future__ import annotations

import atexit
import contextlib
import os
import tempfile
import uuid
import zipfile
from pathlib import Path

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of text that one vectorised step works on (a longer text is one step).
STEP_BYTES = 1 << 18
#: Bytes up to which a table may be broadcast.
BROADCAST_BYTES = 48 << 20
#: Edges that one task joins by itself (16 bytes each).
FINISH_EDGES = 1_000_000
#: Rows of an Arrow batch at most.
ARROW_ROWS = 2000
#: Spark's setting for shuffle files that go with their query.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"

_scratch: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ship(spark: SparkSession) -> None:
    """Give executors this package once per application, however the driver found it, and keep
    Arrow batches small: their rows hold whole texts."""
    rows = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(rows, "10000")) <= ARROW_ROWS:
        spark.conf.set(rows, str(ARROW_ROWS))
    sc = spark.sparkContext
    if getattr(sc, "_ctxviews_shipped", False):
        return
    root = Path(__file__).resolve().parents[1]
    path = Path(tempfile.mkdtemp()) / "ctxviews_pkg.zip"
    with zipfile.ZipFile(path, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, str(Path(root.name) / p.relative_to(root)))
    sc.addPyFile(str(path))
    sc._ctxviews_shipped = True


def scratch_dir(spark: SparkSession) -> str:
    """The cluster's shared folder; a folder of our own only where none is named."""
    d = spark.conf.get("spark.checkpoint.dir", None)
    if not d:
        d = spark.sparkContext.getCheckpointDir()
    if not d:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        d = tempfile.mkdtemp(prefix="ctxviews-")
        spark.sparkContext.setCheckpointDir(d)
    return d.rstrip("/")


@contextlib.contextmanager
def tidy(spark: SparkSession):
    """Queries planned here delete their shuffle files as they end; otherwise these stay until the driver's
    collector happens to find them, and add up on disk.  Only for writes, whose plans nothing runs again."""
    old = spark.conf.get(CLEANUP, "false")
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.set(CLEANUP, old)


def keep(df: DataFrame, spark: SparkSession, **options: str) -> DataFrame:
    """Write to the shared folder and read again: cuts lineage, survives lost executors."""
    path = f"{scratch_dir(spark)}/ctxviews-{uuid.uuid4().hex}"
    with tidy(spark):
        df.write.options(compression="zstd", **options).parquet(path)
    if not _scratch:
        atexit.register(clear)
    _scratch.append((spark, path))
    out = spark.read.schema(df.schema).parquet(path)
    out._ctxviews_path = path
    return out


def release(spark: SparkSession, *dfs: DataFrame) -> None:
    """Delete tables of keep() that nothing reads any more."""
    for df in dfs:
        path = getattr(df, "_ctxviews_path", None)
        if path:
            _delete(spark, path)
            _scratch[:] = [x for x in _scratch if x[1] != path]


def _delete(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def clear() -> None:
    for spark, path in _scratch:
        try:
            _delete(spark, path)
        except Exception:  # the session may be gone at exit
            break
    _scratch.clear()


def _width(kind: T.DataType, c) -> object:
    """Bytes of a value as an expression, never less than it takes in a row."""
    if isinstance(kind, T.StringType):
        return 16 + F.coalesce(F.octet_length(c), F.lit(0))
    if isinstance(kind, T.BinaryType):
        return 16 + F.coalesce(F.octet_length(c), F.lit(0))
    if isinstance(kind, T.ArrayType):
        inner = kind.elementType
        if isinstance(inner, T.NumericType):
            return 24 + F.greatest(F.size(c), F.lit(0)) * (4 if isinstance(inner, (T.IntegerType, T.FloatType)) else 8)
        if isinstance(inner, T.StructType) and not any(isinstance(f.dataType, (T.StringType, T.BinaryType, T.ArrayType, T.MapType, T.StructType)) for f in inner.fields):
            return 24 + F.greatest(F.size(c), F.lit(0)) * (16 + 8 * len(inner.fields))
        return 24 + F.coalesce(F.aggregate(c, F.lit(0).cast("long"), lambda s, x: s + _width(inner, x)), F.lit(0).cast("long"))
    if isinstance(kind, T.StructType):
        return sum((_width(f.dataType, c[f.name]) for f in kind.fields), F.lit(24))
    return F.lit(8)


def small(df: DataFrame, spark: SparkSession, limit: int = BROADCAST_BYTES) -> DataFrame:
    """df with a broadcast hint if its rows are counted to take at most `limit` bytes, else as it is."""
    row = sum((_width(f.dataType, F.col(f.name)) for f in df.schema.fields), F.lit(24)).cast("long")
    return F.broadcast(df) if (df.agg(F.sum(row)).first()[0] or 0) <= limit else df


# --- text kernels --------------------------------------------------------------------------

SPACE = np.zeros(256, bool)
SPACE[[9, 10, 11, 12, 13, 32]] = True
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BYTE = np.random.default_rng(20240607).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_powers: dict[str, np.ndarray] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """Spread 64-bit values (finaliser with two multiplications)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _powers or len(_powers["up"]) < n:
        size = max(n, 1 << 16)
        inverse = pow(int(_BASE), -1, 1 << 64)
        with np.errstate(over="ignore"):
            for name, b in (("up", int(_BASE)), ("down", inverse)):
                a = np.full(size, b, np.uint64)
                a[0] = 1
                _powers[name] = np.multiply.accumulate(a)
    return _powers["up"][:n], _powers["down"][:n]


def prefix_hash(data: np.ndarray) -> np.ndarray:
    """P with P[i] the polynomial hash of data[:i] modulo 2**64, for bytes or other integers."""
    up, _ = powers(len(data) + 1)
    out = np.zeros(len(data) + 1, np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum((_BYTE[data] if data.dtype == np.uint8 else mix(data.astype(np.uint64) + np.uint64(1))) * up[:-1], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Hashes of data[start:end]; equal strings have equal hashes wherever they stand."""
    _, down = powers(len(prefix))
    with np.errstate(over="ignore"):
        return mix((prefix[end] - prefix[start]) * down[start] + (end - start).astype(np.uint64))


def trim() -> None:
    """Give memory that a worker has freed back to the machine; workers live as long as their executor."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library keeps its own ways
        pass


def steps(texts: list[str | None], limit: int = STEP_BYTES):
    """Slices of a batch whose texts together have about `limit` bytes: (first, encoded texts)."""
    first, held, size = 0, [], 0
    for i, t in enumerate(texts):
        b = t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b""
        if held and size + len(b) > limit:
            yield first, held
            first, held, size = i, [], 0
        held.append(b)
        size += len(b)
    if held:
        yield first, held
    trim()


def words(encoded: list[bytes], lower: bool = True) -> tuple[np.ndarray, ...]:
    """Words of several texts at once: (buffer, start, end, number of text, hash)."""
    buf = np.frombuffer(b"\n".join(encoded), np.uint8)
    if lower:
        buf = LOWER[buf]
    size = np.fromiter(map(len, encoded), np.int64, len(encoded))
    first = np.concatenate([[0], np.cumsum(size + 1)[:-1]]).astype(np.int64)
    inside = np.concatenate([[False], ~SPACE[buf], [False]])
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    start, end = edge[::2], edge[1::2]
    doc = np.searchsorted(first, start, "right") - 1
    return buf, start, end, doc, span_hash(prefix_hash(buf), start, end)


def shingles(encoded: list[bytes], size: int = 5) -> list[np.ndarray]:
    """Sorted distinct word-shingle hashes of each text."""
    _, _, _, doc, h = words(encoded)
    n = np.bincount(doc, minlength=len(encoded))
    at = np.concatenate([[0], np.cumsum(n)])
    with np.errstate(over="ignore"):
        roll = np.zeros(max(0, len(h) - size + 1), np.uint64)
        for k in range(size):
            roll = roll * _BASE + h[k : k + len(roll)]
        roll = mix(roll + np.uint64(size))
    out = []
    for i, k in enumerate(n):
        a = at[i]
        if k >= size:
            out.append(np.unique(roll[a : a + k - size + 1]))
        elif k:
            x = np.uint64(0)
            with np.errstate(over="ignore"):
                for w in h[a : a + k]:
                    x = x * _BASE + w
                out.append(mix(np.array([x + np.uint64(k)], np.uint64)))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


# --- bounded labelled samples ----------------------------------------------------------------


def sample_rows(df: DataFrame, key: str, rows: int) -> DataFrame:
    """About `rows` rows of df, the same for the same rows (hash of the key); all if there are fewer."""
    n = df.count()
    if n <= rows:
        return df
    part = max(1, int(rows / n * (1 << 30)))
    return df.filter(F.pmod(F.xxhash64(F.lit("sample"), F.col(key)), F.lit(1 << 30)) < part)


# --- connected components --------------------------------------------------------------------


def components(edges: DataFrame, spark: SparkSession, finish: int = FINISH_EDGES) -> DataFrame:
    """(node, component) for every node of edges (src, dst): the least node reachable.

    Alternating star contraction: each round hooks larger neighbours, then smaller
    ones, to the least known node, so long chains end after a logarithmic number of
    rounds; it goes on until no edge changes.  A round deals the edges twice and
    writes one table to the shared folder.  `finish` edges at most, here or after a
    round, are joined in one task.
    """
    e = edges.select(F.greatest("src", "dst").alias("u"), F.least("src", "dst").alias("v")).filter("u > v")
    w = W.partitionBy("u").orderBy("v")
    state = lambda x: x.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    old, now = None, state(e)
    while now != old:
        if now[0] <= finish:
            return e.coalesce(1).mapInPandas(_joined, "node long, component long")
        # Equal edges stand side by side, so the windows leave them out; the first neighbour is the least.
        once = lambda x: x.withColumn("m", F.first("v").over(w)).withColumn("last", F.lag("v").over(w)).filter("last is null or last <> v")
        both = once(e.union(e.select("v", "u")))
        large = both.withColumn("m", F.least("u", "m")).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        less = once(large)
        star = less.select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v")
        new = keep(star.filter("u > v").distinct(), spark)
        if old is not None:
            release(spark, e)
        e, old, now = new, now, state(new)
    return e.groupBy(F.col("u").alias("node")).agg(F.min("v").alias("component")).union(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _joined(batches):
    """Components of all edges of a task: roots are hooked to the least root they meet, paths halved."""
    import pandas as pd

    parts = [(b["u"].to_numpy(), b["v"].to_numpy()) for b in batches]
    if not parts:
        return
    u, v = (np.concatenate(x) for x in zip(*parts, strict=True))
    nodes, at = np.unique(np.concatenate([u, v]), return_inverse=True)
    a, b, up = at[: len(u)], at[len(u) :], np.arange(len(nodes))
    while True:
        x, y = up[a], up[b]
        apart = x != y
        if not apart.any():
            break
        np.minimum.at(up, np.maximum(x, y)[apart], np.minimum(x, y)[apart])
        while (up[up] != up).any():
            up = up[up]
        a, b = a[apart], b[apart]
    for k in range(0, len(nodes), 100_000):
        yield pd.DataFrame({"node": nodes[k : k + 100_000], "component": nodes[up[k : k + 100_000]]})
