"""Materialized views: built once for each state of the base tables, then only read.

A view is a Parquet table in the cluster's shared folder whose name is a digest of
the application, the view's name and parameters, and the state (path, length, time)
of the base files; changed base data give another name.  A view that is not complete
(no success mark) is built again, so a lost run leaves nothing half-built behind.
"""

from __future__ import annotations

import atexit
import hashlib
import tempfile
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Build seconds and stored bytes by (view, parameters), in order of building.
LEDGER: list[dict] = []
_known: dict[tuple, DataFrame] = {}
_written: list[tuple[SparkSession, str]] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; one of our own only on a single machine."""
    d = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not d:
        if not spark.sparkContext.master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        d = tempfile.mkdtemp(prefix="ctxviews-views-")
        spark.sparkContext.setCheckpointDir(d)
    return d.rstrip("/")


def _fs(spark: SparkSession, path: str):
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), p


def state(spark: SparkSession, path: str) -> str:
    """Names, lengths and times of the files under a path, through Hadoop's file systems."""
    fs, p = _fs(spark, path)
    if not fs.exists(p):
        return "none"
    found, files = fs.listFiles(p, True), []
    while found.hasNext():
        s = found.next()
        files.append(f"{s.getPath().getName()}|{s.getLen()}|{s.getModificationTime()}")
    return "\n".join(sorted(files))


def size_of(spark: SparkSession, path: str) -> int:
    fs, p = _fs(spark, path)
    return int(fs.getContentSummary(p).getLength())


def stored(spark: SparkSession, sf_dir: str, name: str, build: Callable[[], DataFrame], tables: tuple[str, ...] = ("documents",), by: list[str] | None = None) -> DataFrame:
    """The view `name` over base tables of sf_dir; `build` runs only if it is not there.

    by: the view is dealt and sorted by these columns, so that filters on them skip row groups.
    """
    app = spark.sparkContext.applicationId
    key = (app, sf_dir, name, *(state(spark, f"{sf_dir}/{t}.parquet") for t in tables))
    if key in _known and _known[key].sparkSession is spark:
        return _known[key]
    path = f"{shared_dir(spark)}/ctxviews-view-{hashlib.sha256(chr(31).join(key).encode()).hexdigest()[:24]}"
    fs, done = _fs(spark, f"{path}/_SUCCESS")
    if not fs.exists(done):
        began = time.time()
        df = build()
        if by:
            df = df.repartition(*by).sortWithinPartitions(*by)
        df.write.mode("overwrite").option("compression", "zstd").parquet(path)
        LEDGER.append({"view": name, "seconds": round(time.time() - began, 3), "bytes": size_of(spark, path)})
        if not _written:
            atexit.register(clear)
        _written.append((spark, path))
    _known[key] = spark.read.parquet(path)
    return _known[key]


def kept(df: DataFrame) -> DataFrame:
    """df written to the shared folder and read again: a cut in the lineage that outlives executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/ctxviews-kept-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    if not _written:
        atexit.register(clear)
    _written.append((spark, path))
    return spark.read.schema(df.schema).parquet(path)


def path_of(df: DataFrame) -> str:
    """The folder of a table that kept() has written."""
    return df.inputFiles()[0].rsplit("/", 1)[0]


def drop(*own: DataFrame) -> None:
    """Delete tables of kept() that nothing reads any more, before the process ends."""
    for df in own:
        name = path_of(df).rsplit("/", 1)[1]
        for spark, path in [x for x in _written if x[1].rsplit("/", 1)[1] == name]:
            fs, p = _fs(spark, path)
            fs.delete(p, True)
            _written.remove((spark, path))


#: Bytes of rows up to which a kept table goes to every task.
FEW = 48 << 20


def few(df: DataFrame, limit: int = FEW) -> DataFrame:
    """df kept, with a broadcast hint if its rows are counted to take at most `limit` bytes: the other side of its joins stays where it lies."""
    own = kept(df)
    row = sum((F.coalesce(F.octet_length(F.col(c).cast("string")), F.lit(0)) for c in own.columns), F.lit(24)).cast("long")
    return F.broadcast(own) if (own.agg(F.sum(row)).first()[0] or 0) <= limit else own


def write_text(spark: SparkSession, path: str, text: str) -> None:
    """Publish a small file at once: written beside its place, then renamed over it."""
    fs, p = _fs(spark, path)
    draft = _fs(spark, f"{path}.draft-{uuid.uuid4().hex}")[1]
    out = fs.create(draft, True)
    out.write(bytearray(text, "utf-8"))
    out.close()
    if fs.exists(p):
        fs.delete(p, False)
    if not fs.rename(draft, p):
        raise OSError(f"{path} could not be published")


def read_text(spark: SparkSession, path: str) -> str | None:
    """The text of a small file, or None if it is not there."""
    fs, p = _fs(spark, path)
    if not fs.exists(p):
        return None
    stream = fs.open(p)
    try:
        return spark.sparkContext._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
    finally:
        stream.close()


def exists(spark: SparkSession, path: str) -> bool:
    fs, p = _fs(spark, path)
    return bool(fs.exists(p))


def clear() -> None:
    """Delete what this process has stored."""
    _known.clear()
    for spark, path in _written:
        try:
            fs, p = _fs(spark, path)
            fs.delete(p, True)
        except Exception:  # the session may be gone at exit
            break
    _written.clear()
