"""The request and edit feed over `events`: each function takes a batch or a stream (late() a batch, lag_stream() a stream).

Watermarks only matter on streams; a drained stream equals the batch result but
for rows that are later than the watermark.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.operators import maintain as maintain_ops
from ctxviews.plans import store

DELAY = "30 minutes"


def _marked(e: DataFrame) -> DataFrame:
    return e.withWatermark("ts", DELAY) if e.isStreaming else e


def tumbling(e: DataFrame) -> DataFrame:
    """event_type, start (epoch seconds), n, cost for each hour."""
    w = F.window("ts", "1 hour")
    return _marked(e).groupBy("event_type", w).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("cost")).select("event_type", F.unix_seconds("window.start").alias("start"), "n", "cost")


def sliding(e: DataFrame) -> DataFrame:
    w = F.window("ts", "1 hour", "15 minutes")
    return _marked(e).groupBy("event_type", w).agg(F.count("*").alias("n")).select("event_type", F.unix_seconds("window.start").alias("start"), "n")


def sessions(e: DataFrame) -> DataFrame:
    """user_id, start, n: agent sessions with gaps under thirty minutes."""
    w = F.session_window("ts", "30 minutes")
    return _marked(e).groupBy("user_id", w).agg(F.count("*").alias("n")).select("user_id", F.unix_seconds("session_window.start").alias("start"), "n")


def deduplicated(e: DataFrame) -> DataFrame:
    d = _marked(e).dropDuplicatesWithinWatermark(["event_id"]) if e.isStreaming else e.dropDuplicates(["event_id"])
    return d.select("event_id", "user_id")


def clicks_after_signup(e: DataFrame, again: DataFrame) -> DataFrame:
    """click, signup: clicks within an hour after a signup of the same user."""
    c = _marked(e).filter("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u1"), F.col("ts").alias("t1"))
    s = _marked(again.withColumnRenamed("ts", "ts")).filter("event_type = 'signup'").select(F.col("event_id").alias("signup"), F.col("user_id").alias("u2"), F.col("ts").alias("t2"))
    return c.join(s, F.expr("u1 = u2 and t1 >= t2 and t1 <= t2 + interval 1 hour")).select("click", "signup")


def late(e: DataFrame) -> DataFrame:
    """n, late: rows that come, in event_id order, more than the delay behind the newest row before them.

    The running maximum goes through hourly blocks of ids, so no single task sees all rows.
    """
    block = F.floor(F.col("event_id") / 4096)
    tops = e.groupBy(block.alias("block")).agg(F.max("ts").alias("top"))
    before = tops.withColumn("carried", F.max("top").over(W.orderBy("block").rowsBetween(W.unboundedPreceding, -1))).select("block", "carried")
    w = W.partitionBy("block").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1)
    x = e.withColumn("block", block).withColumn("own", F.max("ts").over(w)).join(before, "block")
    seen = F.greatest("own", "carried")
    return x.agg(F.count("*").alias("n"), F.count_if(F.coalesce(F.col("ts") < seen - F.expr(f"interval {DELAY}"), F.lit(False))).alias("late"))


def lag(e: DataFrame) -> DataFrame:
    """user_id, head (edits so far), built (edits up to the user's last view): the version lag of each user's views."""
    last = F.max(F.when(F.col("event_type") == "view", F.col("ts"))).over(W.partitionBy("user_id"))
    p = F.col("event_type") == "purchase"
    return e.withColumn("vt", last).groupBy("user_id").agg(F.count_if(p).alias("head"), F.count_if(p & (F.col("ts") <= F.col("vt"))).alias("built"))


IDLE_MS = 90 * 24 * 3600 * 1000


def lag_stream(e: DataFrame) -> DataFrame:
    """The same lag on a stream that follows time: user_id, head, built, ended, put out whenever a user's state
    changes.  A user who is idle for IDLE_MS of event time is put out once more, ended, and forgotten."""
    import pandas as pd

    def step(key, batches, state):
        if state.hasTimedOut:
            head, built = state.get
            state.remove()
            yield pd.DataFrame({"user_id": [key[0]], "head": [head], "built": [built], "ended": [True]})
            return
        head, built = state.get if state.exists else (0, 0)
        rows = pd.concat(list(batches)).sort_values(["ts", "event_type"], kind="stable")  # at one time a purchase comes before a view
        for kind in rows["event_type"]:
            if kind == "purchase":
                head += 1
            elif kind == "view":
                built = head
        state.update((head, built))
        last = int(rows["ts"].max().timestamp() * 1000)
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs()) + IDLE_MS)
        yield pd.DataFrame({"user_id": [key[0]], "head": [head], "built": [built], "ended": [False]})

    own = _marked(e.select("user_id", "event_type", "ts"))
    return own.groupBy("user_id").applyInPandasWithState(step, "user_id long, head long, built long, ended boolean", "head long, built long", "update", "EventTimeTimeout")


def stream(spark: SparkSession, path: str, schema) -> DataFrame:
    """A file stream over event files."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def drain(out: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream until its files are used up and return what it put out."""
    q = out.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return out.sparkSession.table(name)


def maintain(edits: DataFrame, apply: Callable[[DataFrame, int], None], checkpoint: str):
    """Incremental maintenance for each micro-batch.  `apply(batch, id)` must give the same when it is run
    again with the same id: a crash between it and the mark beside the checkpoint repeats it."""
    spark, mark = edits.sparkSession, f"{checkpoint.rstrip('/')}/applied"

    def once(batch: DataFrame, number: int) -> None:
        done = store.read_text(spark, mark)
        if done is not None and int(done) >= number:
            return
        apply(batch, number)
        store.write_text(spark, mark, str(number))

    return edits.writeStream.foreachBatch(once).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


class GraphMaintainer:
    """Versions of a graph under `root`, each patched from the last by a batch of edits (repo, lang, path, lines or null).

    Version n + 1 comes from batch n and is written in one place, so a repeated batch
    writes the same version again; a version counts when its mark is there.
    """

    TABLES = ("files", "tokens", "decl", "refs", "imports")

    def __init__(self, spark: SparkSession, root: str):
        self.spark, self.root = spark, root.rstrip("/")

    def _at(self, version: int, name: str) -> str:
        return f"{self.root}/v{version}/{name}"

    def read(self, version: int) -> tuple[DataFrame, maintain_ops.Graph]:
        """(texts, graph) of a version."""
        if not store.exists(self.spark, self._at(version, "done")):
            raise ValueError(f"version {version} is not complete")
        g = maintain_ops.Graph(*(self.spark.read.parquet(self._at(version, t)) for t in self.TABLES))
        return self.spark.read.parquet(self._at(version, "texts")), g

    def _write(self, version: int, texts: DataFrame, g: maintain_ops.Graph) -> None:
        for name, df in (("texts", texts), *((t, getattr(g, t)) for t in self.TABLES)):
            df.write.mode("overwrite").parquet(self._at(version, name))
        store.write_text(self.spark, self._at(version, "done"), "")

    def start(self, texts: DataFrame) -> None:
        """Version 0 is built from all texts."""
        self._write(0, texts, maintain_ops.rebuild(texts, store.kept))

    def apply(self, batch: DataFrame, number: int) -> None:
        """Patch version `number` by a batch; each path at most once, null lines delete."""
        texts, g = self.read(number)
        edits = store.kept(batch.select("repo", "lang", "path", "lines"))
        key = ["repo", "lang", "path"]
        old, new = texts.join(edits.select(key), key, "left_semi"), edits.filter("lines is not null")
        t = maintain_ops.Transition.of(old, new, g, store.kept)
        now = texts.join(edits.select(key), key, "left_anti").unionByName(new)
        self._write(number + 1, now, maintain_ops.repair(t, True, store.kept))
