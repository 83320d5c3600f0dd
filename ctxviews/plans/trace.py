"""An ordered ledger of events: view, provider, token usage."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SCHEMA = "seq long, at double, session string, event string, view string, provider string, prompt_tokens long, completion_tokens long"


class Trace:
    def __init__(self, session: str):
        self.session, self.rows, self.seq = session, [], 0

    def add(self, event: str, view: str | None = None, provider: str | None = None, prompt: int = 0, completion: int = 0) -> None:
        self.rows.append((self.seq, time.time(), self.session, event, view, provider, prompt, completion))
        self.seq += 1

    def append(self, spark: SparkSession, path: str) -> DataFrame:
        """Write the events so far behind those of earlier calls."""
        df = spark.createDataFrame(self.rows, SCHEMA)
        df.write.mode("append").parquet(path)
        self.rows = []
        return df


def extend(events: DataFrame, path: str, order: str) -> None:
    """Append the events of many sessions (session, event, view, provider, prompt_tokens, completion_tokens, `order`)
    to the ledger at path: a session's numbers go on behind those that it has there."""
    from ctxviews.plans import store

    spark = events.sparkSession
    new = events.withColumn("seq", (F.row_number().over(W.partitionBy("session").orderBy(order)) - 1).cast("long")).withColumn("at", F.unix_micros(F.current_timestamp()) / 1e6)
    if store.exists(spark, path):
        had = spark.read.schema(SCHEMA).parquet(path).groupBy("session").agg(F.count("*").alias("had"))
        new = new.join(had, "session", "left").withColumn("seq", F.col("seq") + F.coalesce("had", F.lit(0)))
    names = [c.split()[0] for c in SCHEMA.split(", ")]
    new.select(names).write.mode("append").parquet(path)
