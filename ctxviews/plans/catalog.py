"""Identities, catalog entries and view access.

A catalog is a small table with one row for each (version, view, profile).
Builders run one after another; a failure becomes a `failed` entry and leaves the
others alone; the catalog is published by one rename after all have ended.
Opening never builds.  Files go through Hadoop's file systems, so a catalog can lie
wherever Spark reads.
"""

from __future__ import annotations

import json
import time
from collections.abc import Callable
from dataclasses import asdict, dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxviews.functions.text import digest
from ctxviews.plans import store

SCHEMA_VERSION = 1
#: Capabilities of each view; syntactic ones need no resolved symbols.
CAPABILITIES = {"lexical": ["text_search"], "dense": ["semantic_search"], "structural": ["definition", "neighbours", "references"]}
SYNTACTIC = {"text_search", "semantic_search", "contain"}


class ViewUnavailable(RuntimeError):
    """A needed view is missing, failed or stale; nothing is substituted."""


class ViewSchemaMismatch(RuntimeError):
    """A stored view has another schema version: rebuild it."""


class BuildPreparationMissing(RuntimeError):
    """A builder lacks what it needs; weaker data is not published under its name."""


def source_id(repo: Column, version: Column) -> Column:
    return digest(repo, version)


def profile_id(language: Column, schema: str, backend: str, options: str) -> Column:
    return digest(language, F.lit(schema), F.lit(backend), F.lit(options))


def capabilities(entries: DataFrame, by: list[str]) -> DataFrame:
    """Sorted capabilities of the entries that are ok."""
    pairs = entries.sparkSession.createDataFrame([(v, c) for v, cs in CAPABILITIES.items() for c in cs], "view string, capability string")
    return entries.filter("status = 'ok'").join(F.broadcast(pairs), "view").groupBy(*by).agg(F.array_sort(F.collect_set("capability")).alias("capabilities"))


def lag(versions: DataFrame) -> DataFrame:
    """How far a view's version is behind the head version."""
    return versions.withColumn("lag", F.col("head") - F.col("built"))


@dataclass
class Entry:
    view: str
    status: str
    location: str | None = None
    seconds: float = 0.0
    built_at: float = 0.0
    schema_version: int = SCHEMA_VERSION
    config: dict = field(default_factory=dict)
    capabilities: list = field(default_factory=list)
    error: str | None = None


def materialize(root: str, version: str, builders: dict[str, Callable[[str], dict | None]], needs: dict[str, list[str]] | None = None) -> list[Entry]:
    """Run builders(location) in order; returns and publishes their entries."""
    out: list[Entry] = []
    for view, build in builders.items():
        began = time.time()
        location = f"{root.rstrip('/')}/{version}/{view}"
        try:
            config = build(location) or {}
            out.append(Entry(view, "ok", location, time.time() - began, time.time(), config=config, capabilities=CAPABILITIES.get(view, [])))
        except Exception as e:  # siblings go on
            out.append(Entry(view, "failed", None, time.time() - began, time.time(), error=f"{type(e).__name__}: {e}"))
    publish(root, version, out)
    return out


def _path(root: str, version: str) -> str:
    return f"{root.rstrip('/')}/{version}/catalog.json"


def publish(root: str, version: str, entries: list[Entry]) -> None:
    store.write_text(SparkSession.active(), _path(root, version), json.dumps([asdict(e) for e in entries]))


def read(root: str, version: str) -> list[Entry]:
    text = store.read_text(SparkSession.active(), _path(root, version))
    if text is None:
        raise ViewUnavailable(f"no catalog for {version}")
    return [Entry(**e) for e in json.loads(text)]


#: Columns that a view is made of; a builder without them must fail.
PREPARED = {"lexical": ["unit_id", "text"], "dense": ["unit_id", "text"], "structural": ["path", "line", "col", "symbol", "role"]}


def builder(view: str, prepared: DataFrame | None, make: Callable[[DataFrame], DataFrame]) -> Callable[[str], dict]:
    """A builder for materialize() that publishes make(prepared), and fails if its preparation is absent or
    lacks what the view's capabilities rest on: nothing weaker goes out under the same name."""

    def build(location: str) -> dict:
        missing = PREPARED[view] if prepared is None else [c for c in PREPARED[view] if c not in prepared.columns]
        if missing:
            raise BuildPreparationMissing(f"{view} needs {', '.join(missing)}")
        make(prepared).write.mode("overwrite").parquet(location)
        return {"columns": prepared.columns}

    return build


def alias(instances: DataFrame) -> DataFrame:
    """instances (instance, source_id, profile_id) with `canonical`: instance names only stand for an identity,
    the first of them speaks for all."""
    from pyspark.sql import Window as W

    return instances.withColumn("canonical", F.min("instance").over(W.partitionBy("source_id", "profile_id")))


def open_views(spark: SparkSession, root: str, version: str, needs: list[str], head: str | None = None) -> tuple[dict[str, DataFrame], list[str]]:
    """(handles of the needed views, warnings).  Reads metadata only; never builds."""
    entries = {e.view: e for e in read(root, version)}
    handles, warnings = {}, []
    for view in needs:
        e = entries.get(view)
        if e is None or e.status != "ok":
            raise ViewUnavailable(f"{view}: {e.error if e else 'not in the catalog'}")
        if e.schema_version != SCHEMA_VERSION:
            raise ViewSchemaMismatch(f"{view} has schema {e.schema_version}, this engine {SCHEMA_VERSION}: rebuild it")
        if head is not None and head != version:
            warnings.append(f"{view} is of {version}, head is {head}")
        handles[view] = spark.read.parquet(e.location)
    return handles, warnings


#: Backends by purpose, chosen for each kind of file on its own.
class BackendRegistry:
    TIERS = {"documents": "occurrence", "pages": "markup", "benchmark": "text_only", "conversations": "text_only"}
    BACKENDS = {
        ("occurrence", "chunk"): "lines", ("occurrence", "graph"): "occurrences", ("occurrence", "incremental"): "closure", ("occurrence", "live"): "scan",
        ("markup", "chunk"): "elements", ("markup", "graph"): "href", ("markup", "incremental"): "file", ("markup", "live"): "scan",
        ("text_only", "chunk"): "lines",
    }

    @classmethod
    def pick(cls, source: str, purpose: str) -> str:
        tier = cls.TIERS[source]
        if (tier, purpose) not in cls.BACKENDS:
            raise BuildPreparationMissing(f"{source} has no {purpose} backend")
        return cls.BACKENDS[tier, purpose]
