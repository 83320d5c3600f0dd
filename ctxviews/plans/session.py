"""Entry points: a Spark session for the engine, and the three exclusive ways to connect."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ctxviews.plans import catalog as cat


def spark_session(app: str = "ctxviews", **conf: str) -> SparkSession:
    b = SparkSession.builder.appName(app).config("spark.sql.session.timeZone", "UTC").config("spark.sql.adaptive.enabled", "true").config("spark.sql.adaptive.skewJoin.enabled", "true")
    for k, v in conf.items():
        b = b.config(k, v)
    return b.getOrCreate()


@dataclass
class Connection:
    mode: str
    handles: dict[str, DataFrame] = field(default_factory=dict)
    warnings: list[str] = field(default_factory=list)


def connect(spark: SparkSession, *, repo: tuple | None = None, views: dict[str, DataFrame] | None = None, catalog: tuple | None = None) -> Connection:
    """Exactly one of: repo=(root, version, builders) may build and caches by version;
    views=handles; catalog=(root, version, needs[, head]) never builds."""
    given = [m for m, x in (("repo", repo), ("views", views), ("catalog", catalog)) if x is not None]
    if len(given) != 1:
        raise ValueError(f"give exactly one of repo, views, catalog, not {given or 'none'}")
    if views is not None:
        return Connection("views", dict(views))
    if repo is not None:
        root, version, builders = repo
        try:
            entries = cat.read(root, version)
        except cat.ViewUnavailable:
            entries = cat.materialize(root, version, builders)
        return Connection("repo", {e.view: spark.read.parquet(e.location) for e in entries if e.status == "ok"})
    handles, warnings = cat.open_views(spark, *catalog)
    return Connection("catalog", handles, warnings)
