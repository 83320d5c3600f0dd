"""URL filter: host and path rules first, gradient-boosted trees for the rest.

Rules are matched by expressions alone.  Trees learn from labelled URLs - by
default those that a rule decides - on lexical features: lengths, path depth,
digit ratio, character entropy, parameter counts and the block rates of host
suffixes among the labelled URLs.  Training takes a bounded sample of labelled
rows (TRAIN_ROWS).

A null url, or one without `://`, has an empty host and path, fits no rule and is
judged by the trees on its (empty) text.  With labels of one kind only, that kind
is the verdict; with none, every verdict is allow.  A score of exactly 0.5 blocks; of
rules that fit, the longest wins.  Repeated rows are judged each and alike, null ids
are carried, an empty table gives no rows; no other column is read.

A labelled URL learns from host suffix rates of the other FOLDS - 1 parts of the labelled
URLs (dealt by hash of the host), so that a suffix tells the trees no more about a URL
than it will about an unknown one.
"""

from __future__ import annotations

import math
import zlib
from collections import Counter
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import sample_rows, ship

TRAIN_ROWS = 20_000
FOLDS = 5
#: (verdict, rule): a rule is a host and the start of a path.
RULES = [("block", "com/en/"), ("allow", "example.com/en/7"), ("allow", "net/de/"), ("block", "example.net/de/8"), ("block", "org/es/")]


def host_of(url: Column) -> Column:
    rest = F.when(F.instr(url, "://") > 0, F.expr(f"substr({_name(url)}, instr({_name(url)}, '://') + 3)")).otherwise("")
    return F.translate(F.regexp_extract(rest, r"(?s)^([^/?#]*)", 1), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def path_of(url: Column) -> Column:
    rest = F.when(F.instr(url, "://") > 0, F.expr(f"substr({_name(url)}, instr({_name(url)}, '://') + 3)")).otherwise("")
    return F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)


def _name(url: Column) -> str:
    return "`ctxviews_url`"


def rule_of(host: Column, path: Column, rules: list[tuple[str, str]]) -> Column:
    """struct(rule, verdict) of the longest rule that fits, else null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rule in sorted(rules, key=lambda r: (len(r[1]), r[1])):
        h, slash, p = rule.partition("/")
        fits = ((host == h) | host.endswith("." + h)) & path.startswith(slash + p)
        out = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


# --- features ----------------------------------------------------------------------------------


def suffixes(host: str) -> tuple[str, str]:
    parts = host.rsplit(".", 2)
    return parts[-1], ".".join(parts[-2:])


def lexical(url: str | None, host: str, path: str) -> list[float]:
    u = url or ""
    n = max(1, len(u))
    query = u.partition("?")[2].partition("#")[0]
    counts = Counter(u)
    return [
        len(u), len(host), len(path), path.count("/"), host.count("."), sum(map(u.count, "0123456789")) / n,
        -sum(c / n * math.log2(c / n) for c in counts.values()), query.count("=") , query.count("&"), len(query), float("#" in u),
        sum(map(host.count, "0123456789")), host.count("-"), max(map(len, path.split("/")), default=0), float("." in path.rsplit("/", 1)[-1]), float(u.startswith("https")), len(path.split("/")[1]) if path.count("/") else 0,
    ]


@dataclass
class Boosted:
    """Histogram gradient boosting of depth-limited trees with logistic loss."""

    base: float = 0.0
    rate: float = 0.3
    trees: list[list[tuple]] = field(default_factory=list)
    edges: list[np.ndarray] = field(default_factory=list)

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray, rounds: int = 40, depth: int = 4, bins: int = 32) -> Boosted:
        share = y.mean() if len(y) else 0.0
        out = cls(base=float(np.log((share + 1e-4) / (1 - share + 1e-4))))
        if not 0 < share < 1:
            return out
        out.edges = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, bins + 1)[1:-1])) for j in range(x.shape[1])]
        b = np.stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(out.edges)], 1)
        f = np.full(len(y), out.base)
        for _ in range(rounds):
            p = 1 / (1 + np.exp(-f))
            g, h = y - p, p * (1 - p) + 1e-9
            leaf, tree = np.zeros(len(y), np.int64), []
            for _level in range(depth):
                width = leaf.max() + 1
                best = [(1e-6, -1, 0)] * width
                for j in range(x.shape[1]):
                    cell = leaf * (bins + 1) + b[:, j]
                    gs = np.bincount(cell, g, width * (bins + 1)).reshape(width, -1).cumsum(1)
                    hs = np.bincount(cell, h, width * (bins + 1)).reshape(width, -1).cumsum(1)
                    gain = gs[:, :-1] ** 2 / (hs[:, :-1] + 1) + (gs[:, -1:] - gs[:, :-1]) ** 2 / (hs[:, -1:] - hs[:, :-1] + 1) - gs[:, -1:] ** 2 / (hs[:, -1:] + 1)
                    at = gain.argmax(1)
                    for k in range(width):
                        if gain[k, at[k]] > best[k][0] + 1e-9:
                            best[k] = (float(gain[k, at[k]]), j, int(at[k]))
                feature = np.array([t[1] for t in best])
                cut = np.array([t[2] for t in best])
                right = (feature[leaf] >= 0) & (b[np.arange(len(b)), feature[leaf]] > cut[leaf])
                tree.append((feature, cut))
                leaf = leaf * 2 + right
            size = 1 << depth
            value = np.bincount(leaf, g, size) / (np.bincount(leaf, h, size) + 1) * out.rate
            out.trees.append([*tree, value])
            f = f + value[leaf]
        return out

    def margin(self, x: np.ndarray) -> np.ndarray:
        f = np.full(len(x), self.base)
        if self.trees:
            b = np.stack([np.searchsorted(e, x[:, j], "left") for j, e in enumerate(self.edges)], 1)
            row = np.arange(len(b))
            for *levels, value in self.trees:
                leaf = np.zeros(len(b), np.int64)
                for feature, cut in levels:
                    leaf = leaf * 2 + ((feature[leaf] >= 0) & (b[row, feature[leaf]] > cut[leaf]))
                f += value[leaf]
        return f


def fold_of(host: str) -> int:
    return zlib.crc32(host.encode()) % FOLDS


@dataclass
class UrlModel:
    prior: float
    seen: dict[str, tuple[int, int]]  # blocked and all labelled URLs of a suffix
    folds: list[dict[str, tuple[int, int]]]
    trees: Boosted

    def rate(self, suffix: str, but: int | None = None) -> float:
        """Share of blocked URLs of a suffix, drawn to the prior; without those of fold `but`."""
        b, n = self.seen.get(suffix, (0, 0))
        if but is not None:
            less = self.folds[but].get(suffix, (0, 0))
            b, n = b - less[0], n - less[1]
        return (b + 5 * self.prior) / (n + 5)

    def features(self, urls, hosts, paths, labelled: bool = False) -> np.ndarray:
        return np.array([[*lexical(u, h, p), *(self.rate(s, fold_of(h) if labelled else None) for s in suffixes(h))] for u, h, p in zip(urls, hosts, paths, strict=True)], float).reshape(len(urls), -1)


def fit(urls: list[str | None], hosts: list[str], paths: list[str], blocked: np.ndarray) -> UrlModel:
    prior = float(blocked.mean()) if len(blocked) else 0.0
    seen: dict[str, tuple[int, int]] = {}
    folds: list[dict[str, tuple[int, int]]] = [{} for _ in range(FOLDS)]
    for h, b in zip(hosts, blocked.tolist(), strict=True):
        for s in set(suffixes(h)):
            for counts in (seen, folds[fold_of(h)]):
                x, n = counts.get(s, (0, 0))
                counts[s] = x + b, n + 1
    model = UrlModel(prior, seen, folds, Boosted())
    model.trees = Boosted.fit(model.features(urls, hosts, paths, True), blocked.astype(float)) if len(blocked) else Boosted(base=-9.0)
    return model


def judge(pages: DataFrame, spark: SparkSession, rules: list[tuple[str, str]] = RULES, id_col: str = "page_id", url_col: str = "url", rows: int = TRAIN_ROWS) -> DataFrame:
    """id_col, host, path, rule, verdict and the trees' block score for every row."""
    ship(spark)
    kind = dict(pages.dtypes)[id_col]
    url = pages.select(pages[id_col].alias("i"), pages[url_col].alias("ctxviews_url"))
    u = F.col("ctxviews_url")
    parts = url.select("i", u, F.coalesce(host_of(u), F.lit("")).alias("host"), F.coalesce(path_of(u), F.lit("")).alias("path"))
    ruled = parts.withColumn("r", rule_of(F.col("host"), F.col("path"), rules))
    got = sorted(sample_rows(ruled.filter("r is not null"), "i", rows).select("ctxviews_url", "host", "path", (F.col("r.verdict") == "block").alias("b")).collect(), key=str)
    model = fit([r.ctxviews_url for r in got], [r.host for r in got], [r.path for r in got], np.array([r.b for r in got], bool))
    shared = spark.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        for pdf in batches:
            x = m.features(pdf.pop("ctxviews_url").tolist(), pdf["host"].tolist(), pdf["path"].tolist())
            score = 1 / (1 + np.exp(-m.trees.margin(x)))
            verdict = pdf.pop("verdict").where(pdf["rule"].notna(), np.where(score >= 0.5, "block", "allow"))
            yield pdf.rename(columns={"i": id_col}).assign(verdict=verdict, block_score=score)

    return ruled.select("i", "ctxviews_url", "host", "path", "r.rule", "r.verdict").mapInPandas(run, f"`{id_col}` {kind}, host string, path string, rule string, verdict string, block_score double")
