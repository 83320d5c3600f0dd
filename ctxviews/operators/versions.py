"""Repository versions: content digests, edit scripts, changed files, line diffs."""

from __future__ import annotations

import bisect
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ctxviews.functions.ship import ship
from ctxviews.functions.text import md5_number


def digest_of(f: DataFrame) -> DataFrame:
    """repo, lang, n, digest: equal before and after a build if no file changed."""
    return f.groupBy("repo", "lang").agg(F.count("*").alias("n"), F.sum(md5_number(F.concat_ws("\x1f", "path", F.sha2("text", 256)))).alias("digest"))


STEPS = 5


def chosen_repos(f: DataFrame) -> DataFrame:
    """Two repositories for each language: the least md5 of the source."""
    from pyspark.sql import Window as W

    r = f.select("repo", "lang").distinct()
    return r.withColumn("n", F.row_number().over(W.partitionBy("lang").orderBy(F.md5("repo")))).filter("n <= 2").select("repo", "lang")


def evolve(f: DataFrame, steps: int = STEPS, every: int = 1, whole: bool = False) -> DataFrame:
    """repo, lang, step, path, lines for versions 0 .. steps of the chosen repositories, or of all (whole).

    In each step about one file in `every` follows the script; the others stay.

    Each base file follows a script given by hashes: replace, insert or delete a
    line, delete the file, or add a near copy.  A file's history is a chain of array
    expressions on its own row, so all versions come from one scan without a shuffle
    of text (the donor line comes from one window over the repository).
    """
    from pyspark.sql import Window as W

    base = (f if whole else f.join(chosen_repos(f), ["repo", "lang"])).select("repo", "lang", "doc_id", "path", F.split("text", "\n", -1).alias("l0"))
    w = W.partitionBy("repo", "lang").orderBy("doc_id")
    head = F.col("l0")[0]
    cur = base.withColumn("donor", F.coalesce(F.lead(head).over(w), F.first(head).over(w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing))))
    kind = "struct<l:array<string>,extra:array<struct<path:string,lines:array<string>>>,v:array<struct<step:int,path:string,lines:array<string>>>>"

    def step(acc: Column, t: Column) -> Column:
        h = md5_number(F.concat(F.col("doc_id").cast("string"), F.lit("|"), t.cast("string")))
        old, n, op = acc["l"], F.size(acc["l"]), h % 10
        if every > 1:
            op = F.when(md5_number(F.concat(t.cast("string"), F.lit("/"), F.col("doc_id").cast("string"))) % every == 0, op).otherwise(9)
        p = F.when(n > 0, F.floor(h / 10) % n).otherwise(0).cast("int")
        kept = F.when(op == 1, 0).otherwise(1)  # old lines that give way at p: none for an insertion
        put = F.when(op == 2, F.array().cast("array<string>")).otherwise(F.array("donor"))
        edit = F.concat(F.slice(old, 1, p), put, F.slice(old, p + 1 + kept, F.greatest(n - p - kept, F.lit(0))))
        new = F.when(old.isNull() | ((op == 3) & (h % 3 == 0)), None).when((op <= 1) | ((op == 2) & (n > 1)), edit).otherwise(old)
        more = F.when((op == 4) & old.isNotNull(), F.array(F.struct(F.concat("path", F.lit("_v"), t.cast("string")).alias("path"), F.concat(old, F.array("donor")).alias("lines")))).otherwise(F.array().cast("array<struct<path:string,lines:array<string>>>"))
        extra = F.concat(acc["extra"], more)
        now = F.concat(F.array(F.struct(t.alias("step"), F.col("path").alias("path"), new.alias("lines"))), F.transform(extra, lambda x: F.struct(t.alias("step"), x["path"].alias("path"), x["lines"].alias("lines"))))
        return F.struct(new.alias("l"), extra.alias("extra"), F.concat(acc["v"], now).alias("v")).cast(kind)

    first = F.struct(F.col("l0").alias("l"), F.array().cast("array<struct<path:string,lines:array<string>>>").alias("extra"), F.array(F.struct(F.lit(0).alias("step"), F.col("path").alias("path"), F.col("l0").alias("lines"))).alias("v")).cast(kind)
    out = cur.select("repo", "lang", F.explode(F.aggregate(F.sequence(F.lit(1), F.lit(steps)), first, step)["v"]).alias("x"))
    return out.select("repo", "lang", "x.step", "x.path", "x.lines").filter("lines is not null")


def transitions(v: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(old, new) files (repo, lang, path, lines) where repo names the transition: repo@step."""
    name = lambda s: F.concat("repo", F.lit("@"), s.cast("string"))
    old = v.filter(F.col("step") < STEPS).select(name(F.col("step") + 1).alias("repo"), "lang", "path", "lines")
    new = v.filter(F.col("step") > 0).select(name(F.col("step")).alias("repo"), "lang", "path", "lines")
    return old, new


def changed_files(old: DataFrame, new: DataFrame) -> DataFrame:
    """repo, lang, path, kind (added, deleted, modified): digests meet, texts do not."""
    h = lambda df, c: df.select("repo", "lang", "path", F.sha2(F.concat_ws("\n", "lines"), 256).alias(c))
    j = h(old, "a").join(h(new, "b"), ["repo", "lang", "path"], "full")
    return j.withColumn("kind", F.when(F.col("a").isNull(), "added").when(F.col("b").isNull(), "deleted").when(F.col("a") != F.col("b"), "modified")).filter("kind is not null").select("repo", "lang", "path", "kind")


def diff(a: list[str], b: list[str]) -> list[tuple[int, int, int, int]]:
    """Hunks (old start, old length, new start, new length) without context, in order and as early as they can be.

    Common ends are cut off first, the end before the start, so a hunk among equal
    lines slides up; what is left goes through a longest common subsequence.
    """
    hi = 0
    while hi < min(len(a), len(b)) and a[-1 - hi] == b[-1 - hi]:
        hi += 1
    lo = 0
    while lo < min(len(a), len(b)) - hi and a[lo] == b[lo]:
        lo += 1
    x, y = a[lo : len(a) - hi], b[lo : len(b) - hi]
    if not x and not y:
        return []
    if not x or not y or len(x) * len(y) == 1:
        return [(lo, len(x), lo, len(y))]
    out = []
    for o, n, i, m in _hunks(x, y):
        out.append((lo + o, n, lo + i, m))
    return out


#: Cells of a table of common lengths at most.
CELLS = 1_000_000


def _hunks(x: list[str], y: list[str]) -> list[tuple[int, int, int, int]]:
    """Hunks between two lists without common ends.

    Large ones are cut at lines that occur once on both sides, in their longest common
    order, so memory stays linear; without such lines they are one hunk.
    """
    if len(x) * len(y) <= CELLS:
        return _by_table(x, y)
    count_x, count_y = Counter(x), Counter(y)
    where = {v: j for j, v in enumerate(y) if count_y[v] == 1}
    both = [(i, where[v]) for i, v in enumerate(x) if count_x[v] == 1 and v in where]
    fixed = _rising(both)
    if not fixed:
        return [(0, len(x), 0, len(y))]
    out, i0, j0 = [], 0, 0
    for i, j in [*fixed, (len(x), len(y))]:
        out += [(i0 + o, n, j0 + p, m) for o, n, p, m in diff(x[i0:i], y[j0:j])]
        i0, j0 = i + 1, j + 1
    return out


def _rising(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """A longest run of pairs (sorted by the first place) whose second places rise."""
    ends: list[int] = []
    last: list[int] = []
    back: list[int] = []
    for n, (_, j) in enumerate(pairs):
        k = bisect.bisect_left(ends, j)
        ends[k : k + 1] = [j]
        last[k : k + 1] = [n]
        back.append(last[k - 1] if k else -1)
    out, n = [], last[-1] if last else -1
    while n >= 0:
        out.append(pairs[n])
        n = back[n]
    return out[::-1]


def _by_table(x: list[str], y: list[str]) -> list[tuple[int, int, int, int]]:
    best = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
    for i in range(len(x) - 1, -1, -1):
        for j in range(len(y) - 1, -1, -1):
            best[i][j] = best[i + 1][j + 1] + 1 if x[i] == y[j] else max(best[i + 1][j], best[i][j + 1])
    hunks, i, j = [], 0, 0
    while i < len(x) or j < len(y):
        i0, j0 = i, j
        while i < len(x) or j < len(y):
            if i < len(x) and j < len(y) and x[i] == y[j] and best[i][j] == best[i + 1][j + 1] + 1:
                break
            if j >= len(y) or (i < len(x) and best[i + 1][j] >= best[i][j + 1]):
                i += 1
            else:
                j += 1
        if (i, j) != (i0, j0):
            hunks.append((i0, i - i0, j0, j - j0))
        while i < len(x) and j < len(y) and x[i] == y[j]:
            i, j = i + 1, j + 1
    return hunks


def apply(hunks: list[tuple[int, int, int, int]], a: list[str], b: list[str]) -> list[str]:
    """a with the hunks' parts of b in place."""
    out, at = [], 0
    for o, n, s, m in hunks:
        out += a[at:o] + b[s : s + m]
        at = o + n
    return out + a[at:]


def hunks(old: DataFrame, new: DataFrame, changed: DataFrame) -> DataFrame:
    """repo, lang, path, old_start, old_len, new_start, new_len of modified files (only those reach Python)."""
    mod = changed.filter("kind = 'modified'").select("repo", "lang", "path")
    keys = ["repo", "lang", "path"]
    pairs = old.join(mod, keys, "left_semi").withColumnRenamed("lines", "a").join(new.join(mod, keys, "left_semi").withColumnRenamed("lines", "b"), keys)

    ship(old.sparkSession)

    def run(batches):
        import pandas as pd

        for pdf in batches:
            rows = [(r.repo, r.lang, r.path, *h) for r in pdf.itertuples() for h in diff(list(r.a), list(r.b))]
            yield pd.DataFrame(rows, columns=[*keys, "old_start", "old_len", "new_start", "new_len"])

    return pairs.mapInPandas(run, "repo string, lang string, path string, old_start int, old_len int, new_start int, new_len int")
