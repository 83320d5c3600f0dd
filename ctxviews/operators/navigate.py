"""Symbol navigation: requests, the static provider, the live provider, normalization."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import TOKEN, tokens
from ctxviews.operators.structure import DECLARES, SNAP, USES

LIMITS = {"definition": 8, "references": 40}
PER_SNAPSHOT = 5


def requests(occ: DataFrame, per: int = PER_SNAPSHOT) -> DataFrame:
    """Evenly spaced reference anchors of each snapshot, once for each capability.

    Position floor((i + 0.5) n / per) of the sorted anchors, i = 0 .. per-1; all if there are fewer.
    """
    uses = occ.filter(F.col("role") == USES)
    w = W.partitionBy(*SNAP)
    n = uses.withColumn("at", F.row_number().over(w.orderBy("path", "line", "col")) - 1).withColumn("n", F.count("*").over(w))
    wanted = F.exists(F.sequence(F.lit(0), F.lit(per - 1)), lambda i: F.floor((i * 2 + 1) * F.col("n") / F.lit(2.0 * per)) == F.col("at"))
    picked = n.filter((F.col("n") <= per) | wanted)
    both = picked.withColumn("capability", F.explode(F.array(*map(F.lit, LIMITS))))
    return both.select(req_id().alias("req_id"), *SNAP, "capability", "path", "line", "col", "symbol")


def req_id() -> Column:
    return F.concat_ws(":", F.col("capability"), F.col("path"), F.col("line").cast("string"), F.col("col").cast("string"))


def limited(found: DataFrame) -> DataFrame:
    """Provider-side limits: rows (req_id, capability, order.., path, start) in the provider's order, then N()."""
    w = W.partitionBy("req_id").orderBy("far", "place", "loc_path", "loc_line")
    most = F.when(F.col("capability") == "definition", LIMITS["definition"]).otherwise(LIMITS["references"])
    return found.withColumn("n", F.row_number().over(w)).filter(F.col("n") <= most)


def normalize(found: DataFrame, reqs: DataFrame) -> DataFrame:
    """req_id, locs: sorted unique (path, start line) of every request, empty if nothing was found."""
    sets = found.groupBy("req_id").agg(F.array_sort(F.collect_set(F.struct("loc_path", "loc_line"))).alias("locs"))
    text = F.transform("locs", lambda s: F.concat(s["loc_path"], F.lit(":"), s["loc_line"].cast("string")))
    return reqs.join(sets.withColumn("locs", text), "req_id", "left").withColumn("locs", F.coalesce("locs", F.array().cast("array<string>")))


def _answers(reqs: DataFrame, defs: DataFrame, uses: DataFrame, key: str) -> DataFrame:
    """Definitions: nearest before in the file first, then by address.  References: all tokens and the
    declaration, by address; the same for every request of a symbol, so they are cut once for each symbol.

    Of a symbol's declarations only those before the request in its file, and the first 2 * limit by
    address, can be among the first `limit`: fewer than `limit` of the latter are near ones.
    """
    by = W.partitionBy(*SNAP, key).orderBy("loc_path", "loc_line")
    named = reqs.filter("capability = 'definition'")
    places = defs.select(*SNAP, key, F.col("path").alias("loc_path"), F.col("line").alias("loc_line"))
    near = named.join(places.withColumn("path", F.col("loc_path")), [*SNAP, key, "path"]).filter(F.col("loc_line") <= F.col("line")).withColumn("far", F.lit(0)).withColumn("place", -F.col("loc_line"))
    early = places.withColumn("at", F.row_number().over(by)).filter(F.col("at") <= 2 * LIMITS["definition"]).drop("at")
    far = named.join(early, [*SNAP, key]).filter((F.col("loc_path") != F.col("path")) | (F.col("loc_line") > F.col("line"))).withColumn("far", F.lit(1)).withColumn("place", F.lit(0))
    d = near.unionByName(far)
    asked = reqs.filter("capability = 'references'")
    u = uses.select(*SNAP, key, F.col("path").alias("loc_path"), F.col("line").alias("loc_line")).join(asked.select(*SNAP, key).distinct(), [*SNAP, key], "left_semi").distinct()
    first = u.withColumn("at", F.row_number().over(by)).filter(F.col("at") <= LIMITS["references"])
    r = asked.join(first, [*SNAP, key]).withColumn("far", F.lit(0)).withColumn("place", F.lit(0))
    return limited(d.unionByName(r.drop("at")).select("req_id", "capability", "far", "place", "loc_path", "loc_line"))


def located(reqs: DataFrame, occ: DataFrame) -> DataFrame:
    """Requests (path, line, col) with the symbol they are answered for and its granularity.

    The occurrence at the position if there is one, else the enclosing node: the last
    declaration at or before the line in the file.
    """
    exact = occ.select(*SNAP, "path", "line", "col", F.col("symbol").alias("exact")).distinct()
    at = reqs.drop("symbol").join(exact, [*SNAP, "path", "line", "col"], "left")
    decl = occ.filter(F.col("role") == DECLARES).select(*SNAP, "path", F.col("line").alias("from"), F.col("symbol").alias("node"))
    around = at.filter("exact is null").join(decl, [*SNAP, "path"]).filter(F.col("from") <= F.col("line")).groupBy("req_id").agg(F.max_by("node", "from").alias("node"))
    out = at.join(around, "req_id", "left")
    granularity = F.when(F.col("exact").isNotNull(), "occurrence").when(F.col("node").isNotNull(), "enclosing").otherwise("none")
    return out.withColumn("symbol", F.coalesce("exact", "node")).withColumn("granularity", granularity).drop("exact", "node")


def static(reqs: DataFrame, occ: DataFrame, version: str = "0") -> DataFrame:
    """Answers from the occurrences of the structural view, with provider, its version and granularity."""
    asked = located(reqs, occ)
    found = _answers(asked, occ.filter(F.col("role") == DECLARES), occ, "symbol")
    return normalize(found, asked).withColumn("provider", F.lit("static")).withColumn("version", F.lit(version))


def live(reqs: DataFrame, l2: DataFrame) -> DataFrame:
    """Answers from the source text at request time: tokens as they are written, case-sensitive."""
    written = l2.select(*SNAP, "path", F.col("start").alias("line"), F.posexplode(F.regexp_extract_all("text", F.lit(TOKEN), F.lit(0))).alias("col", "written"))
    asked = reqs.join(written.select("path", "line", "col", "written"), ["path", "line", "col"])
    hits = written.join(asked.select(*SNAP, "written").distinct(), [*SNAP, "written"], "left_semi")
    found = _answers(asked, hits.filter("col = 0"), hits, "written")
    return normalize(found, reqs).withColumn("provider", F.lit("live")).withColumn("version", F.lit("worktree")).withColumn("granularity", F.lit("text"))
