"""The structural view: containment, occurrences, resolved references, bounded queries.

A symbol is the head token of a line.  A use is any other token equal to a symbol
that the same snapshot declares; it resolves to the nearest declaration at or
before it in its file, else to the least (path, line) of the snapshot.
Cross-snapshot resolution never happens, so every step partitions by snapshot.
Columns count tokens of the line from 0.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import tokens
from ctxviews.operators import closure, rows
from ctxviews.operators.units import LEAST_SYMBOL, declare, level0, level1, level2

DECLARES, USES, IMPORTS = 1, 2, 4
SNAP = ["repo", "lang"]


def declarations(l2: DataFrame) -> DataFrame:
    """repo, lang, path, line, symbol."""
    return declare(l2).filter("symbol is not null").select(*SNAP, "path", F.col("start").alias("line"), "symbol")


def occurrences(l2: DataFrame, few=None) -> DataFrame:
    """repo, lang, path, line, col, symbol, role of tokens that declare or use a symbol of their snapshot.

    few(df) writes the declared symbols and may send them to every task, so that no token is shuffled.
    """
    t = l2.select(*SNAP, "path", F.col("start").alias("line"), F.posexplode(tokens(F.col("text"))).alias("col", "symbol")).filter(F.length("symbol") >= LEAST_SYMBOL)
    declared = (few or (lambda df: df))(declarations(l2).select(*SNAP, "symbol").distinct())
    role = F.when(F.col("col") == 0, DECLARES).otherwise(USES)
    return t.join(declared, [*SNAP, "symbol"], "left_semi").select(*SNAP, "path", "line", "col", "symbol", role.alias("role"))


def references(occ: DataFrame) -> DataFrame:
    """repo, lang, path, line, col, symbol, def_path, def_line of every use.

    Declarations and uses share one shuffle by symbol: a running maximum over a
    file's occurrences finds the nearest declaration, a minimum over the
    snapshot's declarations is the fallback (both from the same partitioning).
    """
    here = W.partitionBy(*SNAP, "symbol", "path").orderBy("line", "col").rowsBetween(W.unboundedPreceding, 0)
    least = occ.filter(F.col("role") == DECLARES).groupBy(*SNAP, "symbol").agg(F.min(F.struct("path", "line")).alias("first"))
    near = F.max(F.when(F.col("role") == DECLARES, F.col("line"))).over(here)
    uses = occ.withColumn("near", near).filter(F.col("role") == USES).join(least, [*SNAP, "symbol"])
    return uses.select(*SNAP, "path", "line", "col", "symbol", F.when(F.col("near").isNotNull(), F.col("path")).otherwise(F.col("first.path")).alias("def_path"), F.coalesce("near", "first.line").alias("def_line"))


def edges(occ: DataFrame) -> DataFrame:
    """reference edges between lines, and an import edge for a file's first use of a symbol declared elsewhere."""
    return edges_of(references(occ))


def edges_of(refs: DataFrame) -> DataFrame:
    """The edges of resolved references."""
    ref = refs.select(*SNAP, _vid("path", "line").alias("src"), _vid("def_path", "def_line").alias("dst"), F.lit("reference").alias("etype"), F.col("path").alias("anchor_file"), F.col("line").alias("anchor_line"), F.col("col").alias("anchor_col"))
    first = refs.filter("path <> def_path").groupBy(*SNAP, "path", "symbol", "def_path").agg(F.min(F.struct("line", "col")).alias("a"))
    imp = first.select(*SNAP, F.col("path").alias("src"), F.col("def_path").alias("dst"), F.lit("import").alias("etype"), F.col("path").alias("anchor_file"), F.col("a.line").alias("anchor_line"), F.col("a.col").alias("anchor_col"))
    return ref.unionByName(imp)


def imports(f: DataFrame, few=None, keep=None) -> closure.Steps:
    """The steps along import edges, from file to file, without the edges' anchors.

    A file imports a symbol that it uses before it declares it, if it does, from the snapshot's least
    declaration elsewhere.  The first occurrences of a file's symbols are found where its text lies; few(df)
    writes the snapshots' symbols and may send them to every task, so that no token is shuffled.
    """
    few, keep = few or (lambda df: df), keep or (lambda df: df)
    least = keep(declarations(level2(f)).groupBy(*SNAP, "symbol").agg(F.min("path").alias("node")))
    names = keep(closure.coded(least.select(*SNAP, "node").distinct()))
    used = rows.first_uses(f, LEAST_SYMBOL).select(*SNAP, "path", F.explode("symbols").alias("symbol"))
    to = used.join(few(least.join(names, [*SNAP, "node"])), [*SNAP, "symbol"]).filter("path <> node")
    return closure.Steps(keep(to.groupBy(*SNAP, F.col("path").alias("node")).agg(F.collect_set("code").alias("nexts"))), names)


def incident(l2: DataFrame, lines: DataFrame, few=None) -> DataFrame:
    """The edges of `edges` from or to some lines (path, start), among others of the symbols that these lines declare.

    A reference is resolved by its own symbol's declarations alone.  Edges to a line are uses of the symbol at
    its head, edges from it are uses in it: of a head all occurrences count, of any other symbol of the lines
    its declarations and its uses there.  few(df) writes a small table and may send it to every task, so that
    no other token leaves its row.
    """
    few = few or (lambda df: df)
    tokens_of = lambda u: u.select(*SNAP, "path", F.col("start").alias("line"), F.posexplode(tokens(F.col("text"))).alias("col", "symbol")).filter(F.length("symbol") >= LEAST_SYMBOL)
    own = few(tokens_of(l2.join(few(lines.select("path", "start").distinct()), ["path", "start"], "left_semi")))
    want = few(own.groupBy(*SNAP, "symbol").agg(F.max(F.col("col") == 0).alias("head")))
    all_ = tokens_of(l2).join(want, [*SNAP, "symbol"]).filter("col = 0 or head")
    here = own.join(want, [*SNAP, "symbol"]).filter("col > 0 and not head")
    role = F.when(F.col("col") == 0, DECLARES).otherwise(USES)
    return edges_of(references(all_.unionByName(here).select(*SNAP, "path", "line", "col", "symbol", role.alias("role"))))


def _vid(path: str, line: str):
    return F.concat(F.col(path), F.lit("#"), F.col(line).cast("string"))


def contain(f: DataFrame) -> DataFrame:
    """(src, dst) from directory to file, file to run, run to line."""
    dirs = f.select(F.col("repo").alias("src"), F.concat_ws("/", "repo", "lang").alias("dst")).distinct()
    in_dir = f.select(F.concat_ws("/", "repo", "lang").alias("src"), F.col("path").alias("dst"))
    runs = level1(f)
    run_id = F.concat(F.col("path"), F.lit("@"), F.col("start").cast("string"))
    in_file = runs.select(F.col("path").alias("src"), run_id.alias("dst"))
    in_run = runs.select(run_id.alias("src"), "path", F.explode(F.sequence("start", "end")).alias("line")).select("src", _vid("path", "line").alias("dst"))
    return dirs.unionByName(in_dir).unionByName(in_file).unionByName(in_run)


def type_uses(occ: DataFrame, runs: DataFrame) -> DataFrame:
    """Uses whose definition lies in a run: (path, line, col) to (def_path, run start)."""
    r = runs.select("path", F.col("start").alias("run_start"), F.explode(F.sequence("start", "end")).alias("run_line"))
    refs = references(occ)
    return refs.join(r.withColumnRenamed("path", "def_path").withColumnRenamed("run_line", "def_line"), ["def_path", "def_line"]).select("path", "line", "col", "def_path", "run_start")


def page_imports(p: DataFrame) -> DataFrame:
    """href edges of pages; targets that no page has are external vertices."""
    href = p.select("repo", F.col("path").alias("src"), F.posexplode(F.regexp_extract_all("text", F.lit(r'href="([^"]*)"'), F.lit(1))).alias("anchor", "href"))
    dst = F.when(F.col("href").startswith("/"), F.concat("repo", "href")).otherwise(F.col("href"))
    e = href.withColumn("dst", dst)
    known = p.select(F.col("path").alias("dst")).distinct().withColumn("known", F.lit(True))
    return e.join(known, "dst", "left").select("src", "dst", "anchor", F.when(F.col("known"), "file").otherwise("external").alias("kind"))


def at(positions: DataFrame, occ: DataFrame, l2: DataFrame) -> DataFrame:
    """The occurrence at (path, line, col), else the enclosing line, with the granularity that answered."""
    from ctxviews.operators.units import enclosing

    exact = positions.join(occ.select("path", "line", "col", "symbol"), ["path", "line", "col"], "left")
    around = enclosing(positions.select("path", "line", "col"), l2.select("path", "start", "end")).select("path", "line", "col", "start")
    out = exact.join(around, ["path", "line", "col"], "left")
    return out.select("path", "line", "col", "symbol", F.when(F.col("symbol").isNotNull(), "occurrence").when(F.col("start").isNotNull(), "enclosing").otherwise("none").alias("granularity"))


def neighbours(seeds: DataFrame, e: DataFrame, hops: int, families: tuple[str, ...] = ("reference",), direction: str = "both", keep=None) -> DataFrame:
    """seed, node, hop: nodes within `hops` steps, each at its least distance.

    One frontier join for each hop; visited nodes leave by an anti-join.  The
    number of hops is a small constant, so the plan stays one DAG; with keep(df), which
    writes a table and reads it again, steps and frontiers are made once.
    """
    keep = keep or (lambda df: df)
    own = e.filter(F.col("etype").isin(*families))
    parts = []
    if direction in ("out", "both"):
        parts.append(own.select(F.col("src").alias("node"), F.col("dst").alias("next")))
    if direction in ("in", "both"):
        parts.append(own.select(F.col("dst").alias("node"), F.col("src").alias("next")))
    step = parts[0] if len(parts) == 1 else parts[0].union(parts[1])
    step = keep(step.distinct())
    seen = seeds.select("seed", F.col("seed").alias("node"), F.lit(0).alias("hop")).distinct()
    seen = front = keep(seen)
    for h in range(1, hops + 1):
        new = front.select("seed", "node").join(step, "node").select("seed", F.col("next").alias("node")).distinct()
        front = new.join(seen.select("seed", "node"), ["seed", "node"], "left_anti").withColumn("hop", F.lit(h))
        front = keep(front) if h < hops else front
        seen = seen.unionByName(front)
    return seen


def dependencies(seeds: DataFrame, e: DataFrame | closure.Steps, depth: int, keep=None) -> DataFrame:
    """What seeds depend on: import edges outwards.  With steps of `imports` (seeds: repo, lang, seed) those of many seeds are taken at once."""
    if not isinstance(e, closure.Steps):
        return neighbours(seeds, e, depth, ("import",), "out", keep)
    own = (keep or (lambda df: df))(seeds.select(*SNAP, F.col("seed").alias("node")).distinct())
    found = closure.search(e, own, closure.surroundings(depth)).select(F.col("start").alias("seed"), F.explode("nodes").alias("node"), "hop")
    return own.select(F.col("node").alias("seed"), "node", F.lit(0).alias("hop")).unionByName(found)


def route(pairs: DataFrame, e: DataFrame, most: int, keep=None) -> DataFrame:
    """a, b, hops: least number of reference or import steps from a to b, null beyond `most`.

    Only pairs that are still open go on: a step is taken from their a's side until half of the
    way, and met from their b's side, so no start's whole surroundings are made.  keep(df) writes a
    table and reads it again (without it the plan stays one DAG).
    """
    keep = keep or (lambda df: df)
    step = keep(e.filter(F.col("etype").isin("reference", "import")).select("src", "dst").distinct())
    open_, found = keep(pairs.select("a", "b").distinct()), None
    for h in range(most + 1):
        if h == 0:
            hit = open_.filter("a = b")
        elif h == 1:
            hit = open_.join(step.select(F.col("src").alias("a"), F.col("dst").alias("b")), ["a", "b"], "left_semi")
        else:
            near = lambda ends, side, far, n: ends if n == 0 else near(ends, side, far, n - 1).join(step.select(F.col(side).alias("n"), F.col(far).alias("m")), "n").select("end", F.col("m").alias("n")).distinct()
            ahead = near(open_.select(F.col("a").alias("end"), F.col("a").alias("n")).distinct(), "src", "dst", h // 2)
            back = near(open_.select(F.col("b").alias("end"), F.col("b").alias("n")).distinct(), "dst", "src", h - h // 2)
            met = ahead.select(F.col("end").alias("a"), "n").join(back.select(F.col("end").alias("b"), "n"), "n").select("a", "b").distinct()
            hit = open_.join(met, ["a", "b"], "left_semi")
        hit = keep(hit.withColumn("hops", F.lit(h)))
        found = hit if found is None else found.unionByName(hit)
        open_ = keep(open_.join(hit, ["a", "b"], "left_anti"))
    return pairs.join(found, ["a", "b"], "left")


def import_routes(s: closure.Steps, steps: int, most: int) -> DataFrame:
    """a, b, hops: `route` for the pairs (a, b) that just `steps` import steps join, which are stored nowhere.

    For graphs in which no file is also a line (see has_lines): then no reference edge leads to or from one of their nodes.
    """
    found = closure.search(s, s.nexts.select(*SNAP, "node"), closure.routes(steps, most))
    return found.select(F.col("start").alias("a"), F.explode("nodes").alias("b"), F.col("hop").alias("hops"))


def has_lines(s: closure.Steps) -> bool:
    """Whether a node of the steps is named like a line, so that reference edges may meet it."""
    line = F.col("node").rlike("#[0-9]+$")
    return not (s.names.filter(line).isEmpty() and s.nexts.filter(line).isEmpty())


def facts(vertices: DataFrame, e: DataFrame) -> DataFrame:
    """The graph as a multiset of facts: tag, payload, mult."""
    v = vertices.select(F.lit("vertex").alias("tag"), F.concat_ws("\x1f", *vertices.columns).alias("payload"))
    d = e.select(F.lit("edge").alias("tag"), F.concat_ws("\x1f", *[F.col(c).cast("string") for c in e.columns]).alias("payload"))
    return v.unionByName(d).groupBy("tag", "payload").agg(F.count("*").alias("mult"))


def relational_graph(t: dict[str, DataFrame], month: str | None = None) -> DataFrame:
    """(src, dst, etype) over the relational tables, optionally as of the end of a month (yyyy-MM)."""
    orders = t["orders"] if month is None else t["orders"].filter(F.date_format("o_orderdate", "yyyy-MM") <= month)

    def e(df, a, pa, b, pb, kind):
        return df.select(F.concat(F.lit(pa), F.col(a).cast("string")).alias("src"), F.concat(F.lit(pb), F.col(b).cast("string")).alias("dst"), F.lit(kind).alias("etype"))

    li = t["lineitem"].join(orders.select("o_orderkey"), F.col("l_orderkey") == F.col("o_orderkey"), "left_semi").withColumn("lk", F.concat_ws(":", F.col("l_orderkey").cast("string"), F.col("l_linenumber").cast("string")))
    return (
        e(t["nation"], "n_regionkey", "r", "n_nationkey", "n", "contain")
        .unionByName(e(t["customer"], "c_nationkey", "n", "c_custkey", "c", "contain"))
        .unionByName(e(orders, "o_custkey", "c", "o_orderkey", "o", "contain"))
        .unionByName(e(li, "l_orderkey", "o", "lk", "l", "contain"))
        .unionByName(e(li, "lk", "l", "l_partkey", "p", "reference"))
        .unionByName(e(li, "lk", "l", "l_suppkey", "s", "reference"))
        .unionByName(e(t["supplier"], "s_suppkey", "s", "s_nationkey", "n", "import"))
    )
