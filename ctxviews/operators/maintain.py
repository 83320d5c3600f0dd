"""Structural maintenance: full rebuild, file replacement, symbol repair, closure repair.

A graph is stored as four tables, keyed by snapshot (a transition's target is named
repo@step): tokens (what a symbol search reads), declarations (vertices), references
(resolved anchors) and imports.  A patch reads the stored old graph, the texts of
changed files and nothing else: tokens of untouched files meet it only through
semi-joins with the symbols that the edit touched, and only those are resolved.
The rebuild is another function over all texts and is never part of a patch.  What several steps
read is written once (`keep`), which also keeps their plans small.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import md5_number, tokens
from ctxviews.operators import structure, versions
from ctxviews.operators.structure import DECLARES, SNAP, USES
from ctxviews.operators.units import LEAST_SYMBOL
from ctxviews.plans.store import kept

EDGE = ["path", "line", "col", "symbol", "def_path", "def_line"]
Keep = Callable[[DataFrame], DataFrame]


def level2(v: DataFrame) -> DataFrame:
    return v.select(*SNAP, "path", F.posexplode("lines").alias("start", "text")).filter("text <> ''")


def token_index(v: DataFrame) -> DataFrame:
    """repo, lang, path, line, col, symbol of all tokens that could be symbols."""
    t = level2(v).select(*SNAP, "path", F.col("start").alias("line"), F.posexplode(tokens(F.col("text"))).alias("col", "symbol"))
    return t.filter(F.length("symbol") >= LEAST_SYMBOL)


def declared(t: DataFrame) -> DataFrame:
    return t.filter("col = 0").select(*SNAP, "path", "line", "symbol")


def resolve(uses: DataFrame, decl: DataFrame) -> DataFrame:
    """References of the uses (col > 0) whose symbol is declared."""
    uses = uses.filter("col > 0").join(decl.select(*SNAP, "symbol").distinct(), [*SNAP, "symbol"], "left_semi")
    role = lambda df, r: df.select(*SNAP, "path", "line", "col", "symbol", F.lit(r).alias("role"))
    return structure.references(role(decl.withColumn("col", F.lit(0)), DECLARES).unionByName(role(uses, USES)))


def imports_of(refs: DataFrame) -> DataFrame:
    """repo, lang, path, symbol, def_path, line, col: a file's first use of a symbol declared elsewhere."""
    first = refs.filter("path <> def_path").groupBy(*SNAP, "path", "symbol", "def_path").agg(F.min(F.struct("line", "col")).alias("a"))
    return first.select(*SNAP, "path", "symbol", "def_path", "a.line", "a.col")


@dataclass
class Graph:
    files: DataFrame
    tokens: DataFrame
    decl: DataFrame
    refs: DataFrame
    imports: DataFrame


def rebuild(v: DataFrame, keep: Keep = kept) -> Graph:
    """The graph of files (repo, lang, path, lines) from nothing but their texts."""
    t = keep(token_index(v))
    decl = declared(t)
    refs = keep(resolve(t, decl))
    return Graph(v.select(*SNAP, "path"), t, decl, refs, imports_of(refs))


@dataclass
class Transition:
    """A stored old graph and what an edit brings: changed files, hunks, tokens of the files that are there now."""

    old: Graph
    changed: DataFrame
    hunks: DataFrame
    fresh: DataFrame

    @classmethod
    def of(cls, old: DataFrame, new: DataFrame, graph: Graph | None = None, keep: Keep = kept) -> Transition:
        """From both versions' files; only changed ones are cut into tokens."""
        changed = keep(versions.changed_files(old, new))
        now = _semi(new, changed, ["path"])
        return cls(graph or rebuild(old, keep), changed, keep(versions.hunks(old, new, changed)), keep(token_index(now)))


def mapped(df: DataFrame, hunks: DataFrame, path: str, line: str, out: str) -> DataFrame:
    """df with `out`: the line after the edit, null on edited lines.  One row for each changed file holds its line map."""
    per = hunks.groupBy(F.col("repo").alias("hr"), F.col("lang").alias("hl"), F.col("path").alias("hp")).agg(F.sort_array(F.collect_list(F.struct("old_start", "old_len", "new_start", "new_len"))).alias("hs"))
    j = df.join(per, (F.col("repo") == F.col("hr")) & (F.col("lang") == F.col("hl")) & (F.col(path) == F.col("hp")), "left")
    edited = F.exists("hs", lambda h: (F.col(line) >= h["old_start"]) & (F.col(line) < h["old_start"] + h["old_len"]))
    shift = F.aggregate(F.filter("hs", lambda h: h["old_start"] + h["old_len"] <= F.col(line)), F.lit(0), lambda s, h: s + h["new_len"] - h["old_len"])
    return j.withColumn(out, F.when(F.col("hs").isNull(), F.col(line)).when(edited, None).otherwise(F.col(line) + shift)).drop("hs", "hr", "hl", "hp")


def _semi(df: DataFrame, keys: DataFrame, on: list[str], how: str = "left_semi") -> DataFrame:
    return df.join(keys.select(*SNAP, *on).distinct(), [*SNAP, *on], how)


def classify(t: Transition) -> DataFrame:
    """repo, lang, path, symbol, ordinal, class, old_line, new_line of the symbols of changed files."""
    w = W.partitionBy(*SNAP, "path", "symbol").orderBy("line")

    def side(decl: DataFrame, name: str) -> DataFrame:
        return decl.withColumn("ordinal", F.row_number().over(w)).select(*SNAP, "path", "symbol", "ordinal", F.col("line").alias(name))

    old = mapped(side(_semi(t.old.decl, t.changed, ["path"]), "old_line"), t.hunks, "path", "old_line", "mapped")
    j = old.join(side(declared(t.fresh), "new_line"), [*SNAP, "path", "symbol", "ordinal"], "full")
    ranges = t.hunks.groupBy(*SNAP, "path").agg(F.collect_list(F.struct("new_start", "new_len")).alias("rs"))
    j = j.join(ranges, [*SNAP, "path"], "left")
    touched = F.coalesce(F.exists("rs", lambda r: (F.col("new_line") >= r["new_start"]) & (F.col("new_line") < r["new_start"] + r["new_len"])), F.lit(False))
    c = F.when(F.col("new_line").isNull(), "deleted").when(F.col("old_line").isNull(), "added").when(touched | F.col("mapped").isNull() | (F.col("mapped") != F.col("new_line")), "affected").when(F.col("old_line") != F.col("new_line"), "shifted").otherwise("unchanged")
    return j.select(*SNAP, "path", "symbol", "ordinal", c.alias("class"), "old_line", "new_line")


def fact_actions(old: DataFrame, new: DataFrame, t: Transition) -> DataFrame:
    """repo, lang, path, line, col, symbol, action of every old and new reference: kept (same place and
    definition), changed (the same after the line maps), deleted, added.  One symbol may mix them."""
    key = [*SNAP, *EDGE]
    moved = mapped(mapped(old, t.hunks, "path", "line", "to_line"), t.hunks, "def_path", "def_line", "to_def")
    same = (F.col("line") == F.col("to_line")) & (F.col("def_line") == F.col("to_def"))
    moved = moved.select(*SNAP, "path", "col", "symbol", "def_path", F.col("to_line").alias("line"), F.col("to_def").alias("def_line"), F.col("line").alias("was"), F.coalesce(same, F.lit(False)).alias("same"))
    there = moved.filter("line is not null and def_line is not null").join(new.select(*key, F.lit(True).alias("now")), key, "full")
    known = there.select(*SNAP, "path", F.coalesce("was", "line").alias("line"), "col", "symbol", F.when(F.col("was").isNull(), "added").when(F.col("now").isNull(), "deleted").when(F.col("same"), "kept").otherwise("changed").alias("action"))
    lost = moved.filter("line is null or def_line is null").select(*SNAP, "path", F.col("was").alias("line"), "col", "symbol", F.lit("deleted").alias("action"))
    return known.unionByName(lost)


def vertices(t: Transition, listed: DataFrame | None = None) -> DataFrame:
    """Declarations of the target, made before any edge is.

    listed: what a backend reports for changed files (by default their head tokens).  An
    old symbol that it leaves out stays if its declaration line was not edited.
    """
    here = declared(t.fresh)
    if listed is not None:
        old = mapped(_semi(t.old.decl, t.changed.filter("kind = 'modified'"), ["path"]), t.hunks, "path", "line", "to_line").filter("to_line is not null")
        kept = old.select(*SNAP, "path", F.col("to_line").alias("line"), "symbol").join(listed, [*SNAP, "path", "line", "symbol"], "left_anti")
        here = listed.select(*SNAP, "path", "line", "symbol").unionByName(kept)
    return _semi(t.old.decl, t.changed, ["path"], "left_anti").unionByName(here)


def rebase_edges(refs: DataFrame, t: Transition) -> DataFrame:
    """Edges after the line maps: both ends move with their files; edges on edited lines or into deleted files go."""
    gone = t.changed.filter("kind = 'deleted'").select(*SNAP, "path")
    left = refs.join(gone, [*SNAP, "path"], "left_anti").join(gone.withColumnRenamed("path", "def_path"), [*SNAP, "def_path"], "left_anti")
    m = mapped(mapped(left, t.hunks, "path", "line", "to_line"), t.hunks, "def_path", "def_line", "to_def")
    return m.filter("to_line is not null and to_def is not null").select(*SNAP, "path", F.col("to_line").alias("line"), "col", "symbol", "def_path", F.col("to_def").alias("def_line"))


def edited(t: Transition, at: DataFrame) -> DataFrame:
    """Rows (path, line) on new or edited lines, or in added files."""
    added = t.changed.filter("kind = 'added'")
    lines = t.hunks.filter("new_len > 0").select(*SNAP, "path", F.explode(F.sequence("new_start", F.col("new_start") + F.col("new_len") - 1)).alias("line"))
    return _semi(at, added, ["path"]).unionByName(_semi(at, lines, ["path", "line"]))


def _patched(t: Transition, decl: DataFrame, kept: DataFrame, uses: DataFrame, keep: Keep) -> Graph:
    """The target's graph: kept edges and the uses resolved again; imports are derived anew only in files whose edges changed."""
    uses = keep(uses.filter("col > 0"))
    found = keep(resolve(uses, _semi(decl, uses, ["symbol"])))
    lost = _semi(t.old.refs, uses, ["symbol"]).select(*SNAP, "path")
    into = _semi(t.old.refs, t.changed.select(*SNAP, F.col("path").alias("def_path")), ["def_path"]).select(*SNAP, "path")
    paths = keep(t.changed.select(*SNAP, "path").unionByName(found.select(*SNAP, "path")).unionByName(lost).unionByName(into).distinct())
    refs = kept.unionByName(found)
    files = _semi(t.old.files, t.changed, ["path"], "left_anti").unionByName(t.changed.filter("kind <> 'deleted'").select(*SNAP, "path"))
    toks = _semi(t.old.tokens, t.changed, ["path"], "left_anti").unionByName(t.fresh)
    imports = _semi(t.old.imports, paths, ["path"], "left_anti").unionByName(imports_of(_semi(refs, paths, ["path"])))
    return Graph(files, toks, decl, refs, imports)


def replace_files(t: Transition, keep: Keep = kept) -> Graph:
    """Drop and re-extract changed files; reconnect all their symbols and outgoing edges."""
    decl = keep(vertices(t))
    own = keep(declared(t.fresh).select(*SNAP, "symbol").distinct())
    kept = _semi(_semi(t.old.refs, t.changed, ["path"], "left_anti"), own, ["symbol"], "left_anti")
    kept = kept.join(t.changed.select(*SNAP, F.col("path").alias("def_path")), [*SNAP, "def_path"], "left_anti")
    back = _semi(_semi(t.old.tokens, own, ["symbol"]), t.changed, ["path"], "left_anti")
    return _patched(t, decl, kept, t.fresh.unionByName(back), keep)


def repair(t: Transition, closure: bool = False, keep: Keep = kept) -> Graph:
    """Symbol repair: rebase what shifted, resolve again what the edit touched.

    Plain repair discovers incoming uses of added and affected symbols only.  With
    closure every anchor of a symbol that was added, deleted or affected is resolved
    again, which always gives the rebuilt graph.
    """
    decl = keep(vertices(t))
    wanted = ("added", "affected", "deleted") if closure else ("added", "affected")
    symbols = keep(classify(t).filter(F.col("class").isin(*wanted)).select(*SNAP, "symbol").distinct())
    kept = rebase_edges(_semi(t.old.refs, symbols, ["symbol"], "left_anti"), t)
    back = _semi(_semi(t.old.tokens, symbols, ["symbol"]), t.changed, ["path"], "left_anti").unionByName(_semi(t.fresh, symbols, ["symbol"]))
    out = _semi(edited(t, t.fresh), symbols, ["symbol"], "left_anti")
    return _patched(t, decl, kept, back.unionByName(out), keep)


ARMS = {"file": replace_files, "symbol": lambda t, keep=kept: repair(t, False, keep), "closure": lambda t, keep=kept: repair(t, True, keep)}


def facts(g: Graph) -> DataFrame:
    """repo, lang, tag, payload: files, declarations with their lines, typed edges with their anchors."""
    row = lambda df, tag, *cols: df.select(*SNAP, F.lit(tag).alias("tag"), F.concat_ws("\x1f", *[F.col(c).cast("string") for c in cols]).alias("payload"))
    return row(g.files, "file", "path").unionByName(row(g.decl, "symbol", "path", "line", "symbol")).unionByName(row(g.refs, "reference", *EDGE)).unionByName(row(g.imports, "import", "path", "symbol", "def_path", "line", "col"))


def digest(f: DataFrame) -> DataFrame:
    """repo, lang, n, digest of a graph's facts: equal multisets have equal digests."""
    return f.groupBy(*SNAP).agg(F.count("*").alias("n"), F.sum(md5_number(F.concat_ws("\x1f", "tag", "payload"))).alias("digest"))


def in_scope(f: DataFrame, t: Transition) -> DataFrame:
    """Facts whose file, or whose anchor's file, is a changed one."""
    return _semi(f.withColumn("path", F.substring_index("payload", "\x1f", 1)), t.changed, ["path"]).drop("path")


def occurrences_of(g: Graph) -> DataFrame:
    """What a graph serves: its declarations and the anchors of its references."""
    d = g.decl.select(*SNAP, "path", "line", F.lit(0).alias("col"), "symbol", F.lit(DECLARES).alias("role"))
    return d.unionByName(g.refs.select(*SNAP, "path", "line", "col", "symbol", F.lit(USES).alias("role")))


def request_counts(classes: DataFrame, uses_out: DataFrame) -> DataFrame:
    """Lookups of both arms: references for symbols, definitions for outgoing uses.

    File replacement asks for every symbol and every use of a changed file; repair
    asks for added symbols, for uses of added and affected symbols, and validates
    rebased anchors.  uses_out: repo, lang, path, line, symbol, state (kept, rebased, new).
    """
    symbols = classes.filter("new_line is not null").groupBy(*SNAP).agg(F.count("*").alias("file_refs"), F.count_if(F.col("class") == "added").alias("symbol_refs"))
    uses = uses_out.groupBy(*SNAP).agg(F.count("*").alias("file_defs"), F.count_if(F.col("state") != "kept").alias("symbol_defs"))
    return symbols.join(uses, SNAP, "full").select(*SNAP, *[F.coalesce(c, F.lit(0)).alias(c) for c in ("file_refs", "file_defs", "symbol_refs", "symbol_defs")])
