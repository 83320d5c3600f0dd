"""Source units: files (level 0), paragraph runs (1) and lines (2), with addresses.

Lines count from 0.  Level 2 is a non-empty line; level 1 is at most PARAGRAPH
neighbouring non-empty lines; markup pages have their own adapter.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.text import digest, head_token

PARAGRAPH = 4
#: Lines that share a bin in range joins.
BIN = 64
LEAST_SYMBOL = 4
SNAPSHOT = ["repo", "lang", "version"]


def unit_id(path: Column | str, level: int, start: Column | str, end: Column | str) -> Column:
    return digest(path, F.lit(str(level)), F.col(start).cast("string") if isinstance(start, str) else start.cast("string"), F.col(end).cast("string") if isinstance(end, str) else end.cast("string"))


def lines(f: DataFrame) -> DataFrame:
    """All lines of files, empty ones too: keys of the file, line, text."""
    keys = [c for c in f.columns if c != "text"]
    return f.select(*keys, F.posexplode(F.split("text", "\n", -1)).alias("line", "text"))


def level0(f: DataFrame) -> DataFrame:
    last = F.size(F.split("text", "\n", -1)) - 1
    return f.select(*[c for c in f.columns if c != "text"], F.lit(0).alias("level"), F.lit(0).alias("start"), last.alias("end"), F.lit("file").alias("ntype"), "text")


def level2(f: DataFrame) -> DataFrame:
    return lines(f).filter("text <> ''").select(*[c for c in f.columns if c != "text"], F.lit(2).alias("level"), F.col("line").alias("start"), F.col("line").alias("end"), F.lit("line").alias("ntype"), "text")


def level1(f: DataFrame) -> DataFrame:
    """Runs of neighbouring non-empty lines, cut after every PARAGRAPH lines.

    A file's lines are an array already, so runs come from array functions alone:
    no shuffle.
    """
    keys = [c for c in f.columns if c != "text"]
    text = F.split("text", "\n", -1)
    numbered = F.filter(F.transform(text, lambda x, i: F.struct(i.alias("line"), x.alias("text"))), lambda s: s["text"] != "")
    starts = F.aggregate(
        numbered,
        F.array().cast("array<struct<start:int,end:int,text:string>>"),
        lambda acc, s: F.when(
            (F.size(acc) > 0) & (F.try_element_at(acc, F.lit(-1))["end"] == s["line"] - 1) & (F.try_element_at(acc, F.lit(-1))["end"] - F.try_element_at(acc, F.lit(-1))["start"] < PARAGRAPH - 1),
            F.concat(F.slice(acc, 1, F.greatest(F.size(acc) - 1, F.lit(0))), F.array(F.struct(F.try_element_at(acc, F.lit(-1))["start"].alias("start"), s["line"].alias("end"), F.concat(F.try_element_at(acc, F.lit(-1))["text"], F.lit("\n"), s["text"]).alias("text")))),
        ).otherwise(F.concat(acc, F.array(F.struct(s["line"].alias("start"), s["line"].alias("end"), s["text"].alias("text"))))),
    )
    return f.select(*keys, F.explode(starts).alias("u")).select(*keys, F.lit(1).alias("level"), "u.start", "u.end", F.lit("run").alias("ntype"), "u.text")


def with_ids(u: DataFrame, level: int) -> DataFrame:
    return u.withColumn("unit_id", unit_id("path", level, "start", "end"))


def declare(u: DataFrame) -> DataFrame:
    """Lines with the symbol that their head token declares (null if it is too short)."""
    h = head_token(F.col("text"))
    return u.withColumn("symbol", F.when(F.length(h) >= LEAST_SYMBOL, h))


def enclosing(positions: DataFrame, u: DataFrame) -> DataFrame:
    """Units that hold a position (path, line): an equality on path and line bin, then containment."""
    cols = [c for c in u.columns if c != "path"]
    binned = u.withColumn("bin", F.explode(F.sequence((F.col("start") / BIN).cast("int"), (F.col("end") / BIN).cast("int"))))
    p = positions.withColumn("bin", (F.col("line") / BIN).cast("int"))
    return p.join(binned, ["path", "bin"]).filter(F.col("line").between(F.col("start"), F.col("end"))).select(*positions.columns, *cols)


ELEMENT = r"(?s)<(h1|p|li|a)\b[^>]*>(.*?)</\1>"


def page_units(p: DataFrame) -> DataFrame:
    """Leaf elements of pages as level-2 units, in document order (start = end = ordinal)."""
    found = F.regexp_extract_all("text", F.lit(r"(?s)<(?:h1|p|li)\b[^>]*>.*?</(?:h1|p|li)>"), F.lit(0))
    u = p.select("repo", "path", "page_id", F.posexplode(found).alias("start", "raw"))
    return u.select("repo", "path", "page_id", F.lit(2).alias("level"), "start", F.regexp_extract("raw", r"^<(h1|p|li)", 1).alias("ntype"), F.regexp_replace("raw", r"(?s)<[^>]*>", "").alias("text"))
