"""Expressions for tokens, portable hashes and addresses.  All stay on the JVM."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

TOKEN = r"[\p{L}\p{N}]+"


def tokens(c: Column) -> Column:
    """Lower-case runs of letters and digits."""
    return F.regexp_extract_all(F.lower(c), F.lit(TOKEN), F.lit(0))


def head_token(c: Column) -> Column:
    return F.regexp_extract(F.lower(c), TOKEN, 0)


def md5_number(c: Column) -> Column:
    """A portable 32-bit hash as a long."""
    return F.conv(F.substring(F.md5(c), 1, 8), 16, 10).cast("long")


def joined(*cols: Column | str) -> Column:
    """Values joined by a separator that no text holds."""
    return F.concat_ws("\x1f", *cols)


def digest(*cols: Column | str) -> Column:
    return F.sha2(joined(*cols), 256)


def usage(c: Column) -> Column:
    """Token usage proxy: words and single punctuation marks."""
    return F.size(F.regexp_extract_all(F.coalesce(c, F.lit("")), F.lit(r"[\p{L}\p{N}]+|[^\s\p{L}\p{N}]"), F.lit(0))).cast("long")
