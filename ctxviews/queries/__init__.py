"""Registered queries with their DuckDB twins.

Each module fills QUERIES and ORACLE_SQL through `query(name, sql)`.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


# Common table expressions of the DuckDB side.
FILES = "files as (select source as repo, lang, 0 as version, source||'/'||lang||'/'||doc_id as path, doc_id, coalesce(text,'') as text from documents)"
LINES = FILES + ", ln as (select repo, lang, path, doc_id, unnest(range(len(string_split(text, chr(10)))))::int as line, unnest(string_split(text, chr(10))) as text from files)"
L2 = LINES + ", l2 as (select * from ln where text <> '')"
TOKEN = r"'[\p{L}\p{N}]+'"
DECL = L2 + rf", decl as (select repo, lang, path, line, regexp_extract(lower(text), {TOKEN}, 0) as symbol from l2 where length(regexp_extract(lower(text), {TOKEN}, 0)) >= 4)"
OCC = DECL + rf""", tok0 as (select repo, lang, path, line, regexp_extract_all(lower(text), {TOKEN}) as ts from l2),
 tok as (select repo, lang, path, line, unnest(range(len(ts)))::int as col, unnest(ts) as symbol from tok0),
 occ as (select t.*, case when col = 0 then 1 else 2 end as role from tok t where length(symbol) >= 4 and exists (select 1 from decl d where d.repo = t.repo and d.lang = t.lang and d.symbol = t.symbol))"""
REFS = OCC + """, firsts as (select repo, lang, symbol, min(struct_pack(path := path, line := line)) as f from decl group by all),
 nearest as (select u.repo, u.lang, u.path, u.line, u.col, max(d.line) as near from occ u join decl d on d.path = u.path and d.symbol = u.symbol and d.line <= u.line where u.role = 2 group by all),
 refs as (select u.repo, u.lang, u.path, u.line, u.col, u.symbol, case when n.near is not null then u.path else f.f.path end as def_path, coalesce(n.near, f.f.line) as def_line
  from occ u join firsts f on f.repo = u.repo and f.lang = u.lang and f.symbol = u.symbol left join nearest n on n.path = u.path and n.line = u.line and n.col = u.col where u.role = 2)"""
EDGES = REFS + """, edges as (select repo, lang, path||'#'||line as src, def_path||'#'||def_line as dst, 'reference' as etype, path as anchor_file, line as anchor_line, col as anchor_col from refs
 union all select repo, lang, path, def_path, 'import', path, a.line, a.col from (select repo, lang, path, symbol, def_path, min(struct_pack(line := line, col := col)) as a from refs where path <> def_path group by all))"""


def unit_id(path: str, level: int, start: str, end: str) -> str:
    return f"sha256({path}||chr(31)||'{level}'||chr(31)||{start}||chr(31)||{end})"


def num(x: str) -> str:
    return f"('0x'||substr(md5({x}),1,8))::bigint"
