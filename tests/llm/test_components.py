"""Connected components: both ways of joining edges, against a union by hand."""

import random

import pytest

from ctxviews.llm.common import components, small


def by_hand(edges):
    up = {}

    def root(x):
        up.setdefault(x, x)
        while up[x] != x:
            x = up[x]
        return x

    for a, b in edges:
        a, b = root(a), root(b)
        up[max(a, b)] = min(a, b)
    return {x: root(x) for x in up}


@pytest.mark.parametrize("finish", [0, 40, 1_000_000])
@pytest.mark.parametrize("shape", ["chain", "star", "random", "repeated", "empty"])
def test_components(spark, shape, finish):
    rng = random.Random(4)
    edges = {
        "chain": [(i, i + 1) for i in range(60)][::-1],
        "star": [(-5, i) for i in range(50)] + [(100, 101)],
        "random": [(rng.randrange(-90, 90), rng.randrange(-90, 90)) for _ in range(110)],
        "repeated": [(1, 2), (2, 1), (1, 2), (2, 3), (3, 3), (9, 8), (9, 8)],
        "empty": [],
    }[shape]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "src long, dst long"), spark, finish).collect()}
    assert got == by_hand([e for e in edges if e[0] != e[1]])


def test_broadcast_is_bounded_by_bytes(spark):
    df = spark.createDataFrame([(1, "x" * 5000, [(1, 2)] * 10, [b"ab"])], "a long, s string, l array<struct<p: long, q: long>>, t array<binary>")
    assert "broadcast" in small(df, spark)._jdf.queryExecution().toString().lower()
    assert "broadcast" not in small(df, spark, 5000)._jdf.queryExecution().toString().lower()
    empty = df.filter("a > 1")
    assert "broadcast" in small(empty, spark, 0)._jdf.queryExecution().toString().lower()


def test_kept_tables_leave_no_shuffle_files(spark):
    from pathlib import Path

    from ctxviews.llm.common import CLEANUP, keep

    dirs = [Path(d) for d in spark._jsc.sc().env().blockManager().diskBlockManager().localDirsString()]
    files = lambda: {p.name for d in dirs for p in d.rglob("shuffle_*.data")}
    before, old = files(), spark.conf.get(CLEANUP)
    assert keep(spark.range(5000).repartition("id"), spark).count() == 5000
    own = {p.split("_")[1] for p in files() - before}
    assert len(own) <= 1  # that of the count
    assert spark.conf.get(CLEANUP) == old


def test_packed_prefix_rows():
    import numpy as np

    from ctxviews.llm.jaccard_join import PLACE_BITS, packed

    low = (1 << PLACE_BITS) - 1
    s = np.array([2**64 - 1, 5 << PLACE_BITS, (5 << PLACE_BITS) + 3], np.uint64)
    x = packed(s, np.array([0, 7, low + 9]))
    assert (x & low).tolist() == [0, 7, low]
    assert (x >> PLACE_BITS).tolist() == [-1, 5, 5]
