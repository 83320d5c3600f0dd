"""Rows whose ids repeat or are missing."""

import corpus_pipeline
from ctxviews.llm import jaccard_join

A, B, C = (" ".join(f"{c}{i}" for i in range(40)) for c in "abc")
ROWS = [(None, A), (None, B), (None, A), (None, None), (None, None), (5, A + " x"), (5, C), (5, C), (7, C + " y"), (8, ""), (8, ""), (2**60 + 1, "one two three")]


def test_join_keeps_rows_apart(spark):
    got = jaccard_join.join(spark.createDataFrame(ROWS, "doc_id long, text string"), spark).collect()
    key = {}
    for r in got:
        key.setdefault((r.doc_id, r.n_shingles, r.component_id), []).append(r.component_key)
    assert len(got) == len(ROWS)
    assert {k: len(v) for k, v in key.items()} == {(None, 36, 5): 2, (None, 36, None): 1, (None, 0, None): 2, (5, 37, 5): 1, (5, 36, 5): 2, (7, 37, 5): 1, (8, 0, 8): 2, (2**60 + 1, 1, 2**60 + 1): 1}
    a, b, c = key[None, 36, 5] + key[5, 37, 5], key[None, 36, None], key[5, 36, 5] + key[7, 37, 5]
    assert len(set(a)) == len(set(b)) == len(set(c)) == 1 and len({*a, *b, *c}) == 3


def test_stage_keeps_what_nothing_links(spark):
    docs = spark.createDataFrame(ROWS, "doc_id long, text string")
    kept = [tuple(r) for r in corpus_pipeline.near_duplicate_stage(spark, docs, "").collect()]
    want = [(None, B), (None, None), (None, None), (5, A + " x"), (5, C), (8, ""), (2**60 + 1, "one two three")]
    assert sorted(kept, key=repr) == sorted(want, key=repr)
