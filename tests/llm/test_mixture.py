"""Targets, many sources and wide ids of the packing operator."""

import numpy as np
import public_tokenizers as P
import pytest

from ctxviews.llm import packing

PATH = P.path("byte_bpe_50k.json")


def whole(rows, n_docs):
    """Every token lies in one piece, every sequence is gapless; returns pieces by sequence."""
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r.doc_id, []).append((r.start, r.length, r.doc_tokens))
        by_seq.setdefault(r.sequence_id, []).append((r.offset, r.length, r.queue))
    assert len(by_doc) == n_docs
    for parts in by_doc.values():
        at = 0
        for start, length, total in sorted(parts):
            assert start == at
            at += length
        assert at == total
    for parts in by_seq.values():
        at = 0
        for offset, length, _ in sorted(parts):
            assert offset == at
            at += length
        assert at == 1024 or at & (at - 1) == 0
    return by_seq


def test_apportion_keeps_caps_and_sums():
    rng = np.random.default_rng(2)
    for _ in range(300):
        w = rng.integers(1, 50, rng.integers(1, 9)).tolist()
        caps = [x * 7 for x in w]
        x = int(rng.integers(0, sum(caps) + 1))
        got = packing.apportion(x, w, caps)
        assert sum(got) == x and all(g <= c for g, c in zip(got, caps, strict=True))


def test_many_small_queues_never_overrun():
    sizes = [5000] + [1] * 500
    m = packing.Mixture(sizes, segment=2)
    total = np.zeros(len(sizes), np.int64)
    for k in range(m.segments):
        _, take = m.segment(k)
        assert (take >= 0).all()
        total += take.sum(0)
    assert total.tolist() == sizes


def test_targets_hold_until_a_queue_is_used_up():
    m = packing.Mixture([400_000, 400_000, 50_000], segment=64, weights=[3, 1, 0])
    first = m.segment(0)[1]
    assert (np.abs(first / 1024 - [0.75, 0.25, 0]) < 0.01).all()
    total = sum(m.segment(k)[1].sum(0) for k in range(m.segments))
    assert total.tolist() == [400_000, 400_000, 50_000]
    last = m.segment(m.segments - 1)[1]
    assert last[:, 0].sum() == 0 and last[-10:, 2].sum() > 0


def test_targets_in_tables(spark):
    rows = [(i, "word " * 400, "a" if i % 2 else "b") for i in range(120)] + [(200, None, None), (201, "", "c")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    seqs = whole(packing.pack(df, spark, PATH, targets={"a": 3, "b": 1}).collect(), 122)
    shares = [sum(n for _, n, q in seqs[s] if q == "a") / 1024 for s in sorted(seqs)[:20]]
    assert np.allclose(shares, 0.75, atol=0.01)


@pytest.mark.parametrize("slice_rows", [50, 50_000])
def test_more_sources_than_queues(spark, monkeypatch, slice_rows):
    monkeypatch.setattr(packing, "MAX_QUEUES", 3)
    monkeypatch.setattr(packing, "SLICE_ROWS", slice_rows)
    rows = [(i, f"word{i} " * (20 + i % 30), f"s{i % 12}") for i in range(600)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(5)
    got = packing.pack(df, spark, PATH).collect()
    seqs = whole(got, 600)
    source = {i: s for i, _, s in rows}
    total = {}
    for r in got:
        total[source[r.doc_id]] = total.get(source[r.doc_id], 0) + r.length
    half = {}
    for r in got:
        if r.sequence_id < len(seqs) // 2:
            half[source[r.doc_id]] = half.get(source[r.doc_id], 0) + r.length
    for s, n in total.items():  # each source is half used up at the middle, within a few documents
        assert abs(half.get(s, 0) / n - 0.5) < 0.08, s


def test_repeated_rows_and_clashing_columns(spark):
    rows = [(1, "same text", "x", 7, b"z")] * 3 + [(2, None, None, None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, n long, ids binary")
    got = packing.pack(df, spark, PATH).collect()
    n = {r.doc_id: r.doc_tokens for r in got}
    assert sum(r.length for r in got) == 3 * n[1] + n[2] and n[2] == 1


def test_wide_ids(tmp_path):
    import json

    spec = {"added_tokens": [{"id": 70000, "content": "<x>"}], "model": {"vocab": {"a": 0}}}
    (tmp_path / "v.json").write_text(json.dumps(spec))
    assert packing.id_type(str(tmp_path / "v.json"), 0) is np.uint32 and packing.id_type(PATH, 0) is np.uint16
