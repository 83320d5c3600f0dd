"""Recall of the cap filters by cosine band, each pair on its own, and the code's growth."""

import numpy as np
import pytest

from ctxviews.llm import cap_neardup


def mates(n: int, cosine: float, dim: int = 64, seed: int = 3) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    x = rng.normal(size=(n, dim))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    g = rng.normal(size=x.shape)
    g -= (g * x).sum(1, keepdims=True) * x
    g /= np.linalg.norm(g, axis=1, keepdims=True)
    return x, cosine * x + np.sqrt(1 - cosine * cosine) * g


@pytest.mark.parametrize("cosine", [0.9501, 0.955, 0.96, 0.97, 0.98, 0.99, 0.999])
def test_filters_meet_in_every_band(cosine):
    x, y = mates(600, cosine)
    met = [bool(np.intersect1d(a, b).size) for a, b in zip(cap_neardup.decode(x), cap_neardup.decode(y), strict=True)]
    assert np.mean(met) >= 0.97


@pytest.mark.parametrize("words", [32, 64])
def test_more_code_words_keep_the_recall(words):
    x, y = mates(150, 0.9501)
    met = [bool(np.intersect1d(a, b).size) for a, b in zip(cap_neardup.decode(x, words), cap_neardup.decode(y, words), strict=True)]
    assert np.mean(met) >= 0.9


def test_list_decoding_finds_all_exceeding_directions():
    x, _ = mates(20, 0.99)
    for mine, found in zip(x, cap_neardup.decode(x), strict=True):
        want = set()
        for t in range(cap_neardup.TABLES):
            rotation, parts, code_words, level = cap_neardup.code(64, t)
            y, score = mine @ rotation, np.zeros(1)
            for p, w in zip(parts, code_words, strict=True):
                score = (score[:, None] + (w @ y[p])[None]).ravel()
            least = min(level, np.sort(score)[-cap_neardup.LEAST])
            want |= {(64 << 48) + (t << 40) + f for f in np.flatnonzero(score >= least - 1e-12).tolist()}
        assert set(found.tolist()) == want


def test_links_by_band_end_to_end(spark):
    parts, rows = [], []
    for k, c in enumerate((0.951, 0.955, 0.965, 0.975, 0.985, 0.999)):
        parts += [(k, *xy) for xy in zip(*mates(250, c, seed=10 + k), strict=True)]
    for i, (_, x, y) in enumerate(parts):
        rows += [(2 * i, x.tolist()), (2 * i + 1, y.tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = {r.vec_id: r for r in cap_neardup.near_duplicates(df, spark).collect()}
    for band in range(6):
        ids = [2 * i for i, p in enumerate(parts) if p[0] == band]
        assert np.mean([got[i + 1].component_id == i and got[i].n_links == 1 for i in ids]) >= 0.95


def test_rows_without_id_and_clashing_columns(spark):
    rows = [(None, [1.0, 0.0], 1), (2, [1.0, 0.0], 2), (3, [0.0, 1.0], 3), (3, [0.0, 1.0], 4), (5, None, 5)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, rep int")
    got = sorted(((r.vec_id, r.n_links, r.component_id, r.kept) for r in cap_neardup.near_duplicates(df, spark).collect()), key=str)
    assert got == sorted([(None, 1, 2, False), (2, 1, 2, True), (3, 1, 3, True), (3, 1, 3, True), (5, 0, 5, True)], key=str)
