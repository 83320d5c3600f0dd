"""Repeated passages are judged by words."""

import corpus_pipeline
import numpy as np

from ctxviews.llm import suffix_dedup


def test_short_words_and_chains(spark):
    rng = np.random.default_rng(3)
    word = lambda n: "".join(rng.choice(list("abcdefgh"), n))
    some = lambda n, size=5: " ".join(word(size) for _ in range(n))
    short, fifty, left, right = some(51, 2), some(50, 9), some(40), some(40)  # 152 bytes; 499 bytes
    texts = [f"{some(30)} {short} {some(30)}", f"{some(9)} {short}", f"{some(30)} {fifty} {some(9)}", f"{fifty} {some(30)}", f"{left} {right}", f"{left} {some(20)}", f"{some(20)} {right}", some(60), None, "", short]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: r.text for r in corpus_pipeline.repeat_stage(spark, docs, "").collect()}
    assert got == {i: t.replace(short, "") if t else t for i, t in enumerate(texts) if i != 10}


def test_word_windows_brute_force(spark):
    rng = np.random.default_rng(5)
    pool = ["a", "b", "é"]
    texts = [" ".join(rng.choice(pool, rng.integers(0, 40))) + rng.choice(["", "  ", "\n"]) for _ in range(30)] + ["x\ny  z a b a b", None]
    n, seen, cover = 5, {}, []
    for t in texts:
        b = (t or "").encode()
        _, _, h, g = w = suffix_dedup.word_windows(b, [(0, len(b))], n) if b.split() else ([], [], [], [])
        for x, y in zip(w[0], w[1]):
            assert len(b[x:y].split()) == n and b[x:y] == b[x:y].strip()
            seen[b[x:y]] = seen.get(b[x:y], 0) + 1
        assert len(w[0]) == max(0, len(b.split()) - n + 1)
        cover.append((b, list(zip(w[0], w[1]))))
    want = []
    for b, own in cover:
        gone = np.zeros(len(b), bool)
        for x, y in own:
            if seen[b[x:y]] > 1:
                gone[x:y] = True
        want.append(int(gone.sum()))
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = suffix_dedup.dedup(docs, spark, ["doc_id"], n_words=n).orderBy("doc_id").collect()
    assert [r.n_removed for r in got] == want and sum(want) > 0
