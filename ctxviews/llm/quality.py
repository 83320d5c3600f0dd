"""Document quality from random-indexing word vectors and a small network.

Units are words and word shapes (case, length, symbols), hashed to buckets.  Each
bucket has a fixed sparse ternary index vector; a bucket's context vector is the
sum of the index vectors of the units beside it.  A document is the mean and the
spread of its units' vectors; a two-layer network scores it and a temperature
fitted on rows set aside makes the scores probabilities.

Vectors and network come from a bounded sample of labelled rows (TRAIN_ROWS);
scoring reads whole texts.  Null and empty texts have zero vectors and get the
network's score for those; with labels of one kind only, that label's share is
the score.  Repeated rows are scored each and alike, null ids are carried (and never
labelled), an empty table gives no rows; carried columns may have any name but score.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import sample_rows, ship, steps, words

TRAIN_ROWS = 6000
BUCKETS = 1 << 14
SHAPES = 512
DIM = 24
WINDOW = 2
POOLED = 4 * DIM + 4


def index_vectors() -> np.ndarray:
    rng = np.random.default_rng(11)
    out = np.zeros((BUCKETS + SHAPES, DIM), np.float32)
    for sign in (1, 1, -1, -1):
        out[np.arange(len(out)), rng.integers(0, DIM, len(out))] += sign
    return out


def units(encoded: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, word bucket, shape bucket) of every word."""
    buf, start, end, doc, h = words(encoded, lower=False)
    kind = np.zeros((4, 256), np.int32)
    kind[0, 65:91] = 1  # upper case
    kind[1, 48:58] = 1  # digits
    kind[2, [*b"!#$%&*+<=>?@[\\]^_`{|}~/"]] = 1  # symbols
    kind[3, [*b".,;:'\"-()"]] = 1  # punctuation
    size = end - start
    sums = []
    for k in kind:
        c = np.concatenate([[0], np.cumsum(k[buf])])
        sums.append(c[end] - c[start])
    upper, digit, symbol, mark = sums
    shape = np.minimum(np.log2(np.maximum(size, 1)).astype(np.int64), 7)
    shape = shape * 3 + np.where(upper == 0, 0, np.where(upper <= 1, 1, 2))
    shape = shape * 2 + (digit > 0)
    shape = shape * 3 + np.minimum(symbol, 2)
    shape = shape * 2 + (mark > 0)
    return doc, (h % np.uint64(BUCKETS)).astype(np.int64), BUCKETS + shape % SHAPES


def context_sums(texts: list[str | None]) -> np.ndarray:
    """Sums of the index vectors around each bucket."""
    index = index_vectors()
    out = np.zeros_like(index)
    for _, raw in steps(texts):
        doc, word, shape = units(raw)
        for k in range(1, WINDOW + 1):
            same = doc[k:] == doc[:-k]
            a, b = np.arange(len(doc) - k)[same], np.arange(k, len(doc))[same]
            for u in (word, shape):
                for v in (word, shape):
                    np.add.at(out, u[a], index[v[b]])
                    np.add.at(out, u[b], index[v[a]])
    return out


def pool(texts: list[str | None], vectors: np.ndarray) -> np.ndarray:
    """Of whole texts: mean and spread of word and of shape vectors, agreement of neighbouring
    word vectors, share of words equal to the one before or two before, log number of words."""
    out = np.zeros((len(texts), POOLED), np.float32)
    for first, raw in steps(texts):
        doc, word, shape = units(raw)
        if not len(doc):
            continue
        here, at, n = np.unique(doc, return_index=True, return_counts=True)
        row = first + here
        for j, u in enumerate((word, shape)):
            v = vectors[u]
            mean = np.add.reduceat(v, at, axis=0) / n[:, None]
            square = np.add.reduceat(v * v, at, axis=0) / n[:, None]
            out[row, 2 * j * DIM : (2 * j + 1) * DIM] = mean
            out[row, (2 * j + 1) * DIM : (2 * j + 2) * DIM] = np.sqrt(np.maximum(square - mean * mean, 0))
        out[row, -1] = np.log1p(n) / 5
        for j, k in enumerate((1, 2)):
            same = (doc[k:] == doc[:-k]) & (word[k:] == word[:-k])
            out[row, 4 * DIM + j] = np.bincount(doc[k:][same], minlength=len(raw))[here] / n
        dot = (vectors[word[1:]] * vectors[word[:-1]]).sum(1) * (doc[1:] == doc[:-1])
        out[row, 4 * DIM + 2] = np.bincount(doc[1:], dot, minlength=len(raw))[here] / n
    return out


@dataclass
class Network:
    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float
    constant: float | None = None

    @classmethod
    def fit(cls, x: np.ndarray, y: np.ndarray, hidden: int = 32, epochs: int = 100) -> Network:
        d = x.shape[1]
        if len(set(y.tolist())) < 2:
            return cls(np.zeros(d), np.ones(d), np.zeros((d, 1)), np.zeros(1), np.zeros(1), 0.0, 1.0, float(y.mean()) if len(y) else 0.5)
        rng = np.random.default_rng(5)
        mean, scale = x.mean(0), x.std(0) + 1e-3
        x = (x - mean) / scale
        aside = np.arange(len(x)) % 5 == 4
        xt, yt = x[~aside], y[~aside].astype(np.float32)
        p = [rng.normal(0, d**-0.5, (d, hidden)), np.zeros(hidden), rng.normal(0, hidden**-0.5, hidden), np.zeros(1)]
        m, v, t = [a * 0 for a in p], [a * 0 for a in p], 0
        for _ in range(epochs):
            order = rng.permutation(len(xt))
            for a in range(0, len(order), 128):
                xb, yb = xt[order[a : a + 128]], yt[order[a : a + 128]]
                h = np.maximum(xb @ p[0] + p[1], 0)
                e = (1 / (1 + np.exp(-np.clip(h @ p[2] + p[3][0], -30, 30))) - yb) / len(xb)
                dh = e[:, None] * p[2] * (h > 0)
                grads = [xb.T @ dh + 5e-3 * p[0], dh.sum(0), h.T @ e + 5e-3 * p[2], e.sum(keepdims=True)]
                t += 1
                for k, g in enumerate(grads):
                    m[k] = 0.9 * m[k] + 0.1 * g
                    v[k] = 0.999 * v[k] + 0.001 * g * g
                    p[k] = p[k] - 0.003 * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.999**t)) + 1e-8)
        net = cls(mean, scale, p[0], p[1], p[2], float(p[3][0]), 1.0)
        if aside.any():
            z, ya = net.logit(x[aside] * scale + mean), y[aside]
            loss = {s: np.logaddexp(0, np.where(ya == 1, -z, z) / s).mean() for s in np.geomspace(0.3, 6, 40)}
            net.temperature = float(min(loss, key=loss.get))
        return net

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.maximum((x - self.mean) / self.scale @ self.w1 + self.b1, 0) @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(x), self.constant)
        return 1 / (1 + np.exp(-np.clip(self.logit(x) / self.temperature, -500, 500)))


@dataclass
class QualityModel:
    vectors: np.ndarray
    net: Network


def fit(docs: DataFrame, labels: DataFrame, spark: SparkSession, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", rows: int = TRAIN_ROWS) -> QualityModel:
    """Learn from a bounded sample of rows that have a label."""
    ship(spark)
    some = sample_rows(labels.filter(labels[label_col].isNotNull() & labels[id_col].isNotNull()).select(labels[id_col].alias("i"), labels[label_col].cast("int").alias("y")).distinct(), "i", rows)
    train = docs.select(docs[id_col].alias("i"), docs[text_col].alias("t")).join(F.broadcast(some), "i")

    def context(batches):
        import pandas as pd

        total = None
        for pdf in batches:
            c = context_sums(pdf["t"].tolist())
            total = c if total is None else total + c
        if total is not None:
            at = np.flatnonzero(np.abs(total).sum(1))
            if not len(at):  # no word has a neighbour
                return
            yield pd.DataFrame({"part": at >> 10, "at": at, "v": [total[i].tolist() for i in at]})

    cells = train.mapInPandas(context, "part long, at long, v array<float>")
    sums = cells.groupBy("at").agg(F.array(*[F.sum(F.col("v")[k]) for k in range(DIM)]).alias("v")).collect()  # BUCKETS + SHAPES rows at most
    vectors = np.zeros((BUCKETS + SHAPES, DIM), np.float32)
    for r in sums:
        vectors[r["at"]] = r["v"]
    vectors -= vectors.mean(0)
    vectors /= np.maximum(np.linalg.norm(vectors, axis=1, keepdims=True), 1e-6)
    unseen = ~vectors.any(1)
    vectors[unseen] = 0
    shared = spark.sparkContext.broadcast(vectors)

    def pooled(batches):
        import pandas as pd

        for pdf in batches:
            x = pool(pdf["t"].tolist(), shared.value)
            yield pd.DataFrame({"i": pdf["i"].values, "y": pdf["y"].values, "x": [r.tobytes() for r in x]})

    got = sorted(train.mapInPandas(pooled, "i long, y int, x binary").collect(), key=lambda r: (r.i, r.y))
    x = np.array([np.frombuffer(r.x, np.float32) for r in got], np.float64).reshape(len(got), POOLED)
    return QualityModel(vectors, Network.fit(x, np.array([r.y for r in got])))


def score(docs: DataFrame, spark: SparkSession, model: QualityModel, carry: list[str], text_col: str = "text") -> DataFrame:
    """The columns `carry`, then score double."""
    ship(spark)
    shared = spark.sparkContext.broadcast(model)

    held = text_col if text_col in carry else "ctxviews_text"

    def run(batches):
        m = shared.value
        for pdf in batches:
            for a in range(0, len(pdf), 500):
                part = pdf.iloc[a : a + 500]
                yield part[carry].assign(score=m.net.score(pool(part[held].tolist(), m.vectors)))

    schema = "".join(f"`{c}` {k}, " for c, k in docs.select(*carry).dtypes)
    own = docs.select(*carry) if held == text_col else docs.select(*carry, docs[text_col].alias(held))
    return own.mapInPandas(run, schema + "score double")
