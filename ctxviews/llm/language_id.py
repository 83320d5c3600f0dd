"""Language identification with error-correcting output codes.

Every language has a codeword of +1/-1 bits; one linear classifier over hashed
byte n-grams predicts each bit.  Decoding weighs each bit's exponential loss by
the bit's accuracy on rows set aside, takes the codeword with the least loss and
flags a text as ambiguous when two codewords are about as near.

Training uses a bounded sample of labelled rows (TRAIN_ROWS); prediction reads
whole texts.  A null text, or one without a letter, is `und` with score 0 and is
not ambiguous.  With no labelled rows every text is `und`; with one language
every text with a letter is that language.  Of codewords with equal loss the first
language by name wins.  Repeated rows are told each and alike, null ids are carried, an
empty table gives no rows; carried columns may have any names but those returned.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import LOWER, sample_rows, ship, steps

TRAIN_ROWS = 3000
BUCKETS = 1 << 12
LETTER = regex.compile(r"\p{L}")


def features(texts: list[str | None]) -> np.ndarray:
    """Hashed counts of byte n-grams (1 to 3) of whole texts: square roots, scaled to length one."""
    out = np.zeros((len(texts), BUCKETS), np.float32)
    for first, raw in steps(texts):
        for i, b in enumerate(raw):
            x = LOWER[np.frombuffer(b"  " + b + b" ", np.uint8)].astype(np.uint32)
            h = x * np.uint32(2654435761)
            total = np.bincount(h >> np.uint32(20), minlength=BUCKETS)
            for _ in range(2):
                h = (h[:-1] ^ x[len(x) - len(h) + 1 :]) * np.uint32(2246822519)
                h ^= h >> np.uint32(15)
                total = total + np.bincount((h * np.uint32(2654435761)) >> np.uint32(20), minlength=BUCKETS)
            out[first + i] = total
    np.sqrt(out, out=out)
    return out / np.maximum(np.linalg.norm(out, axis=1, keepdims=True), 1e-9)


def codewords(n: int) -> np.ndarray:
    """n codewords with a large least distance, and columns that split the languages."""
    if n < 2:
        return np.ones((n, 1), np.float32)
    bits = max(7, int(np.ceil(3 * np.log2(n))) + 4)
    best, far = None, -1
    rng = np.random.default_rng(7)
    for _ in range(300):
        c = np.where(rng.random((n, bits)) < 0.5, -1.0, 1.0)
        flat = np.abs(c.sum(0)) == n
        c[rng.integers(0, n, flat.sum()), np.flatnonzero(flat)] *= -1
        d = ((bits - c @ c.T) / 2 + bits * np.eye(n)).min()
        if d > far:
            best, far = c, d
    return best.astype(np.float32)


@dataclass
class OutputCodes:
    languages: list[str]
    code: np.ndarray
    weights: np.ndarray
    bias: np.ndarray
    trust: np.ndarray  # weight of each bit

    @classmethod
    def fit(cls, x: np.ndarray, labels: list[str], rounds: int = 150) -> OutputCodes:
        langs = sorted(set(labels))
        code = codewords(len(langs))
        y = code[[langs.index(v) for v in labels]] if labels else np.zeros((0, code.shape[1] if len(code) else 1), np.float32)
        aside = np.arange(len(x)) % 5 == 4
        w, b = np.zeros((BUCKETS, y.shape[1]), np.float32), np.zeros(y.shape[1], np.float32)
        xt, yt = x[~aside], y[~aside]
        share = np.array([labels.count(v) for v in langs], np.float64)
        weight = (1 / share[[langs.index(v) for v in labels]])[~aside].astype(np.float32)[:, None] if labels else 1
        weight = weight / np.mean(weight) if labels else 1
        m, v, mb, vb = w * 0, w * 0, b * 0, b * 0
        for t in range(1, rounds + 1 if len(xt) else 1):
            g = -yt * weight / (1 + np.exp(np.clip(yt * (xt @ w + b), -30, 30)))
            gw, gb = xt.T @ g / len(xt) + 1e-6 * w, g.mean(0)
            m, v, mb, vb = 0.9 * m + 0.1 * gw, 0.99 * v + 0.01 * gw**2, 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb**2
            w -= 0.3 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
            b -= 0.3 * (mb / (1 - 0.9**t)) / (np.sqrt(vb / (1 - 0.99**t)) + 1e-8)
        right = ((x[aside] @ w + b) * y[aside] > 0).mean(0) if aside.any() else np.full(y.shape[1], 0.9)
        trust = np.log((right + 0.01) / (1.01 - right)).clip(0.05)
        return cls(langs, code, w, b, trust / trust.sum())

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(number of the language, score, ambiguous)."""
        margin = np.clip(x @ self.weights + self.bias, -6, 6)
        loss = np.exp(-margin[:, None, :] * self.code[None]) @ self.trust
        p = np.exp(-4 * np.log(np.maximum(loss, 1e-6)))
        p /= p.sum(1, keepdims=True)
        order = np.sort(p, axis=1)
        gap = order[:, -1] - (order[:, -2] if p.shape[1] > 1 else 0)
        return loss.argmin(1), p.max(1), gap < 0.2


def fit(labelled: DataFrame, spark: SparkSession, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", rows: int = TRAIN_ROWS) -> OutputCodes:
    """Learn from a bounded sample of labelled rows; features are made on the executors from whole texts."""
    ship(spark)

    def run(batches):
        import pandas as pd

        for pdf in batches:
            for a in range(0, len(pdf), 256):
                part = pdf.iloc[a : a + 256]
                x = features(part["t"].tolist()).astype(np.float16)
                yield pd.DataFrame({"i": part["i"].values, "lang": part["lang"].values, "x": [r.tobytes() for r in x]})

    some = sample_rows(labelled.filter(labelled[lang_col].isNotNull() & labelled[text_col].isNotNull()), id_col, rows)
    got = some.select(labelled[id_col].cast("string").alias("i"), labelled[text_col].alias("t"), labelled[lang_col].alias("lang")).mapInPandas(run, "i string, lang string, x binary").collect()
    got.sort(key=lambda r: (r.i or "", r.lang, r.x))
    x = np.array([np.frombuffer(r.x, np.float16) for r in got], np.float32).reshape(len(got), BUCKETS)
    return OutputCodes.fit(x, [r.lang for r in got])


def identify(docs: DataFrame, spark: SparkSession, model: OutputCodes, carry: list[str], text_col: str = "text") -> DataFrame:
    """The columns `carry`, then lang_pred, score, ambiguous."""
    ship(spark)
    shared = spark.sparkContext.broadcast(model)

    held = text_col if text_col in carry else "ctxviews_text"

    def run(batches):
        m = shared.value
        for pdf in batches:
            for first in range(0, len(pdf), 1000):
                part = pdf.iloc[first : first + 1000]
                texts = part[held].tolist()
                lang, score, unsure = ["und"] * len(texts), [0.0] * len(texts), [False] * len(texts)
                ok = [i for i, t in enumerate(texts) if isinstance(t, str) and m.languages and LETTER.search(t)]
                for a in range(0, len(ok), 256):
                    who, p, flag = m.predict(features([texts[i] for i in ok[a : a + 256]]))
                    for i, k, s, f in zip(ok[a : a + 256], who, p, flag, strict=True):
                        lang[i], score[i], unsure[i] = m.languages[k], float(s), bool(f)
                yield part[carry].assign(lang_pred=lang, score=score, ambiguous=unsure)

    schema = "".join(f"`{c}` {k}, " for c, k in docs.select(*carry).dtypes)
    own = docs.select(*carry) if held == text_col else docs.select(*carry, docs[text_col].alias(held))
    return own.mapInPandas(run, schema + "lang_pred string, score double, ambiguous boolean")
