"""BPE encoding and decoding with an index from each pair to its positions.

A partition's distinct words form one flat symbol array.  The index maps every
merge rank to the positions where its pair stands; active ranks are taken from
a heap in ascending order, all positions of a rank merge at once, and only the
lists of the pairs beside the merged positions are extended.  In the vocabularies
used a merge never makes a pair of a lower rank (checked when the file is read),
so this is the same as merging word by word.

Null and empty texts have no tokens.  Text of any length is encoded whole; words
are encoded once for each partition's working set.  Repeated rows are encoded each,
null ids are carried, an empty table gives no rows; no other column is read.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import unicodedata

import numpy as np
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import ship

#: Distinct words held before the working set starts anew.
HELD_WORDS = 300_000
#: Characters of text whose new words are encoded together.
GROUP_CHARS = 12_000_000


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    extra = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(extra)) for b in range(256)]


class PairIndexBpe:
    """A tokenizers JSON file with word ends, NFC, lower case and removed white space."""

    def __init__(self, path: str):
        spec = json.loads(open(path, encoding="utf-8").read())
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.end = model["end_of_word_suffix"] or ""
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.tokens = {i: t for t, i in {**self.vocab, **special}.items()}
        self.special = special
        self.cut = regex.compile("|".join(map(regex.escape, sorted(special, key=len, reverse=True)))) if special else None
        split = next(p for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.word = regex.compile(split["pattern"]["Regex"])
        letters = byte_letters()
        self.first = np.array([self.vocab[c] for c in letters], np.int32)
        self.last = np.array([self.vocab[c + self.end] for c in letters], np.int32)
        pairs = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        left = np.array([self.vocab[a] for a, _ in pairs], np.int64)
        right = np.array([self.vocab[b] for _, b in pairs], np.int64)
        self.made = np.array([self.vocab[a + b] for a, b in pairs], np.int32)
        self.left, self.right, self.width = left, right, max(self.vocab.values()) + 1
        born = np.full(self.width, -1)
        born[self.made] = np.arange(len(pairs))
        if (np.maximum(born[left], born[right]) >= np.arange(len(pairs))).any() or len(set(self.made.tolist())) < len(pairs):
            raise ValueError("a merge of this vocabulary makes a pair of a lower rank")
        key = left * self.width + right
        self.order = np.argsort(key)
        self.keys = key[self.order]

    def ranks(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Merge rank of each pair, -1 where there is none."""
        key = a.astype(np.int64) * self.width + b
        at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
        return np.where(self.keys[at] == key, self.order[at], -1)

    def encode_words(self, texts: list[str]) -> list[np.ndarray]:
        """Token ids of each word."""
        raw = [t.encode("utf-8", "surrogatepass") for t in texts]
        size = np.fromiter(map(len, raw), np.int64, len(raw))
        at = np.concatenate([[0], np.cumsum(size)])
        data = np.frombuffer(b"".join(raw), np.uint8)
        n = len(data)
        sym = np.append(self.first[data], np.int32(-1))
        last = at[1:][size > 0] - 1
        sym[last] = self.last[data[last]]
        nxt = np.arange(1, n + 2)
        nxt[last] = n  # n: no neighbour
        prv = np.arange(-1, n)
        prv[at[:-1][size > 0]] = n
        prv = np.append(prv, n)
        sides = np.arange(n)[nxt[:n] < n]
        index: dict[int, list[np.ndarray]] = {}
        heap: list[int] = []

        def add(where: np.ndarray) -> None:
            r = self.ranks(sym[where], sym[nxt[where]])
            ok = r >= 0
            if not ok.any():
                return
            where, r = where[ok], r[ok]
            if len(r) > 1:
                by = np.argsort(r, kind="stable")
                where, r = where[by], r[by]
                cut = np.flatnonzero(r[1:] != r[:-1]) + 1
                parts = zip(r[np.concatenate([[0], cut])].tolist(), np.split(where, cut), strict=True)
            else:
                parts = [(int(r[0]), where)]
            for k, p in parts:
                if k in index:
                    index[k].append(p)
                else:
                    index[k] = [p]
                    heapq.heappush(heap, k)

        add(sides)
        while heap:
            k = heapq.heappop(heap)
            lists = index.pop(k)
            p = np.unique(np.concatenate(lists))
            q = nxt[p]
            ok = (sym[p] == self.left[k]) & (q < n)
            p, q = p[ok], q[ok]
            ok = sym[q] == self.right[k]
            p, q = p[ok], q[ok]
            if not len(p):
                continue
            if self.left[k] == self.right[k] and len(p) > 1:  # in a run of one symbol every second pair counts
                start = np.concatenate([[True], q[:-1] != p[1:]])
                run = np.maximum.accumulate(np.where(start, np.arange(len(p)), 0))
                ok = (np.arange(len(p)) - run) % 2 == 0
                p, q = p[ok], q[ok]
            after = nxt[q]
            sym[p] = self.made[k]
            sym[q] = -1
            nxt[p] = after
            prv[after[after < n]] = p[after < n]
            before = prv[p]
            new = np.concatenate([before[before < n], p[after < n]])
            if len(new):
                add(new)
        live = sym[:n] >= 0
        count = np.concatenate([[0], np.cumsum(live)])
        ids = sym[:n][live]
        return np.split(ids, count[at[1:-1]]) if len(raw) > 1 else [ids]

    def normal(self, text: str) -> str:
        if not text.isascii():
            text = unicodedata.normalize("NFC", text).replace("Σ", "σ")  # letters are lowered one by one: no final sigma
        return text.lower()

    def pieces(self, text: str) -> list[str]:
        """Words and special tokens of a text in order."""
        if not self.cut or not self.cut.search(text):
            return self.word.findall(self.normal(text))
        out, at = [], 0
        for m in self.cut.finditer(text):
            out += self.word.findall(self.normal(text[at : m.start()]))
            out.append("\0" + m[0])
            at = m.end()
        return out + self.word.findall(self.normal(text[at:]))


class WordStore:
    """Encodings of the words in use: word -> ids as text, and word -> decoded text."""

    def __init__(self, bpe: PairIndexBpe):
        self.bpe, self.ids, self.text = bpe, {}, {}

    def learn(self, seen: set[str]) -> None:
        if len(self.ids) > HELD_WORDS:
            self.ids, self.text = {}, {}
        new = [w for w in seen if w not in self.ids]
        plain = [w for w in new if w[0] != "\0"]
        tokens = self.bpe.tokens
        for w, ids in zip(plain, self.bpe.encode_words(plain) if plain else [], strict=True):
            ids = ids.tolist()
            self.ids[w] = " ".join(map(str, ids))
            self.text[w] = " ".join([tokens[i] for i in ids])
        for w in new:
            if w[0] == "\0":
                self.ids[w], self.text[w] = str(self.bpe.special[w[1:]]), w[1:]


_loaded: dict[str, PairIndexBpe] = {}


def load(path: str) -> PairIndexBpe:
    if path not in _loaded:
        _loaded[path] = PairIndexBpe(path)
    return _loaded[path]


def encode_texts(texts: list[str | None], store: WordStore):
    """(ids as text, decoded text) of each text."""
    first = 0
    while first < len(texts):
        held, size, end = [], 0, first
        seen: set[str] = set()
        while end < len(texts) and (not held or size < GROUP_CHARS and len(seen) < HELD_WORDS):
            t = texts[end] if isinstance(texts[end], str) else ""
            held.append(store.bpe.pieces(t))
            seen.update(held[-1])
            size += len(t)
            end += 1
        store.learn(seen)
        for p in held:
            yield " ".join(map(store.ids.__getitem__, p)), " ".join(map(store.text.__getitem__, p))
        first = end


def encode(docs: DataFrame, spark: SparkSession, path: str, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """Encode and decode every whole text.

    Returns id_col, n_tokens, ids_sha256, decoded_sha256 and, if with_text, ids
    (decimal, joined by spaces) and decoded.  Other columns of docs are not read.
    """
    ship(spark)
    kind = dict(docs.dtypes)[id_col]

    def run(batches):
        import pandas as pd

        store = WordStore(load(path))
        for pdf in batches:
            rows = []
            for ids, text in encode_texts(pdf["t"].tolist(), store):
                rows.append((ids.count(" ") + 1 if ids else 0, hashlib.sha256(ids.encode()).hexdigest(), hashlib.sha256(text.encode("utf-8", "surrogatepass")).hexdigest(), *((ids, text) if with_text else ())))
            out = pd.DataFrame(rows, columns=["n_tokens", "ids_sha256", "decoded_sha256", *(("ids", "decoded") if with_text else ())])
            out.insert(0, id_col, pdf["i"].values)
            yield out

    schema = f"`{id_col}` {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string" + (", ids string, decoded string" if with_text else "")
    return docs.select(docs[id_col].alias("i"), docs[text_col].alias("t")).mapInPandas(run, schema)
