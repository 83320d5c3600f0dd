"""Token counts by a count-only Viterbi pass over a unigram vocabulary.

Aho-Corasick enumerates every vocabulary piece in a word; the dynamic program
carries, for each position, the best score and the number of pieces only, and
never keeps back pointers or pieces.  Ties follow the tokenizers library: ends
are filled from earlier starts first and a later way must be strictly better, so
the longest last piece wins; a character that begins no one-character piece costs
the least score minus ten; neighbouring unknown characters fuse and count as
their bytes (byte fallback).

No piece of the vocabulary has a word-start mark after another character (checked
when it is read; otherwise texts are not cut), so words are independent and each
distinct word is solved once for a partition's working set.  Null and empty texts
have no tokens; texts of any length are counted whole.  Repeated rows are counted
each, null ids are carried, an empty table gives no rows; no other column is read.
"""

from __future__ import annotations

from collections import Counter

import ahocorasick
import regex
from pyspark.sql import DataFrame, SparkSession

from .common import ship

MARK = "▁"
UNKNOWN_PENALTY = 10.0
HELD_WORDS = 400_000


def read_pieces(path: str) -> list[tuple[str, float]]:
    """Pieces and scores of a sentencepiece model file, in the order of their ids."""
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=path)
    return [(sp.id_to_piece(i), sp.get_score(i)) for i in range(sp.get_piece_size())]


class UnigramCounter:
    def __init__(self, pieces: list[tuple[str, float]]):
        self.auto = ahocorasick.Automaton()
        for piece, score in pieces:
            if piece:
                self.auto.add_word(piece, (len(piece), score))
        self.auto.make_automaton()
        self.unknown = min(s for _, s in pieces) - UNKNOWN_PENALTY
        known = {p for p, _ in pieces}
        self.bytes = all(f"<0x{b:02X}>" in known for b in range(256))
        apart = not any(MARK in p.lstrip(MARK) for p in known) and all(float(s).is_integer() for _, s in pieces)
        self.cut = regex.compile(f"{MARK}+[^{MARK}]*|[^{MARK}]+") if apart else None
        self.held: dict[str, int] = {}

    def word(self, w: str) -> int:
        """Pieces on the best path through w."""
        n = len(w)
        ends: list[list[tuple[int, float]]] = [[] for _ in range(n)]
        single = [False] * n
        for end, (size, score) in self.auto.iter(w):
            ends[end].append((size, score))
            if size == 1:
                single[end] = True
        best = [0.0] * (n + 1)
        count = [0] * (n + 1)
        open_bytes = [False] * (n + 1)  # the best path ends in unknown characters
        for end in range(n):
            top, pick, unk = None, 0, False
            options = ends[end]
            if not single[end]:
                options = [*options, (1, self.unknown)]
            options.sort(reverse=True)  # earlier starts first
            for size, score in options:
                s = best[end + 1 - size] + score
                if top is None or s > top:
                    top, pick, unk = s, size, size == 1 and not single[end]
            start = end + 1 - pick
            best[end + 1] = top
            if not unk:
                count[end + 1] = count[start] + 1
            elif self.bytes:
                count[end + 1] = count[start] + len(w[end].encode("utf-8", "surrogatepass"))
            else:
                count[end + 1] = count[start] + (not open_bytes[start])
            open_bytes[end + 1] = unk
        return count[n]

    def text(self, t: str | None) -> int:
        if not t:
            return 0
        t = MARK + t.replace(" ", MARK)
        if not self.cut:
            return self.word(t)
        if len(self.held) > HELD_WORDS:
            self.held = {}
        held, total = self.held, 0
        for w, k in Counter(self.cut.findall(t)).items():
            c = held.get(w)
            if c is None:
                c = self.word(w)
                if len(w) < 64:
                    held[w] = c
            total += k * c
        return total


_loaded: dict[str, UnigramCounter] = {}


def load(path: str) -> UnigramCounter:
    if path not in _loaded:
        _loaded[path] = UnigramCounter(read_pieces(path))
    return _loaded[path]


def count_tokens(docs: DataFrame, spark: SparkSession, path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """id_col, n_tokens long for every row."""
    ship(spark)

    def run(batches):
        import pandas as pd

        counter = load(path)
        for pdf in batches:
            yield pd.DataFrame({id_col: pdf["i"].values, "n_tokens": [counter.text(t if isinstance(t, str) else None) for t in pdf["t"]]})

    return docs.select(docs[id_col].alias("i"), docs[text_col].alias("t")).mapInPandas(run, f"`{id_col}` {dict(docs.dtypes)[id_col]}, n_tokens long")
