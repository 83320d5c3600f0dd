"""Removal of byte strings that repeat, by suffix arrays.

A byte goes if a string of `length` bytes covers it that also starts anywhere
else - in another document or the same one; overlaps count, and strings are
judged on the input.

Every window of `length` bytes has one anchor: its k-gram of least hash, the
leftmost on ties.  The windows of a document with the same anchor are a run; the
run's bytes are its context.  Equal windows have equal anchors, so

1. anchors that occur once need no more work;
2. contexts that occur twice or more repeat as a whole;
3. the other contexts of shared anchors are cut into slots by the windows' distance
   to the anchor.  All windows of a slot hold its core, so only slots with equal
   cores meet: in one task, which writes each slot as its bytes around one symbol
   for the core and sorts the suffixes of their concatenation (linear grouping).  A
   window repeats if a neighbour in the suffix array shares its whole length.

Copies of a passage are thus counted, not gathered, and only distinct slots around
shared cores are sorted.  Cores with more than HOT_SLOTS slots are not gathered:
their windows are counted by hash, in as many tasks as needed.

A length can also be given in words.  The symbols are then words with the white space
that follows them instead of bytes: a repeated string of w words begins with w - 1 such
symbols that repeat.  The strings of w words in what the suffix arrays found are counted
by hash once more, with their last word, and only repeated ones go.

Null and empty texts have no bytes and no spans.  Texts shorter than `length` are
kept whole.  Repeated rows count as further occurrences, and each gets the same result;
rows without an id are told apart by their texts.  An empty table gives no rows.
"""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACE, keep, prefix_hash, release, ship, small, span_hash, steps, trim
from .suffix_array import suffix_array

HOT_SLOTS = 10_000
#: Symbols that one suffix array takes, and slots that one group has on average.
SORT_SYMBOLS = 300_000
GROUP_SLOTS = 8_000
#: Slots of a context at most.
SLOTS = 5
#: Windows of one document that are anchored together.
SEGMENT = 1 << 22


def byte_symbols(encoded: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(bytes of all texts, number of each text's)."""
    return np.frombuffer(b"".join(encoded), np.uint8), np.fromiter(map(len, encoded), np.int64, len(encoded))


def word_symbols(encoded: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(64-bit hashes of each word with the white space up to the next word, number of each text's): all words but a text's last."""
    buf = np.frombuffer(b"\n".join(encoded), np.uint8)
    size = np.fromiter(map(len, encoded), np.int64, len(encoded))
    first = np.concatenate([[0], np.cumsum(size + 1)[:-1]]).astype(np.int64)
    word = ~SPACE[buf]
    start = np.flatnonzero(word & ~np.concatenate([[False], word[:-1]]))
    doc = np.searchsorted(first, start, "right") - 1
    pair = np.flatnonzero(doc[1:] == doc[:-1])
    return span_hash(prefix_hash(buf), start[pair], start[pair + 1]), np.bincount(doc[pair], minlength=len(encoded)).astype(np.int64)


def anchors(m: int, prefix: np.ndarray, length: int, k: int) -> np.ndarray:
    """Position of the anchor of each window start among m k-grams."""
    w = length - k + 1
    at = np.arange(m)
    v = (span_hash(prefix, at, at + k) >> np.uint64(23) << np.uint64(23)) | at.astype(np.uint64)
    pad = -m % w
    v = np.concatenate([v, np.full(pad, np.iinfo(np.uint64).max, np.uint64)]).reshape(-1, w)
    ahead = np.minimum.accumulate(v, 1).ravel()
    back = np.minimum.accumulate(v[:, ::-1], 1)[:, ::-1].ravel()
    n = m - w + 1
    return (np.minimum(back[:n], ahead[w - 1 : w - 1 + n]) & np.uint64((1 << 23) - 1)).astype(np.int64)


def runs(data: np.ndarray, size: np.ndarray, length: int, k: int):
    """(document, first window, last window, anchor, anchor hash, context hash) of every run, as arrays."""
    if len(data) < length:
        return None
    prefix = prefix_hash(data)
    end = np.cumsum(size)
    out = []
    for a in range(0, len(data) - length + 1, SEGMENT):
        b = min(len(data), a + SEGMENT + length - 1)
        # hashes do not depend on where the slice starts
        pos = a + anchors(b - a - k + 1, prefix[: b + 1] if a == 0 else prefix_hash(data[a:b]), length, k)
        start = a + np.arange(len(pos))
        doc = np.searchsorted(end, start, "right")
        ok = start + length <= end[np.minimum(doc, len(end) - 1)]
        start, doc, pos = start[ok], doc[ok], pos[ok]
        if not len(start):
            continue
        new = np.flatnonzero(np.concatenate([[True], (pos[1:] != pos[:-1]) | (doc[1:] != doc[:-1]) | (start[1:] != start[:-1] + 1)]))
        last = np.append(new[1:] - 1, len(start) - 1)
        p = pos[new]
        out.append((doc[new], start[new], start[last], p, span_hash(prefix, p, p + k), span_hash(prefix, start[new], start[last] + length)))
    if not out:
        return None
    doc, i0, i1, p, anchor, context = (np.concatenate(x) for x in zip(*out, strict=True))
    begin = (end - size)[doc]
    return doc, i0 - begin, i1 - begin, p - begin, anchor.view(np.int64), context.view(np.int64)


def gathered(doc, i0, i1, p, anchor, ctx) -> tuple[np.ndarray, np.ndarray, list]:
    """(first of each document's equal contexts, how many there are, their first windows if more than one)."""
    order = np.lexsort((i0, ctx, anchor, doc))
    same = (np.diff(doc[order]) == 0) & (np.diff(anchor[order]) == 0) & (np.diff(ctx[order]) == 0)
    cut = np.flatnonzero(np.concatenate([[True], ~same]))
    times = np.diff(np.append(cut, len(order)))
    more: list = [None] * len(cut)
    for g in np.flatnonzero(times > 1).tolist():
        more[g] = i0[order[cut[g] : cut[g] + times[g]]]
    return order[cut], times, more


def repeated_windows(pieces: list[np.ndarray], length: int) -> list[tuple[int, int, int]]:
    """(number of the piece, first, last) of runs of windows of `length` symbols that also start elsewhere in the pieces.

    Pieces are sequences of integers from 0 on.
    """
    size = np.array([len(c) for c in pieces])
    at = np.concatenate([[0], np.cumsum(size + 1)])
    m = len(pieces)
    body = np.zeros(at[-1], np.int64)
    inside = np.ones(at[-1], bool)
    inside[at[1:] - 1] = False
    body[inside] = np.concatenate(pieces)
    text = np.append(body + m + 1, 0)
    text[at[1:] - 1] = np.arange(m, 0, -1)  # separators: each once, lower than all symbols
    order = suffix_array(text)
    doc = np.searchsorted(at, np.arange(at[-1]), "right") - 1
    wide = at[doc + 1] - 1 - np.arange(at[-1]) >= length
    order = order[order < at[-1]]
    order = order[wide[order]]  # a suffix between two that share `length` symbols has as many
    h = span_hash(prefix_hash(body), order, order + length)
    same = h[1:] == h[:-1]
    hit = np.zeros(at[-1] + 1, bool)
    hit[order[:-1][same]] = True
    hit[order[1:][same]] = True
    edge = np.flatnonzero(np.diff(np.concatenate([[False], hit])))
    return [(int(doc[a]), int(a - at[doc[a]]), int(b - 1 - at[doc[a]])) for a, b in zip(edge[::2], edge[1::2], strict=True)]


def removed(docs: DataFrame, spark: SparkSession, length: int = 400, k: int | None = None, text_col: str = "text", id_col: str = "doc_id", by_word: bool = False) -> tuple[DataFrame, DataFrame]:
    """(docs with key columns k1, k2; table (k1, k2, spans array<struct<a, b>>) of the ranges of symbols that go).

    Symbols are bytes, or words with the white space that follows them.
    """
    ship(spark)
    # Words tell more than bytes: shorter anchors are as rare, and there are fewer of them.
    k = k or max(1, length // (4 if by_word else 2))
    symbols, kind = (word_symbols, np.uint64) if by_word else (byte_symbols, np.uint8)
    width = np.dtype(kind).itemsize
    keyed = docs.withColumn("ctxviews_k1", F.xxhash64(docs[id_col], docs[text_col])).withColumn("ctxviews_k2", F.hash(docs[id_col], docs[text_col]))
    source = keyed.select(F.col("ctxviews_k1").alias("k1"), F.col("ctxviews_k2").alias("k2"), docs[text_col].alias("t"))

    def find(batches):
        import pandas as pd

        for pdf in batches:
            k1, k2 = pdf["k1"].to_numpy(), pdf["k2"].to_numpy()
            for first, raw in steps(pdf["t"].tolist()):
                if (r := runs(*symbols(raw), length, k)) is not None:
                    at, times, more = gathered(*r)
                    doc, i0, i1, p, anchor, ctx = (x[at] for x in r)
                    yield pd.DataFrame({"k1": k1[first + doc], "k2": k2[first + doc], "i0": i0, "i1": i1, "p": p, "anchor": anchor, "ctx": ctx, "times": times, "more": more})

    # A context that a document repeats is one row with all its places: text that goes round and round stays small.
    occ = keep(source.mapInPandas(find, "k1 long, k2 int, i0 long, i1 long, p long, anchor long, ctx long, times long, more array<long>"), spark)
    one = F.xxhash64("k1", "k2", "i0")
    ctxs = occ.groupBy("anchor", "ctx").agg(F.sum("times").alias("n"), F.min(one).alias("pick"))
    ctxs = keep(ctxs, spark)
    totals = ctxs.groupBy("anchor").agg(F.sum("n").alias("total"), F.count("*").alias("m"), F.sum((F.col("n") == 1).cast("long")).alias("lone")).filter("total > 1")
    known = keep(ctxs.join(totals, "anchor").select("anchor", "ctx", "n", "pick", "m", "lone"), spark)
    release(spark, ctxs)
    hit = keep(occ.join(known, ["anchor", "ctx"]).withColumn("one", one), spark)
    release(spark, occ)
    places = F.coalesce("more", F.array("i0"))
    whole = hit.filter("n > 1").select("k1", "k2", F.transform(places, lambda s: F.struct(s.alias("a"), (s + F.col("i1") - F.col("i0") + length).alias("b"))).alias("spans"))

    sort = hit.filter("lone > 0 and m > 1 and (n = 1 or one = pick)")
    # A document's windows to be cut, as integers: first and last window, anchor (its complement if the context repeats).
    place = F.when(F.col("n") == 1, F.col("p")).otherwise(-F.col("p") - 1)
    listed = sort.groupBy("k1", "k2").agg(F.collect_list(F.array(*(x.cast("int") for x in (F.col("i0"), F.col("i1"), place)))).alias("w"))
    wanted = keep(listed.select("k1", "k2", F.flatten("w").alias("want")), spark)
    fetch = source.join(small(wanted, spark), ["k1", "k2"])
    step = max(1, (length - k) // SLOTS)

    def cut(batches):
        import pandas as pd

        for pdf in batches:
            for a in range(0, len(pdf), 500):
                rows = []
                part = pdf.iloc[a : a + 500]
                for k1, k2, t, want in zip(part["k1"], part["k2"], part["t"], part["want"], strict=True):
                    data, _ = symbols([t.encode("utf-8", "surrogatepass")])
                    prefix = prefix_hash(data)
                    own = []
                    i0, i1, p = np.asarray(want, np.int64).reshape(-1, 3).T
                    once, p = p >= 0, np.where(p >= 0, p, -p - 1)
                    anchor_of = span_hash(prefix, p, p + k).view(np.int64)
                    for w0, w1, at, anchor, n in zip(i0.tolist(), i1.tolist(), p.tolist(), anchor_of.tolist(), np.where(once, 1, 2).tolist(), strict=True):
                        for j in range((at - w1) // step, (at - w0) // step + 1):
                            core = at - step * j
                            own.append((max(w0, core - step + 1), min(w1, core), core, anchor, j, n))
                    core = np.array([o[2] for o in own])
                    h = span_hash(prefix, core, core + length - step).view(np.int64).tolist()
                    for (x, y, c, anchor, j, n), g in zip(own, h, strict=True):
                        rows.append((k1, k2, x, n, anchor, j, g, data[x:c].tobytes(), data[c + length - step : y + length].tobytes()))
                yield pd.DataFrame(rows, columns=["k1", "k2", "at", "n", "anchor", "j", "core", "before", "after"])

    slots = keep(fetch.select("k1", "k2", "t", "want").mapInPandas(cut, "k1 long, k2 int, at long, n long, anchor long, j int, core long, before binary, after binary"), spark)
    numbered = slots.withColumn("c", F.xxhash64("anchor", "j", "core"))
    cores = keep(numbered.groupBy("c").agg(F.count("*").alias("s"), F.min("n").alias("n1")).filter("s > 1 and n1 = 1"), spark)
    groups = max(1, (cores.agg(F.sum("s")).first()[0] or 0) // GROUP_SLOTS)
    met = numbered.select("k1", "k2", "at", "n", "c", "before", "after").join(small(cores.select("c", "s"), spark), "c")

    def sort_group(pdf):
        import pandas as pd

        out, batch, owners, held = [], [], [], 0

        def solve():
            # Symbols are numbered from 0 on, the cores' own symbols after them.
            _, code = np.unique(np.concatenate([x for before, after, _ in batch for x in (before, after)]), return_inverse=True)
            top, at, pieces = int(code.max(initial=-1)) + 1, 0, []
            for before, after, number in batch:
                mid, end = at + len(before), at + len(before) + len(after)
                pieces.append(np.concatenate([code[at:mid], [top + number], code[mid:end]]))
                at = end
            for i, x, y in repeated_windows(pieces, step + 1):
                k1, k2, at, n = owners[i]
                if n == 1:
                    out.append((k1, k2, at + x, at + y + length))

        for number, (_, part) in enumerate(pdf.groupby("c", sort=False)):
            seen: dict[tuple[bytes, bytes], list] = {}
            for row in zip(part["k1"], part["k2"], part["at"], part["n"], part["before"], part["after"], strict=True):
                seen.setdefault(row[4:], []).append(row[:4])
            for (before, after), who in seen.items():
                if len(who) > 1:  # the whole slot repeats
                    out += [(k1, k2, at, at + (len(before) + len(after)) // width + length - step) for k1, k2, at, n in who if n == 1]
            if len(seen) > 1:
                for (before, after), who in seen.items():
                    batch.append((np.frombuffer(before, kind), np.frombuffer(after, kind), number))
                    owners.append(who[0])
                    held += 1 + (len(before) + len(after)) // width
            if held > SORT_SYMBOLS:
                solve()
                batch, owners, held = [], [], 0
        if batch:
            solve()
        trim()
        return pd.DataFrame(out, columns=["k1", "k2", "a", "b"])

    usual = met.filter(F.col("s") <= HOT_SLOTS).withColumn("g", F.pmod(F.xxhash64("c"), F.lit(groups)))
    sorted_ = usual.groupBy("g").applyInPandas(sort_group, "k1 long, k2 int, a long, b long")

    def window_hashes(batches):
        import pandas as pd

        for pdf in batches:
            for k1, k2, at, n, c, before, after in zip(pdf["k1"], pdf["k2"], pdf["at"], pdf["n"], pdf["c"], pdf["before"], pdf["after"], strict=True):
                s = np.concatenate([np.frombuffer(before, kind).astype(np.uint64), np.array([1 << 63], np.uint64), np.frombuffer(after, kind).astype(np.uint64)])
                x = np.arange(len(s) - step)
                yield pd.DataFrame({"k1": k1, "k2": k2, "at": at + x, "n": n, "c": c, "h": span_hash(prefix_hash(s), x, x + step + 1).view(np.int64)})

    ranges = whole.union(_lists(sorted_))
    if cores.filter(F.col("s") > HOT_SLOTS).limit(1).count():
        hot = met.filter(F.col("s") > HOT_SLOTS).mapInPandas(window_hashes, "k1 long, k2 int, at long, n long, c long, h long")
        twice = hot.groupBy("c", "h").agg(F.count("*").alias("times")).filter("times > 1").select("c", "h")
        ranges = ranges.union(_lists(hot.join(twice, ["c", "h"], "left_semi").filter("n = 1").select("k1", "k2", F.col("at").alias("a"), (F.col("at") + length).alias("b"))))
    spans = _merged(ranges, spark)
    release(spark, hit, known, wanted, slots, cores)
    return keyed, spans


def _lists(ranges: DataFrame) -> DataFrame:
    """Rows (k1, k2, a, b) as rows (k1, k2, spans)."""
    return ranges.select("k1", "k2", F.array(F.struct("a", "b")).alias("spans"))


def _merged(ranges: DataFrame, spark: SparkSession) -> DataFrame:
    """(k1, k2, spans) with the maximal runs of each document's ranges, from rows with some of its spans."""

    def run(batches):
        for pdf in batches:
            yield pdf.assign(spans=[[{"a": a, "b": b} for a, b in merge(s)] for s in pdf["spans"]])

    lists = ranges.groupBy("k1", "k2").agg(F.flatten(F.collect_list("spans")).alias("spans"))
    return keep(lists.mapInPandas(run, "k1 long, k2 int, spans array<struct<a: long, b: long>>"), spark)


def merge(spans) -> list[tuple[int, int]]:
    """Maximal runs of byte ranges."""
    out: list[list[int]] = []
    for a, b in sorted((s["a"], s["b"]) for s in spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def word_windows(raw: bytes, cuts: list[tuple[int, int]], n: int) -> tuple[np.ndarray, ...]:
    """(start, end, two hashes) of every string of n words whose first n - 1 symbols lie inside a range of `cuts`."""
    buf = np.frombuffer(raw, np.uint8)
    inside = np.concatenate([[False], ~SPACE[buf], [False]])
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    start, end = edge[::2], edge[1::2]
    i = np.arange(max(0, len(start) - n + 1))
    cut = np.searchsorted([x for x, _ in cuts], i, "right") - 1
    i = i[(cut >= 0) & (i + n - 1 <= np.array([y for _, y in cuts])[cut])]
    a, b = start[i], end[i + n - 1]
    h = span_hash(prefix_hash(buf), a, b)
    g = span_hash(prefix_hash(buf.astype(np.int64) + 256), a, b)
    return a, b, h.view(np.int64), g.view(np.int64)


def removed_words(docs: DataFrame, spark: SparkSession, n: int, text_col: str = "text", id_col: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """Like removed(), for strings of n words, from the start of the first to the end of the last."""
    keyed, spans = removed(docs, spark, n - 1, None, text_col, id_col, by_word=True)
    source = keyed.select(F.col("ctxviews_k1").alias("k1"), F.col("ctxviews_k2").alias("k2"), docs[text_col].alias("t"))
    fetch = source.join(small(spans, spark), ["k1", "k2"])

    def find(batches):
        import pandas as pd

        for pdf in batches:
            for k1, k2, t, s in zip(pdf["k1"], pdf["k2"], pdf["t"], pdf["spans"], strict=True):
                a, b, h, g = word_windows(t.encode("utf-8", "surrogatepass"), merge(s), n)
                if len(a):
                    yield pd.DataFrame({"k1": k1, "k2": k2, "a": a, "b": b, "h": h, "g": g})
            trim()

    seen = keep(fetch.select("k1", "k2", "t", "spans").mapInPandas(find, "k1 long, k2 int, a long, b long, h long, g long"), spark)
    twice = keep(seen.groupBy("h", "g").agg(F.count("*").alias("times")).filter("times > 1").select("h", "g"), spark)
    ranges = seen.join(small(twice, spark), ["h", "g"], "left_semi")
    out = _merged(_lists(ranges), spark)
    release(spark, spans, seen, twice)
    return keyed, out


def dedup(docs: DataFrame, spark: SparkSession, carry: list[str], length: int = 400, k: int | None = None, with_text: bool = False, text_col: str = "text", id_col: str = "doc_id", n_words: int | None = None) -> DataFrame:
    """Strings of `length` bytes go, or of `n_words` words.  The columns `carry`, then n_bytes, n_removed, n_spans, kept_sha256 and, if with_text,
    kept_text: the remaining bytes as text, without characters that a cut has split (null stays null)."""
    keyed, spans = removed_words(docs, spark, n_words, text_col, id_col) if n_words else removed(docs, spark, length, k, text_col, id_col)
    kinds = dict(docs.dtypes)
    joined = keyed.select(*(keyed[c].alias(f"c_{c}") for c in carry), keyed[text_col].alias("t"), F.col("ctxviews_k1").alias("k1"), F.col("ctxviews_k2").alias("k2")).join(small(spans, spark), ["k1", "k2"], "left")

    def run(batches):
        import pandas as pd

        for pdf in batches:
            rows = []
            for t, spans in zip(pdf["t"], pdf["spans"], strict=True):
                b = t.encode("utf-8", "surrogatepass") if isinstance(t, str) else b""
                cuts = merge(spans) if spans is not None else []
                kept, at = [], 0
                for x, y in cuts:
                    kept.append(b[at:x])
                    at = y
                kept.append(b[at:])
                rest = b"".join(kept)
                rows.append((len(b), len(b) - len(rest), len(cuts), hashlib.sha256(rest).hexdigest(), *((None if not isinstance(t, str) else t if not cuts else "".join(p.decode("utf-8", "ignore") for p in kept),) if with_text else ())))
            out = pd.DataFrame(rows, columns=["n_bytes", "n_removed", "n_spans", "kept_sha256", *(("kept_text",) if with_text else ())])
            for c in reversed(carry):
                out.insert(0, c, pdf[f"c_{c}"].values)
            yield out

    schema = "".join(f"`{c}` {kinds[c]}, " for c in carry) + "n_bytes long, n_removed long, n_spans long, kept_sha256 string" + (", kept_text string" if with_text else "")
    return joined.select(*(f"c_{c}" for c in carry), "t", "spans").mapInPandas(run, schema)
