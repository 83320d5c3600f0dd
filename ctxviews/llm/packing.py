"""Mixture-controlled packing of whole corpora into fixed windows.

Every source is a queue of token ids.  Deficit round-robin fills each window to
the queues' target shares (by default the sources' shares of all tokens, so that
all queues end together): a queue's deficit grows by its quantum, it gives the
whole tokens of its deficit, and what is missing goes to the queues with the
largest deficits left.  Deficits carry over from window to window.  A segment of
windows starts with the deficits that the shares imply for all windows before it
- closed form - so partitions pack on their own and still continue each other.

Only token counts by (block, source) are exchanged.  Ids are written once to the
shared folder and cut where they lie; they never cross a shuffle.  The windows'
last, partial one is cut into sequences of power-of-two lengths, which need no
padding; every other sequence is full.

Targets can be given for sources by name.  Then shares follow them until a queue is
used up, and after that the targets of the queues that are left; sources without a
target come last.

A plan holds at most MAX_QUEUES queues.  With more sources the plan is made twice over:
sources share queues by hash, and inside a shared queue documents stand in the order of
their sources' virtual times (the share of its source that comes before a document), so
that any stretch of the queue holds its sources in proportion to their sizes, within a
document each.  Positions in such a queue come from counts by (queue, slice of time), and
no task holds more than a slice.

Null and empty texts give the end id alone.  A null source is the empty one.  Repeated
rows are documents of their own; a null id is carried.  An empty table gives no rows.
"""

from __future__ import annotations

import base64
import bisect
import json
import zlib
from functools import lru_cache

import numpy as np
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import keep, ship, small

MAX_QUEUES = 512
#: Documents of a shared queue that are put in order together, on average.
SLICE_ROWS = 50_000
#: Windows that are planned together.
SEGMENT = 1024


# --- tokens ------------------------------------------------------------------------------------

_encoders: dict[str, object] = {}


def encoder(path: str):
    """ids of a text, equal to those of the tokenizers file at path.

    The byte-level file is read as ranks; its special token is recognised in the
    text, as the tokenizers library does.
    """
    if path not in _encoders:
        import tiktoken

        from .bpe_codec import byte_letters

        spec = json.loads(open(path, encoding="utf-8").read())
        back = {c: b for b, c in enumerate(byte_letters())}
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        ranks = {bytes(back[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in special}
        pattern = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
        name = base64.b32encode(path.encode()).decode()
        _encoders[path] = tiktoken.Encoding(name, pat_str=pattern, mergeable_ranks=ranks, special_tokens=special)
    enc = _encoders[path]
    return lambda t: enc.encode(t, allowed_special="all") if "<|" in t else enc.encode_ordinary(t)


def id_type(path: str, end_id: int) -> type:
    """The least unsigned type that holds the file's ids and the end id."""
    spec = json.loads(open(path, encoding="utf-8").read())
    most = max([end_id, *spec["model"]["vocab"].values(), *(t["id"] for t in spec["added_tokens"])])
    return np.uint16 if most < 1 << 16 else np.uint32


# --- deficit round-robin -------------------------------------------------------------------------


def apportion(tokens: int, weights: list[int], caps: list[int]) -> list[int]:
    """Whole shares of `tokens` by weight, none over its cap; what rounding leaves goes to the heaviest with room."""
    total = sum(weights)
    out = [min(c, tokens * w // total) if total else 0 for w, c in zip(weights, caps, strict=True)]
    rest = tokens - sum(out)
    for q in sorted(range(len(out)), key=lambda q: (-weights[q], q)):
        if not rest:
            break
        more = min(rest, caps[q] - out[q])
        out[q] += more
        rest -= more
    return out


class Mixture:
    """The plan: sizes of all windows and what each takes from each queue.

    sizes: tokens of each queue (all are packed).  limit: length of a window.  weights: target
    proportions as integers, by default the sizes.
    """

    def __init__(self, sizes: list[int], limit: int = 1024, segment: int = SEGMENT, weights: list[int] | None = None):
        self.n = np.array(sizes, np.int64)
        self.total, self.limit, self.per = int(self.n.sum()), limit, segment
        self.full = self.total // limit
        rest = self.total - self.full * limit
        self.tail = [1 << b for b in range(rest.bit_length() - 1, -1, -1) if rest >> b & 1] if rest else []
        self.segments = max(1, -(-self.full // segment))
        self.segment = lru_cache(maxsize=512)(self._segment)
        self.phases = self._phases([int(x) for x in sizes], [int(w) for w in (weights or sizes)])

    def _phases(self, left: list[int], weights: list[int]) -> list[tuple[int, list[int], list[int], list[int]]]:
        """(first token, taken before, weights, tokens left) of the stretches between which a queue is used up."""
        out, at, taken = [], 0, [0] * len(left)
        while sum(left):
            w = [x if n else 0 for x, n in zip(weights, left, strict=True)]
            w = w if sum(w) else left  # only queues without a target are left
            size = min(min(-(-n * sum(w) // x) for n, x in zip(left, w, strict=True) if x), sum(n for n, x in zip(left, w, strict=True) if x))
            out.append((at, list(taken), list(w), list(left)))
            got = apportion(size, w, [n if x else 0 for n, x in zip(left, w, strict=True)])
            taken = [t + g for t, g in zip(taken, got, strict=True)]
            left = [n - g for n, g in zip(left, got, strict=True)]
            at += size
        return out

    def _phase(self, tokens: int) -> tuple[int, list[int], list[int], list[int]]:
        return self.phases[max(0, bisect.bisect_right([p[0] for p in self.phases], tokens) - 1)]

    def taken(self, tokens: int) -> np.ndarray:
        """Tokens of each queue in the first `tokens` of all, in whole shares."""
        if not self.total:
            return self.n * 0
        at, taken, w, left = self._phase(tokens)
        caps = [n if x else 0 for n, x in zip(left, w, strict=True)]
        return np.array(taken, np.int64) + np.array(apportion(tokens - at, w, caps), np.int64)

    def expected(self, tokens: int) -> np.ndarray:
        """The same in fractions of tokens."""
        at, taken, w, _ = self._phase(tokens)
        return np.array(taken, np.float64) + (tokens - at) * self.share(tokens)

    def share(self, tokens: int) -> np.ndarray:
        """Target shares of the queues at a token."""
        w = np.array(self._phase(tokens)[2], np.float64)
        return w / w.sum()

    def bounds(self, k: int) -> tuple[int, int]:
        """Windows [a, b) of segment k; the last also has the power-of-two tail."""
        return k * self.per, self.full + len(self.tail) if k == self.segments - 1 else (k + 1) * self.per

    def start(self, w: int) -> int:
        """Tokens before window w."""
        return self.limit * w if w <= self.full else self.limit * self.full + sum(self.tail[: w - self.full])

    def _segment(self, k: int) -> tuple[np.ndarray, np.ndarray]:
        """(tokens of each queue before each window and after the last, tokens taken) of segment k."""
        a, b = self.bounds(k)
        before = self.taken(self.start(a))
        left = self.taken(self.start(b)) - before
        deficit = self.expected(self.start(a)) - before if self.total else before * 0.0
        take = np.zeros((b - a, len(self.n)), np.int64)
        for i in range(b - a):
            size = self.start(a + i + 1) - self.start(a + i)
            deficit = deficit + size * self.share(self.start(a + i))
            give = np.minimum(np.maximum(np.floor(deficit), 0).astype(np.int64), left)
            if (over := int(give.sum()) - size) > 0:  # the round ends early for the queues that come last
                for q in np.roll(np.arange(len(give)), -(a + i))[::-1]:
                    cut = min(over, int(give[q]))
                    give[q] -= cut
                    over -= cut
                    if not over:
                        break
            short = size - int(give.sum())
            while short > 0:
                can = np.flatnonzero(left > give)
                by = can[np.argsort(-(deficit - give)[can], kind="stable")][:short]
                if len(can) <= short:  # few queues are left: they share the rest
                    more = np.minimum(left[by] - give[by], -(-short // len(by)))
                    more = np.minimum(more, np.maximum(0, short - np.concatenate([[0], np.cumsum(more)[:-1]])))
                    give[by] += more
                    short -= int(more.sum())
                else:
                    give[by] += 1
                    short -= len(by)
            take[i] = give
            deficit = deficit - give
            left = left - give
        return before + np.concatenate([np.zeros((1, len(self.n)), np.int64), np.cumsum(take, 0)]), take

    def find(self, queue: int, at: int) -> int:
        """Segment that holds token `at` of a queue."""
        lo, hi = 0, self.segments - 1
        while lo < hi:
            mid = (lo + hi + 1) // 2
            if self.taken(self.start(self.bounds(mid)[0]))[queue] <= at:
                lo = mid
            else:
                hi = mid - 1
        return lo

    def pieces(self, queue: int, first: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, ...]:
        """Pieces of documents that stand at first .. first+size of a queue: (document, start, length, window, offset)."""
        out: list[tuple[np.ndarray, ...]] = []
        lo, hi = int(first.min()), int((first + size).max())
        k = self.find(queue, lo)
        while k < self.segments:
            at, take = self.segment(k)
            a, _ = self.bounds(k)
            edge = at[:, queue]
            if edge[0] >= hi:
                break
            s, e = np.maximum(first, edge[0]), np.minimum(first + size, edge[-1])
            doc = np.flatnonzero(e > s)
            if len(doc):
                s, e = s[doc], e[doc]
                w0 = np.searchsorted(edge, s, "right") - 1
                w1 = np.searchsorted(edge, e, "left") - 1
                n = w1 - w0 + 1
                d = np.repeat(np.arange(len(doc)), n)
                w = w0[d] + np.arange(len(d)) - np.repeat(np.cumsum(n) - n, n)
                x, y = np.maximum(s[d], edge[w]), np.minimum(e[d], edge[w + 1])
                keep_ = y > x  # windows without this queue are empty
                d, w, x, y = d[keep_], w[keep_], x[keep_], y[keep_]
                offset = take[w, :queue].sum(1) + x - edge[w]
                out.append((doc[d], x - first[doc[d]], y - x, a + w, offset))
            k += 1
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))


# --- Spark ---------------------------------------------------------------------------------------


def _queues(docs: DataFrame, source: Column, targets: dict[str, float] | None) -> tuple[Column, bool]:
    """(queue of a row, whether queues are shared): sources with a target have their own."""
    own = sorted(targets or ())
    if len(own) >= MAX_QUEUES:
        raise ValueError(f"at most {MAX_QUEUES - 1} targets")
    if docs.select(source.alias("q")).distinct().limit(MAX_QUEUES + 1).count() <= MAX_QUEUES:
        return source, False
    shared = F.concat(F.lit("\x1f"), F.pmod(F.xxhash64(source), F.lit(MAX_QUEUES - len(own))).cast("string"))
    return (F.when(source.isin(own), source).otherwise(shared) if own else shared), True


def _in_virtual_time(tokens: DataFrame, base: DataFrame, spark: SparkSession) -> DataFrame:
    """tokens with `at`, their place in a shared queue: documents by the share of their source before them."""
    size = base.groupBy("s").agg(F.sum("n").alias("whole"))
    timed = tokens.join(base.drop("n"), ["s", "block"]).join(size, "s").withColumn("time", (F.col("base") + F.col("off")) / F.col("whole"))
    rows = tokens.groupBy("q").count().agg(F.max("count")).first()[0] or 0
    parts = max(1, -(-rows // SLICE_ROWS))
    timed = timed.withColumn("slice", F.least(F.floor(F.col("time") * parts), F.lit(parts - 1)).cast("int"))
    counts = keep(timed.groupBy("q", "slice").agg(F.sum("n").alias("n")), spark)
    before = counts.withColumn("before", F.sum("n").over(W.partitionBy("q").orderBy("slice")) - F.col("n")).drop("n")
    order = W.partitionBy("q", "slice").orderBy("time", "s", "off", "block").rowsBetween(W.unboundedPreceding, W.currentRow)
    placed = timed.withColumn("sum", F.sum("n").over(order)).join(before, ["q", "slice"])
    return placed.withColumn("at", F.col("before") + F.col("sum") - F.col("n"))


def pack(docs: DataFrame, spark: SparkSession, path: str, limit: int = 1024, end_id: int = 0, with_ids: bool = False, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", targets: dict[str, float] | None = None) -> DataFrame:
    """One row for each piece: id_col, start, length, ids_crc32, doc_tokens, sequence_id, offset, queue
    and, if with_ids, ids array<int>.  targets: proportions of sources by name."""
    ship(spark)
    kind, whole = dict(docs.dtypes)[id_col], id_type(path, end_id)
    source = F.coalesce(docs[source_col].cast("string"), F.lit("")) if source_col in docs.columns else F.lit("")
    queue, shared = _queues(docs, source, targets)

    def tokenise(batches):
        import pandas as pd

        ids_of, block, offsets = encoder(path), TaskContext.get().partitionId(), {}
        for pdf in batches:
            ids, sizes, first = [], [], []
            for t, s in zip(pdf["t"].tolist(), pdf["s"].tolist(), strict=True):
                x = np.array([*(ids_of(t) if isinstance(t, str) else ()), end_id], whole)
                ids.append(x.tobytes())
                sizes.append(len(x))
                first.append(offsets.get(s, 0))
                offsets[s] = first[-1] + len(x)
            yield pd.DataFrame({"i": pdf["i"], "s": pdf["s"], "q": pdf["q"], "block": block, "n": sizes, "off": first, "ids": ids})

    given = docs.select(docs[id_col].alias("i"), docs[text_col].alias("t"), source.alias("s"), queue.alias("q"))
    tokens = keep(given.mapInPandas(tokenise, f"i {kind}, s string, q string, block long, n long, off long, ids binary"), spark)
    counts = keep(tokens.groupBy("s", "q", "block").agg(F.sum("n").alias("n")), spark)
    sizes = sorted((r.q, r.n) for r in counts.groupBy("q").agg(F.sum("n").alias("n")).collect())  # MAX_QUEUES rows at most
    names = {q: k for k, (q, _) in enumerate(sizes)}
    weights = None if targets is None else [round(1e9 * targets.get(q, 0)) for q, _ in sizes]
    plan = (tuple(n for _, n in sizes), limit, SEGMENT, weights)
    base = counts.withColumn("base", F.sum("n").over(W.partitionBy("s").orderBy("block")) - F.col("n")).select("s", "block", "n", "base")
    if shared:
        placed = _in_virtual_time(tokens, base, spark)
    else:
        placed = tokens.join(small(base.drop("n"), spark), ["s", "block"]).withColumn("at", F.col("base") + F.col("off"))

    def cut(batches):
        import pandas as pd

        mixture = Mixture(*plan)
        for pdf in batches:
            for q, part in pdf.groupby("q", sort=False):
                first, size = part["at"].to_numpy(), part["n"].to_numpy()
                doc, start, length, window, offset = mixture.pieces(names[q], first, size)
                ids = [np.frombuffer(x, whole) for x in part["ids"]]
                own = [ids[d][s : s + n] for d, s, n in zip(doc.tolist(), start.tolist(), length.tolist(), strict=True)]
                out = pd.DataFrame({id_col: part["i"].to_numpy()[doc], "start": start, "length": length, "ids_crc32": [zlib.crc32(x.astype("<u4").tobytes()) for x in own], "doc_tokens": size[doc], "sequence_id": window, "offset": offset, "queue": q})
                if with_ids:
                    out["ids"] = [x.astype(np.int32) for x in own]
                yield out

    return placed.select("i", "q", "n", "at", "ids").mapInPandas(cut, f"`{id_col}` {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, queue string" + (", ids array<int>" if with_ids else ""))
