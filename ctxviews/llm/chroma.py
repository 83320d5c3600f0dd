"""Chroma fingerprints of audio columns, and alignment of recordings.

Frames of a recording become pitch-class energies.  Filters - differences of
rectangle sums, taken from one integral image - are compared at three levels and
packed as two Gray-coded bits each into one 32-bit integer per frame.  Recordings
align at offsets that enough equal integers vote for; of those whose share of bit
errors is small, the one with the least errors decides.  Votes alone do not: silent
or held passages vote for every offset between them.

Null, empty and too short recordings have no integers and align with nothing.
Recordings with the same fingerprint form a class that is compared once.  Repeated rows
are rows of one class; a row without an id is in its class but never a query; an empty
table gives no rows.  Columns of ours never meet the table's.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import keep, ship

RATE = 4000
FRAME = 512
HOP = 170
SPAN = 16  # frames under one integer
LOW_HZ, HIGH_HZ = 110, 1760
#: Bit errors up to which an offset is an alignment, integers that must overlap, equal integers needed.
MOST_ERRORS = 0.15
LEAST_OVERLAP = 24
LEAST_VOTES = 3
QUERY_BLOCK = 2000


def _bins() -> np.ndarray:
    hz = np.fft.rfftfreq(FRAME, 1 / RATE)
    out = np.zeros((len(hz), 12), np.float32)
    ok = (hz >= LOW_HZ) & (hz <= HIGH_HZ)
    pitch = np.round(12 * np.log2(np.maximum(hz, 1) / 440)).astype(int) % 12
    out[np.flatnonzero(ok), pitch[ok]] = 1
    return out


BINS = _bins()
HANN = np.hanning(FRAME).astype(np.float32)


def chroma(pcm: np.ndarray) -> np.ndarray:
    """frames x 12 energies, each frame scaled to length one (silent frames stay zero)."""
    if len(pcm) < FRAME:
        return np.zeros((0, 12), np.float32)
    frames = np.lib.stride_tricks.sliding_window_view(pcm, FRAME)[::HOP] * HANN
    x = np.fft.rfft(frames, axis=1)
    e = (x.real**2 + x.imag**2).astype(np.float32) @ BINS
    norm = np.linalg.norm(e, axis=1, keepdims=True)
    return np.where(norm > 1e-3, e / np.maximum(norm, 1e-9), 0)


#: Sixteen filters: (kind, first pitch class, pitch classes, frames).
FILTERS = [(k, p, h, w) for k, p, h, w in (
    (0, 0, 6, 8), (0, 3, 6, 16), (0, 6, 6, 4), (0, 9, 3, 16), (1, 0, 12, 8), (1, 0, 6, 12), (1, 6, 6, 12), (1, 4, 4, 16),
    (2, 0, 4, 12), (2, 4, 4, 12), (2, 8, 4, 12), (3, 0, 6, 9), (3, 6, 6, 9), (3, 2, 9, 15), (4, 0, 12, 12), (5, 0, 9, 12))]
LEVELS = (-0.06, 0.0, 0.06)
GRAY = np.array([0, 1, 3, 2], np.uint32)


def integers(energies: np.ndarray) -> np.ndarray:
    """One packed integer for each frame that has SPAN frames from it on."""
    n = len(energies) - SPAN + 1
    if n <= 0:
        return np.zeros(0, np.uint32)
    wide = np.concatenate([energies, energies], 1)  # pitch classes go round
    image = np.zeros((len(wide) + 1, wide.shape[1] + 1))
    image[1:, 1:] = wide.cumsum(0).cumsum(1)
    t = np.arange(n)

    def area(t0: int, t1: int, p0: int, p1: int) -> np.ndarray:
        return image[t + t1, p1] - image[t + t0, p1] - image[t + t1, p0] + image[t + t0, p0]

    out = np.zeros(n, np.uint32)
    for kind, p, h, w in FILTERS:
        whole = area(0, w, p, p + h)
        if kind == 0:  # upper and lower half of the pitch classes
            a = area(0, w, p, p + h // 2)
            b = whole - a
        elif kind == 1:  # earlier and later half
            a = area(0, w // 2, p, p + h)
            b = whole - a
        elif kind == 2:  # against the pitch classes next to it
            a, b = whole, area(0, w, p + h, p + 2 * h)
        elif kind == 3:  # middle third in time against the rest
            a = area(w // 3, 2 * w // 3, p, p + h) * 2
            b = whole - a / 2
        elif kind == 4:  # quarters, crosswise
            a = area(0, w // 2, p, p + h // 2) + area(w // 2, w, p + h // 2, p + h)
            b = whole - a
        else:  # middle third in pitch against the rest
            a = area(0, w, p + h // 3, p + 2 * h // 3) * 2
            b = whole - a / 2
        value = np.log1p(np.maximum(a, 0)) - np.log1p(np.maximum(b, 0))
        out = (out << np.uint32(2)) | GRAY[np.searchsorted(LEVELS, np.round(value, 9))]
    return out


def fingerprint(pcm: bytes | None) -> np.ndarray:
    """Integers of a recording of 16-bit little-endian samples at RATE."""
    if not pcm:
        return np.zeros(0, np.uint32)
    return integers(chroma(np.frombuffer(pcm[: len(pcm) // 2 * 2], "<i2").astype(np.float32) / 32768))


_ONES = np.array([bin(i).count("1") for i in range(1 << 16)], np.uint8)


def bit_errors(a: np.ndarray, b: np.ndarray, offset: int) -> tuple[float, int]:
    """Share of differing bits with b moved by offset (b[i] against a[i + offset]), and the overlap."""
    lo, hi = max(0, offset), min(len(a), len(b) + offset)
    if hi <= lo:
        return 1.0, 0
    x = a[lo:hi] ^ b[lo - offset : hi - offset]
    return float((_ONES[x & 0xFFFF].sum() + _ONES[x >> 16].sum()) / (32 * (hi - lo))), hi - lo


class QueryBlock:
    """Fingerprints that others are aligned with."""

    def __init__(self, ids: list[int], prints: list[np.ndarray]):
        self.ids, self.prints = ids, prints
        size = [len(p) for p in prints]
        value = np.concatenate(prints) if prints else np.zeros(0, np.uint32)
        self.who = np.repeat(np.arange(len(prints)), size)
        self.at = np.concatenate([np.arange(n) for n in size]) if prints else np.zeros(0, np.int64)
        order = np.argsort(value, kind="stable")
        self.value, self.who, self.at = value[order], self.who[order], self.at[order]

    def align(self, p: np.ndarray):
        """(query, offset, votes, bit errors) of every query that p aligns with: least bit errors of all
        offsets with enough votes, then longest overlap, most votes, least offset."""
        lo, hi = np.searchsorted(self.value, p, "left"), np.searchsorted(self.value, p, "right")
        n = hi - lo
        if not n.sum():
            return
        hit = np.repeat(lo - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
        offset = self.at[hit] - np.repeat(np.arange(len(p)), n)
        key, votes = np.unique(self.who[hit] * (1 << 24) + offset + (1 << 23), return_counts=True)
        key, votes = key[votes >= LEAST_VOTES], votes[votes >= LEAST_VOTES]
        who = key >> 24
        for k in np.unique(who):
            mine = np.flatnonzero(who == k)
            best = None
            for o, v in zip(((key[mine] & ((1 << 24) - 1)) - (1 << 23)).tolist(), votes[mine].tolist(), strict=True):
                errors, overlap = bit_errors(self.prints[k], p, o)
                if errors <= MOST_ERRORS and overlap >= min(LEAST_OVERLAP, len(p), len(self.prints[k])):
                    found = errors, -overlap, -v, o
                    best = found if best is None else min(best, found)
            if best is not None:
                yield self.ids[k], best[3], -best[2], best[0]


_notes: list[np.ndarray] = []


def sonify(vector) -> bytes | None:
    """16-bit samples for tables without a media column: each component of a vector becomes a note.

    A null vector gives null audio; null and non-finite components are silent.
    """
    if vector is None:
        return None
    if not _notes:
        step = 2 * HOP
        t = np.arange(step) / RATE
        _notes.append(np.stack([*((np.sin(2 * np.pi * 130.8128 * 2 ** (k / 12) * t) * np.hanning(step) * 16000).astype("<i2") for k in range(37)), np.zeros(step, "<i2")]))
    x = np.array([np.nan if c is None else c for c in vector], float)
    k = np.floor((np.clip(np.where(np.isfinite(x), x, 0) * 4, -1, 1) + 1) * 18).astype(int)
    return _notes[0][np.where(np.isfinite(x), k, 37)].tobytes()


def fingerprints(media: DataFrame, spark: SparkSession, id_col: str = "media_id", audio_col: str = "audio", render: Callable | None = None) -> DataFrame:
    """id_col, n_items, fp_sha256, fp (little-endian 32-bit integers) for every row.

    audio_col holds samples, or what `render` makes samples of, one row at a time."""
    ship(spark)

    def run(batches):
        import pandas as pd

        for pdf in batches:
            fp = [fingerprint(render(a) if render else a).astype("<u4").tobytes() for a in pdf["a"]]
            yield pd.DataFrame({id_col: pdf["i"].values, "n_items": [len(x) // 4 for x in fp], "fp_sha256": [hashlib.sha256(x).hexdigest() for x in fp], "fp": fp})

    return media.select(media[id_col].alias("i"), media[audio_col].alias("a")).mapInPandas(run, f"`{id_col}` {dict(media.dtypes)[id_col]}, n_items long, fp_sha256 string, fp binary")


def search(prints: DataFrame, spark: SparkSession, every: int = 100, id_col: str = "vec_id") -> DataFrame:
    """Every row of prints with its class and, for queries (id divisible by `every`), the classes that align.

    Returns id_col, n_items, fp_sha256, class_id (least id with the same fingerprint),
    is_query, matches array<struct<class_id, offset, votes, bit_errors>>.  Queries go
    in blocks of QUERY_BLOCK classes against all classes.
    """
    ship(spark)
    classes = keep(prints.filter("n_items > 0").groupBy("fp_sha256").agg(F.min(id_col).cast("long").alias("class_id"), F.first("fp").alias("fp"), F.max((F.col(id_col) % every == 0).cast("int")).alias("asked")), spark)
    asked = classes.filter("asked = 1").select("class_id", "fp")
    blocks, found = -(-asked.count() // QUERY_BLOCK), None
    for n in range(blocks):  # about QUERY_BLOCK classes each, dealt by hash
        block = asked.filter(F.pmod(F.xxhash64("class_id"), F.lit(blocks)) == n).orderBy("class_id").collect()
        shared = spark.sparkContext.broadcast(([r.class_id for r in block], [np.frombuffer(r.fp, "<u4") for r in block]))

        def run(batches, shared=shared):
            import pandas as pd

            queries = QueryBlock(*shared.value)
            for pdf in batches:
                rows = [(q, int(c), o, v, e) for c, fp in zip(pdf["class_id"], pdf["fp"], strict=True) for q, o, v, e in queries.align(np.frombuffer(fp, "<u4"))]
                yield pd.DataFrame(rows, columns=["query_class", "class_id", "offset", "votes", "bit_errors"])

        part = classes.select("class_id", "fp").mapInPandas(run, "query_class long, class_id long, offset long, votes long, bit_errors double")
        found = part if found is None else found.union(part)
    out = prints.select(id_col, "n_items", "fp_sha256", F.coalesce(F.col(id_col) % every == 0, F.lit(False)).alias("is_query"))
    out = out.join(classes.select("fp_sha256", "class_id"), "fp_sha256", "left")
    match = "array<struct<class_id:long,offset:long,votes:long,bit_errors:double>>"
    if found is None:
        return out.withColumn("matches", F.array().cast(match))
    lists = found.groupBy("query_class").agg(F.array_sort(F.collect_list(F.struct("class_id", "offset", "votes", F.round("bit_errors", 9).alias("bit_errors")))).cast(match).alias("matches"))
    key = F.when(F.col("is_query"), F.col("class_id")).otherwise(-1 - F.pmod(F.xxhash64(id_col), F.lit(1 << 20)))
    return out.withColumn("query_class", key).join(lists, "query_class", "left").withColumn("matches", F.coalesce("matches", F.array().cast(match))).select(id_col, "n_items", "fp_sha256", "class_id", "is_query", "matches")
