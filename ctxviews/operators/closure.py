"""Steps over a graph from many starts at once, as bit rows.

Edges stay inside a snapshot.  A snapshot's starts are dealt over blocks; a block gets the steps of all nodes
that some edge leads to, one row of bits each, so that the nodes after one more step are the `or` of some rows.
Neither the pairs that two steps meet nor their distinct ones are shuffled or stored: a start's nodes leave its
block as lists.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ctxviews.functions.ship import ship

SNAP = ["repo", "lang"]
#: Starts for which a snapshot gets one more block, up to two a core.
STARTS = 2048
#: Bytes of bit rows that a task holds (a wider graph is taken in ranges of columns), starts stepped together, nodes sent at once.
BITS, TOGETHER, SENT = 96 << 20, 256, 1 << 17


class Graph:
    """names: the nodes that have a column; the steps of each as (edge, to): positions in `to` and columns."""

    def __init__(self, names, edge: np.ndarray, to: np.ndarray):
        self.names, self.edge, self.to, n = names, edge, to, len(names)
        self.wide = max(64, min(-(-n // 64) * 64, BITS * 8 // max(1, n) // 64 * 64))
        self.bytes = -(-n // 64) * 8
        self.whole = self._bits(0) if self.wide >= n else None

    def _bits(self, first: int) -> np.ndarray:
        """The columns from `first` on, `wide` of them, of every node's steps."""
        n = len(self.names)
        out = np.zeros((n, self.wide // 8), np.uint8)
        for a in range(0, n, 512):
            b = min(n, a + 512)
            row = np.repeat(np.arange(b - a), np.diff(self.edge[a : b + 1]))
            to = self.to[self.edge[a] : self.edge[b]] - first
            has = (to >= 0) & (to < self.wide)
            own = np.zeros((b - a, self.wide), bool)
            own[row[has], to[has]] = True
            out[a:b] = np.packbits(own, axis=1)
        return out.view(np.uint64)

    def set(self, fronts: list[np.ndarray]) -> np.ndarray:
        """Bit rows of lists of columns."""
        own = np.zeros((len(fronts), self.bytes * 8), bool)
        for i, x in enumerate(fronts):
            own[i, x] = True
        return np.packbits(own, axis=1)

    def step(self, fronts: list[np.ndarray]) -> np.ndarray:
        """Bit rows of the nodes that one step from some node of each front leads to."""
        out = np.zeros((len(fronts), self.bytes), np.uint8)
        for first in range(0, len(self.names), self.wide):
            bits = self._bits(first) if self.whole is None else self.whole
            part = out[:, first // 8 : (first + self.wide) // 8]
            for i, x in enumerate(fronts):
                if len(x):
                    part[i] = np.bitwise_or.reduce(bits[x], axis=0).view(np.uint8)[: part.shape[1]]
        return out

    def codes(self, bits: np.ndarray) -> list[np.ndarray]:
        return [np.flatnonzero(np.unpackbits(x)) for x in bits]


def surroundings(depth: int):
    """Kernel: (hop, columns) of the nodes of each start within `depth` steps, each at its least distance; hop 0, the start, is left to the caller."""

    def run(g: Graph, own: np.ndarray, fronts: list[np.ndarray]):
        seen = g.set([x[x >= 0] for x in own[:, None]])
        for h in range(1, depth + 1):
            new = (g.set(fronts) if h == 1 else g.step(fronts)) & ~seen
            seen |= new
            fronts = g.codes(new)
            yield h, fronts

    return run


def routes(steps: int, most: int):
    """Kernel: (hop, columns) of the nodes that just `steps` steps lead to, by the least number of steps up to `most` (None beyond)."""

    def run(g: Graph, own: np.ndarray, fronts: list[np.ndarray]):
        walks = [g.set([x[x >= 0] for x in own[:, None]]), g.set(fronts)]

        def walk(h: int) -> np.ndarray:
            while len(walks) <= h:
                walks.append(g.step(g.codes(walks[-1])))
            return walks[h]

        open_ = walk(steps).copy()
        for h in range(most + 1):
            if not open_.any():
                return
            yield h, g.codes(open_ & walk(h))
            open_ &= ~walk(h)
        yield None, g.codes(open_)

    return run


@dataclass
class Steps:
    """nexts: repo, lang, node, nexts (codes of the nodes that a step leads to); names: repo, lang, node, code of all these, from 0 in each snapshot."""

    nexts: DataFrame
    names: DataFrame


def coded(ends: DataFrame) -> DataFrame:
    """The names of nodes (repo, lang, node), distinct ones."""
    return ends.withColumn("code", F.row_number().over(W.partitionBy(*SNAP).orderBy("node")) - 1)


def steps_of(e: DataFrame, keep=None) -> Steps:
    """The steps along edges (repo, lang, src, dst)."""
    keep = keep or (lambda df: df)
    names = keep(coded(e.select(*SNAP, F.col("dst").alias("node")).distinct()))
    to = e.join(names.withColumnRenamed("node", "dst"), [*SNAP, "dst"])
    return Steps(keep(to.groupBy(*SNAP, F.col("src").alias("node")).agg(F.collect_set("code").alias("nexts"))), names)


def search(s: Steps, starts: DataFrame, kernel) -> DataFrame:
    """start, hop, nodes (lists; a start may have several rows of a hop).  starts: repo, lang, node, distinct."""
    spark = starts.sparkSession
    ship(spark)
    cores = spark.sparkContext.defaultParallelism
    n = F.ceil(F.count("*") / STARTS).cast("int")
    blocks = F.broadcast(starts.groupBy(*SNAP).agg(F.least(n, F.lit(2 * cores)).alias("blocks")))
    by = [*SNAP, "node"]
    told = s.names.join(s.nexts, by, "left").join(blocks, SNAP).select(*SNAP, F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"), F.lit(0).alias("kind"), "code", "node", "nexts")
    asked = starts.select(*by).join(s.nexts, by, "left").join(s.names, by, "left").join(blocks, SNAP)
    asked = asked.select(*SNAP, F.pmod(F.xxhash64("node"), "blocks").cast("int").alias("block"), F.lit(1).alias("kind"), F.coalesce("code", F.lit(-1)).alias("code"), "node", "nexts")
    part = F.concat_ws("\x1f", *SNAP, F.col("block").cast("string"))
    dealt = told.unionByName(asked).select(part.alias("part"), "kind", "code", "node", F.coalesce("nexts", F.array().cast("array<int>")).alias("nexts"))

    def run(batches):
        import pyarrow as pa
        import pyarrow.compute as pc

        at, g, names, sizes, to = None, None, [], [], []

        def send(node, of, hops, codes):
            edge = pa.array(np.append(0, np.cumsum([len(c) for c in codes])), pa.int32())
            return pa.RecordBatch.from_arrays([node.take(pa.array(of)), pa.array(hops, pa.int32()), pa.ListArray.from_arrays(edge, g.names.take(pa.array(np.concatenate(codes))))], ["start", "hop", "nodes"])

        for whole in batches:
            for first in range(0, whole.num_rows, TOGETHER):
                rb = whole.slice(first, TOGETHER)
                keys = rb.column(0).to_pylist()
                kinds = rb.column(1).to_numpy()
                cut = [0, *(i for i in range(1, len(keys)) if keys[i] != keys[i - 1] or kinds[i] != kinds[i - 1]), len(keys)]
                for a, b in zip(cut, cut[1:], strict=False):
                    if keys[a] != at:
                        at, g, names, sizes, to = keys[a], None, [], [], []
                    x = rb.slice(a, b - a)
                    node, size, codes = x.column(3), pc.list_value_length(x.column(4)).to_numpy().astype(np.int64), x.column(4).flatten().to_numpy()
                    if kinds[a] == 0:
                        names.append(pa.array(node.to_pylist(), pa.string()))
                        sizes.append(size)
                        to.append(codes.copy())
                        continue
                    if g is None:
                        g = Graph(pa.concat_arrays(names or [pa.array([], pa.string())]), np.append(0, np.cumsum(np.concatenate([[0], *sizes])[1:])), np.concatenate([np.zeros(0, np.int32), *to]))
                        names, sizes, to = [], [], []
                    edge = np.append(0, np.cumsum(size))
                    of, hops, held, n = [], [], [], 0
                    for hop, found in kernel(g, x.column(2).to_numpy(), [codes[edge[i] : edge[i + 1]] for i in range(b - a)]):
                        for i, c in enumerate(found):
                            if len(c):
                                of.append(i)
                                hops.append(hop)
                                held.append(c)
                                n += len(c)
                            if n > SENT:
                                yield send(node, of, hops, held)
                                of, hops, held, n = [], [], [], 0
                    if held:
                        yield send(node, of, hops, held)

    return dealt.repartition(4 * cores, "part").sortWithinPartitions("part", "kind", "code").mapInArrow(run, "start string, hop int, nodes array<string>")
