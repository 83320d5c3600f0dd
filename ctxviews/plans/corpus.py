"""The materialized views of a corpus: units, lexical lists, vectors, occurrences, references, edges.

Each is built once (see store) and read by every plan after that; a query that is
about building a view calls the operators instead.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ctxviews.operators import dense, lexical, rows, structure
from ctxviews.operators import units as unit_ops
from ctxviews.plans import store
from ctxviews.plans.plan import Views
from ctxviews.sources.tables import files, spread


class Corpus:
    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.dir = spark, sf_dir
        self._lexical: dict[int, lexical.Index] = {}

    def _put(self, name: str, build, by: list[str] | None = None) -> DataFrame:
        return store.stored(self.spark, self.dir, name, build, by=by)

    def cut(self, level: int = 2) -> DataFrame:
        """The units as a plan over the base table, not stored."""
        own = {0: unit_ops.level0, 1: unit_ops.level1, 2: unit_ops.level2}[level]
        return unit_ops.with_ids(own(files(self.spark, self.dir, deal=level > 0)), level)

    def units(self, level: int = 2) -> DataFrame:
        """Whole files (level 0) are rows of the base table as they stand: they are read there, a stored copy would hold every text again."""
        return self.cut(level) if level == 0 else self._put(f"units-{level}", lambda: self.cut(level))

    def lexical(self, level: int = 2, units: DataFrame | None = None) -> lexical.Index:
        """units: where they are read from while the counts are not stored yet; without them the stored ones are."""
        if level not in self._lexical:
            u = self.units(level) if units is None else units
            self._lexical[level] = lexical.index(spread(u) if level == 0 else u, put=lambda name, build: self._put(f"lexical-{level}-{name}", build))
        return self._lexical[level]

    def idf(self, e: dense.Encoder, level: int = 2) -> DataFrame:
        if e.features == "token":
            x = self.lexical(level)
            return x.terms.crossJoin(F.broadcast(x.stats)).select(F.col("term").alias("f"), F.log(1 + F.col("n") / F.col("df")).alias("idf"))
        return self._put(f"idf-{e.features}-{level}", lambda: dense.document_frequency(self.units(level), e))

    def vectors(self, e: dense.Encoder, level: int = 2) -> DataFrame:
        """Vectors over tokens are weighed as they are read: all encoders share the stored counts."""
        if e.features == "token":
            return rows.weigh(self.lexical(level).counts, self.idf(e, level), e.dim)
        return self._put(f"vectors-{e.name}-{e.dim}-{e.features}-{level}", lambda: dense.vectors(self.units(level), e, self.idf(e, level)))

    def occurrences(self) -> DataFrame:
        return self._put("occurrences", lambda: structure.occurrences(self.units(), store.few))

    def references(self) -> DataFrame:
        return self._put("references", lambda: structure.references(self.occurrences()))

    def edges(self) -> DataFrame:
        return self._put("edges", lambda: structure.edges_of(self.references()), by=["etype", "src"])

    def views(self, e: dense.Encoder | None = dense.ENCODERS[2], edges: bool = False, level: int = 2, texts: bool = True) -> Views:
        """Handles for ranked plans; what a plan does not need is not built.

        texts=False: for plans that return ids and scores; the texts are counted as they are cut, and no copy of them is stored.
        """
        u = self.units(level) if texts else self.cut(level)
        v = Views(u, lexical=self.lexical(level, u))
        if e is not None:
            v.vectors, v.encoder, v.idf = self.vectors(e, level), e, self.idf(e, level)
        if edges:
            v.edges = self.edges()
        return v
