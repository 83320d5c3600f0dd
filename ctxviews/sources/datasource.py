"""Stored views as a Spark data source: format "ctxview", options location and view."""

from __future__ import annotations

import json
from pathlib import Path

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition


class ViewDataSource(DataSource):
    """Reads the Parquet files of one view; an equality on `version` or `level` prunes directories."""

    @classmethod
    def name(cls) -> str:
        return "ctxview"

    def schema(self) -> str:
        return json.loads((Path(self.options["location"]) / "_view.json").read_text())["schema"]

    def reader(self, schema) -> ViewReader:
        return ViewReader(self.options["location"], [f.name for f in schema.fields])


class FilePart(InputPartition):
    def __init__(self, path: str, level: int):
        self.path, self.level = path, level


class ViewReader(DataSourceReader):
    def __init__(self, location: str, names: list[str]):
        self.location, self.names, self.level = location, names, None

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("level",):
                self.level = int(f.value)
            else:
                yield f

    def partitions(self):
        out = []
        for p in sorted(Path(self.location).glob("level=*/*.parquet")):
            level = int(p.parent.name.partition("=")[2])
            if self.level is None or level == self.level:
                out.append(FilePart(str(p), level))
        return out or [FilePart("", -1)]

    def read(self, part: FilePart):
        if not part.path:
            return
        import pyarrow as pa
        import pyarrow.parquet as pq

        for batch in pq.ParquetFile(part.path).iter_batches(columns=[n for n in self.names if n != "level"]):
            if "level" in self.names:
                at = self.names.index("level")
                batch = pa.RecordBatch.from_arrays([*batch.columns[:at], pa.array([part.level] * batch.num_rows, pa.int32()), *batch.columns[at:]], names=self.names)
            yield batch
