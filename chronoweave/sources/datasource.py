"""A Python data source ``temporal_edges``: Parquet edges laid out by label class and month, pruned by label and time.

    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(TemporalEdges)
    spark.read.format("temporal_edges").option("path", p).load().filter("p = 'link' AND ts < '2024-02-01'")
"""

from __future__ import annotations

import os
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition, LessThan, LessThanOrEqual

SCHEMA = "s string, p string, o string, ts timestamp_ntz, te timestamp_ntz"


class _File(InputPartition):
    def __init__(self, path: str, label: str | None, before: object) -> None:
        self.path, self.label, self.before = path, label, before


class _Reader(DataSourceReader):
    def __init__(self, options) -> None:
        self.path = options["path"]
        self.label, self.before = None, None

    def pushFilters(self, filters) -> Iterator:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("p",) and self.label is None:
                self.label = f.value
            elif isinstance(f, LessThan | LessThanOrEqual) and f.attribute == ("ts",):
                self.before = f.value if self.before is None else min(self.before, f.value)
                yield f  # used to skip files; Spark still tests the rows
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        out = []
        for folder, _, names in os.walk(self.path):
            month = next((x.split("=")[1] for x in folder.split("/") if x.startswith("month=")), None)
            if month and self.before is not None and month > f"{self.before:%Y-%m}":
                continue
            out += [_File(os.path.join(folder, n), self.label, self.before) for n in sorted(names) if n.endswith(".parquet")]
        return out

    def read(self, part: _File) -> Iterator:
        import pyarrow.parquet as pq

        where = [("p", "=", part.label)] if part.label is not None else None
        table = pq.ParquetFile(part.path).read(columns=["s", "p", "o", "ts", "te"]) if where is None else pq.read_table(part.path, columns=["s", "p", "o", "ts", "te"], filters=where, partitioning=None)
        yield from table.to_batches()


class TemporalEdges(DataSource):
    @classmethod
    def name(cls) -> str:
        return "temporal_edges"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
