"""A data source of triples in text files (one ``s<TAB>p<TAB>o`` a line), with the labels
pushed down: ``spark.read.format("triples").option("path", ...).load().filter("p = 'a'")``."""

from __future__ import annotations

import glob
import os

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, path: str):
        self.path, self.labels = path, None

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("p",):
                self.labels = (self.labels or {f.value}) & {f.value}
            elif isinstance(f, In) and f.attribute == ("p",):
                self.labels = (self.labels or set(f.value)) & set(f.value)
            else:
                yield f

    def partitions(self):
        files = sorted(glob.glob(os.path.join(self.path, "*"))) if os.path.isdir(self.path) else [self.path]
        return [_File(f) for f in files if not os.path.basename(f).startswith(("_", "."))]

    def read(self, partition):
        with open(partition.path, encoding="utf-8") as f:
            for line in f:
                parts = tuple(line.rstrip("\n").split("\t"))
                if len(parts) == 3 and (self.labels is None or parts[1] in self.labels):
                    yield parts


class TripleSource(DataSource):
    """Reads files that the executors can open by path; other stores go through ``io.read_triples``."""

    @classmethod
    def name(cls) -> str:
        return "triples"

    def schema(self) -> str:
        return "s string, p string, o string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options["path"])


def register(spark) -> None:
    """Registers the format ``triples``; labels are pushed down only with the session's setting on."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(TripleSource)
