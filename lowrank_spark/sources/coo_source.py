"""A Python data source `coo_text`: files of 'i<tab>j<tab>r' lines as (i, j, r), one partition a file.

Options: paths (newline-separated). Files must be readable where tasks run; broken lines fail the read unless
mode=drop.
"""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class CooPartition(InputPartition):
    def __init__(self, path: str):
        self.path = path


class CooReader(DataSourceReader):
    def __init__(self, options: dict):
        self.paths = [p for p in options.get("paths", "").split("\n") if p]
        self.drop = options.get("mode", "fail") == "drop"

    def partitions(self):
        return [CooPartition(p) for p in self.paths]

    def read(self, partition):
        from urllib.parse import unquote, urlparse

        u = urlparse(partition.path)
        with open(unquote(u.path) if u.scheme else partition.path, encoding="utf-8") as f:
            for line in f:
                parts = line.rstrip("\n").split("\t")
                try:
                    i, j, r = parts
                    yield int(i), int(j), float(r)
                except ValueError:
                    if not self.drop:
                        raise


class CooSource(DataSource):
    @classmethod
    def name(cls):
        return "coo_text"

    def schema(self):
        return "i bigint, j bigint, r double"

    def reader(self, schema):
        return CooReader(dict(self.options))


def register(spark) -> None:
    from lowrank_spark.runtime import ship_package

    ship_package(spark)
    spark.dataSource.register(CooSource)
