"""Spark data source "gamat_coordinate": coordinate matrix files, split by file; register with spark.dataSource.register."""

from __future__ import annotations

import glob
import os

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class CoordinateSource(DataSource):
    """Option path: a file or a glob on a file system that every executor mounts."""

    @classmethod
    def name(cls) -> str:
        return "gamat_coordinate"

    def schema(self) -> str:
        return "dst bigint, src bigint, w double"

    def reader(self, schema) -> DataSourceReader:
        return CoordinateReader(self.options["path"])


class CoordinateReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        names = sorted(glob.glob(self.path)) or [self.path]
        return [InputPartition(n) for n in names if os.path.isfile(n)]

    def read(self, partition):
        sized = False
        with open(partition.value) as lines:
            for line in lines:
                if line.startswith("%") or not line.strip():
                    continue
                if not sized:
                    sized = True
                    continue
                a, b, w = line.split()[:3]
                yield int(a) - 1, int(b) - 1, float(w)
