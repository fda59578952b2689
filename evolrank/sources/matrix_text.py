"""A data source for text lists of matrix entries."""

from __future__ import annotations

import glob
import os

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class MatrixText(DataSource):
    """Lines 'row column' are edges; '%' comments and the size line of three numbers are skipped.

    ``path`` is a file or a folder of files that all machines share; each file is one partition.
    """

    @classmethod
    def name(cls) -> str:
        return "matrix_text"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema):
        return MatrixReader(self.options["path"])


class MatrixReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path.removeprefix("file:")

    def partitions(self):
        files = sorted(glob.glob(f"{self.path}/part-*")) if os.path.isdir(self.path) else [self.path]
        return [InputPartition(f) for f in files]

    def read(self, partition):
        with open(partition.value) as lines:
            for line in lines:
                entry = line.split()
                if len(entry) == 2 and not line.startswith("%"):
                    yield int(entry[0]), int(entry[1])
