"""A folder of JSON grid files as a Spark data source: one partition for each file, batch or stream alike in form.

Each line of a file is {"table_id": ..., "family": ..., "grid": [[...], ...]}. The folder may lie in any store that pyarrow reads.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "table_id string, family string, grid array<array<string>>"


class GridFile(InputPartition):
    def __init__(self, path: str):
        self.path = path


class GridReader(DataSourceReader):
    def __init__(self, folder: str):
        self.folder = folder

    def _store(self):
        from pyarrow import fs

        folder = self.folder.replace("file:///", "/", 1).replace("file:/", "/", 1)
        return (fs.LocalFileSystem(), folder) if folder.startswith("/") else fs.FileSystem.from_uri(folder)

    def partitions(self) -> list[GridFile]:
        from pyarrow import fs

        where, base = self._store()
        return [GridFile(f.path) for f in sorted(where.get_file_info(fs.FileSelector(base)), key=lambda f: f.path) if f.is_file and f.base_name.endswith(".json")]

    def read(self, partition: GridFile) -> Iterator[tuple]:
        where, _ = self._store()
        with where.open_input_stream(partition.path) as lines:
            for line in lines.read().decode().splitlines():
                if line.strip():
                    row = json.loads(line)
                    yield row["table_id"], row.get("family"), row["grid"]


class GridSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "tabqa_grids"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> GridReader:
        return GridReader(self.options["path"])


def read_grids(spark: SparkSession, folder: str) -> DataFrame:
    spark.dataSource.register(GridSource)
    return spark.read.format("tabqa_grids").load(folder)
