"""A Python data source of served resources: NDJSON files of flat records, a partition for each file.

``spark.dataSource.register(BundleSource)``; then ``spark.read.format("bundle").option("files", "a,b").load()``.
Files are opened where a task runs, by path or URI of a file system that Arrow knows, so their folder has to be shared.
"""

from __future__ import annotations

import io
import json
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.files = [x for x in options.get("files", "").split(",") if x]

    def partitions(self) -> list[_File]:
        return [_File(f) for f in self.files]

    def read(self, partition: _File) -> Iterator[tuple]:
        from pyarrow import fs

        system, path = fs.FileSystem.from_uri(partition.path)
        with io.TextIOWrapper(system.open_input_stream(path), encoding="utf-8") as f:
            for line in f:
                r = json.loads(line)
                yield r["kind"], r["id"], json.dumps(r.get("body"), separators=(",", ":"), ensure_ascii=False)


class BundleSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "bundle"

    def schema(self) -> str:
        return "kind string, id string, body string"

    def reader(self, schema) -> _Reader:
        return _Reader(self.options)
