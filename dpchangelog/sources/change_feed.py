"""A Spark data source for change feeds: JSON lines of mutations, a partition a file.

    spark.dataSource.register(ChangeFeed)
    spark.read.format("change_feed").option("path", folder).load()

For folders of any store that pyarrow opens by its address (file, hdfs, s3, gs); others go through Spark's json reader with
SCHEMA. A folder without a scheme must be one that every executor sees.
"""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "entry long, ts long, seq long, kind string, before string, after string"


class FeedFile(InputPartition):
    def __init__(self, path: str):
        self.path = path


def _open(path: str):
    """(file system, path there)."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


class FeedReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        from pyarrow import fs

        store, at = _open(self.path)
        return [FeedFile(f.path) for f in sorted(store.get_file_info(fs.FileSelector(at)), key=lambda f: f.path) if f.path.endswith((".json", ".jsonl"))]

    def read(self, partition):
        import io

        store, _ = _open(self.path)
        with store.open_input_stream(partition.path) as f:
            for line in io.TextIOWrapper(f, encoding="utf-8"):
                if line.strip():
                    m = json.loads(line)
                    yield m["entry"], m["ts"], m.get("seq", 0), m.get("kind"), m.get("before"), m.get("after")


class ChangeFeed(DataSource):
    @classmethod
    def name(cls):
        return "change_feed"

    def schema(self):
        return SCHEMA

    def reader(self, schema):
        return FeedReader(self.options["path"])
