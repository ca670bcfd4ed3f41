"""A data source of prompt shards: a folder of JSON-lines files, one partition a file, on any file system that Arrow opens.

    spark.dataSource.register(PromptShards)
    spark.read.format("prompt_shards").load("file:///folder")
"""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class Shard(InputPartition):
    def __init__(self, path: str):
        self.path = path


class PromptShards(DataSource):
    @classmethod
    def name(cls) -> str:
        return "prompt_shards"

    def schema(self) -> str:
        return "shard string, line long, role string, content string"

    def reader(self, schema) -> ShardReader:
        return ShardReader(self.options["path"])


class ShardReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(self.path)
        files = system.get_file_info(fs.FileSelector(root))
        return [Shard(f.path) for f in files if f.is_file and not f.base_name.startswith(("_", "."))]

    def read(self, partition):
        import io
        import json

        from pyarrow import fs

        system, _ = fs.FileSystem.from_uri(self.path)
        with system.open_input_stream(partition.path) as raw:
            for n, line in enumerate(io.TextIOWrapper(raw, "utf-8")):
                for m in json.loads(line)["messages"] if line.strip() else []:
                    yield partition.path.rsplit("/", 1)[-1], n, m["role"], m["content"]
