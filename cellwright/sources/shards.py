"""Training shards through Spark's Python data source interface: a folder of pairs, one partition a file, read in batches.

    spark.dataSource.register(ShardSource)
    spark.read.format("training_shards").option("path", folder).option("objective", "span").load()
"""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "batch_id long, variant string, source string, target string"


class ShardFile(InputPartition):
    def __init__(self, path: str):
        self.path = path


class ShardSource(DataSource):
    """Files written by tables.write_shards. Options: path; objective, to read one objective's folder alone."""

    @classmethod
    def name(cls) -> str:
        return "training_shards"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> ShardReader:
        return ShardReader(self.options)


class ShardReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.objective = options["path"], options.get("objective")

    def partitions(self) -> list[ShardFile]:
        from pyarrow import fs

        store, at = fs.FileSystem.from_uri(self.path)
        folder = f"{at}/objective={self.objective}" if self.objective else at
        found = store.get_file_info(fs.FileSelector(folder, recursive=True, allow_not_found=True))
        files = sorted(f.path for f in found if f.path.endswith(".parquet") and f.size)
        return [ShardFile(f) for f in files] or [ShardFile("")]

    def read(self, partition: ShardFile):
        """Record batches of one file; only the four columns are read."""
        import pyarrow.parquet as pq
        from pyarrow import fs

        if partition.path:
            store, _ = fs.FileSystem.from_uri(self.path)
            with store.open_input_file(partition.path) as f:
                for batch in pq.ParquetFile(f).iter_batches(4096, columns=["batch_id", "variant", "source", "target"]):
                    yield batch
