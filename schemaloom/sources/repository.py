"""A data source that lists a folder of tables and opens the wanted ones alone."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class TableFile(InputPartition):
    def __init__(self, table_id: str, uri: str):
        super().__init__(uri)
        self.table_id, self.uri = table_id, uri


class TableReader(DataSourceReader):
    """One partition for each file of the tables asked for; a file is read in batches."""

    def __init__(self, options):
        self.root, wanted = options["path"], options.get("tables", "")
        self.wanted = set(wanted.split(",")) if wanted else None

    def partitions(self) -> list[TableFile]:
        from pyarrow import fs

        system, root = fs.FileSystem.from_uri(self.root)
        scheme = self.root[: len(self.root) - len(root)]
        found = []
        for folder in system.get_file_info(fs.FileSelector(root)):
            key, _, table_id = folder.base_name.partition("=")
            if key != "table_id" or self.wanted is not None and table_id not in self.wanted:
                continue
            found += [TableFile(table_id, scheme + x.path) for x in system.get_file_info(fs.FileSelector(folder.path)) if x.base_name.endswith(".parquet")]
        return found

    def read(self, partition: TableFile) -> Iterator[pa.RecordBatch]:
        import pyarrow.parquet as pq
        from pyarrow import fs

        system, path = fs.FileSystem.from_uri(partition.uri)
        with system.open_input_file(path) as source:
            for batch in pq.ParquetFile(source).iter_batches(columns=["header", "value"]):
                ids = pa.array([partition.table_id] * batch.num_rows, pa.string())
                yield pa.RecordBatch.from_arrays([ids, batch.column("header").cast(pa.string()), batch.column("value").cast(pa.string())], ["table_id", "header", "value"])


class TableRepository(DataSource):
    """Options: path, a folder of table_id=<name> folders in the shared store; tables, the wanted names with commas."""

    @classmethod
    def name(cls) -> str:
        return "table_repository"

    def schema(self) -> str:
        return "table_id string, header string, value string"

    def reader(self, schema) -> TableReader:
        return TableReader(self.options)


def write(cells: DataFrame, path: str) -> None:
    """cells: (table_id, header, value)."""
    cells.write.partitionBy("table_id").parquet(path)


def read(spark: SparkSession, path: str, tables: list[str] | None = None) -> DataFrame:
    spark.dataSource.register(TableRepository)
    held = spark.read.format("table_repository").option("path", path)
    return (held.option("tables", ",".join(tables)) if tables else held).load()
